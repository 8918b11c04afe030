"""Histograms of gradient sums, prefix sums, subtraction, and best splits.

Cells are (node, fid, bin) with exact fixed-point sums. Rows are expanded to one for each feature inside a task and
summed there first, so what is shuffled is cells, not rows; a bin that holds most rows is one cell of each task.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import codec, splits
from . import chunks, sampling


def fixed_columns(df: DataFrame, r: int, classes: int = 1, rounding: str = "floor") -> DataFrame:
    """Adds the high and low limbs of g and h, one pair for each class."""
    out = []
    for name in ("g", "h"):
        for j in range(classes):
            high, low = codec.limbs(F.get(name, F.lit(j)) if classes > 1 else F.col(name), r, rounding)
            out += [high.alias(f"{name}{j}_hi"), low.alias(f"{name}{j}_lo")]
    return df.select("*", *out)


def _sums(classes: int) -> list[Column]:
    return [F.sum(f"{n}{j}_{p}").alias(f"{n}{j}_{p}") for n in ("g", "h") for j in range(classes) for p in ("hi", "lo")]


def limb_cells(df: DataFrame, classes: int = 1, first: int = 0, count: int | None = None) -> DataFrame:
    """node, fid, bin, cnt and the summed limbs."""
    bins = F.col("bins") if count is None else F.slice("bins", first + 1, count)
    names = [f"{n}{j}_{p}" for n in ("g", "h") for j in range(classes) for p in ("hi", "lo")]
    flat = df.select("node", F.posexplode(bins).alias("k", "bin"), *names)
    return flat.groupBy("node", (F.col("k") + first).alias("fid"), "bin").agg(F.count("*").alias("cnt"), *_sums(classes))


#: Entries of a task's table of sums at most, for each summed number; beyond, it is passed on batch by batch.
TABLE = 1 << 22
#: Entries (rows x features) that are counted at once.
AT_ONCE = 1 << 20


def _exact_bincount(at: np.ndarray, values: np.ndarray, size: int) -> np.ndarray:
    """Integer sums by cell. Doubles hold them exactly unless the values are very large."""
    if len(values) and float(np.abs(values).max()) * len(values) < 2.0**53:
        return np.bincount(at, weights=values, minlength=size).astype(np.int64)
    out = np.zeros(size, dtype=np.int64)
    np.add.at(out, at, values)
    return out


def arrow_cells(df: DataFrame, place: Callable[[np.ndarray], np.ndarray], nodes: list[int], classes: int = 1, spans: list[tuple[int, int]] | None = None, width: int = 64) -> DataFrame:
    """node, fid, bin, cnt and the summed limbs, from rows with bins and limbs: counted on Arrow batches.

    place: a bin matrix to each row's node; nodes: those to build; spans: first and last + 1 of the features to build.
    A row is never expanded: a task keeps one table of sums and sends its cells.
    """
    names = [f"{n}{j}_{p}" for n in ("g", "h") for j in range(classes) for p in ("hi", "lo")]
    slot_of = np.full(max(nodes, default=0) + 2, -1, dtype=np.int64)
    slot_of[nodes] = np.arange(len(nodes))
    schema = "node int, fid int, bin int, cnt long, " + ", ".join(f"{n} long" for n in names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table: list[np.ndarray] | None = None
        fids = np.zeros(0, np.int64)

        def cells() -> pa.RecordBatch:
            some = np.flatnonzero(table[0])
            slot, rest = np.divmod(some, len(fids) * width)
            fid, b = np.divmod(rest, width)
            columns = [np.array(nodes, np.int32)[slot], fids[fid].astype(np.int32), b.astype(np.int32), *[t[some] for t in table]]
            return pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["node", "fid", "bin", "cnt", *names])

        for batch in batches:
            n = batch.num_rows
            if not n:
                continue
            x = batch.column("bins").values.to_numpy(zero_copy_only=False).reshape(n, -1)
            fids = np.concatenate([np.arange(a, b) for a, b in spans]) if spans is not None else np.arange(x.shape[1])
            node = place(x)
            slot = np.where((node >= 0) & (node < len(slot_of)), slot_of[np.clip(node, 0, len(slot_of) - 1)], -1)
            size = len(nodes) * len(fids) * width
            if table is None:
                table = [np.zeros(size, np.int64) for _ in range(1 + len(names))]
            live = np.flatnonzero(slot >= 0)
            limbs = [batch.column(c).to_numpy(zero_copy_only=False) for c in names]
            step = max(1, AT_ONCE // max(1, len(fids)))
            for lo in range(0, len(live), step):
                rows = live[lo : lo + step]
                at = ((slot[rows, None] * len(fids) + np.arange(len(fids))) * width + x[rows[:, None], fids]).ravel()
                table[0] += np.bincount(at, minlength=size)
                for t, v in zip(table[1:], limbs):
                    t += _exact_bincount(at, np.repeat(v[rows], len(fids)), size)
            if size > TABLE:
                yield cells()
                table = None
        if table is not None:
            yield cells()

    flat = df.select("bins", *names).mapInArrow(run, schema)
    return flat.groupBy("node", "fid", "bin").agg(F.sum("cnt").alias("cnt"), *_sums(classes))


#: Features of a message: a block's table of sums is what a task holds at least.
BLOCK = 64
#: Rows that a task counts at once, and entries of the tables that it holds until its last row.
ROWS_AT_ONCE = 1 << 15
HELD = 1 << 24


def _limbs(x: np.ndarray, r: int, rounding: str) -> tuple[np.ndarray, np.ndarray]:
    """`codec.limbs` on arrays: the same integers, and the same error."""
    if rounding == "round":
        x = x + 0.5 / 2.0**r
    scaled = x * 2.0 ** (r - 32)
    if not (np.abs(scaled) < float(1 << codec.HIGH_BITS)).all():
        raise OverflowError("a gradient or hessian exceeds the fixed-point range")
    high = np.floor(scaled)
    return high.astype(np.int64), np.floor((scaled - high) * float(codec.LIMB)).astype(np.int64)


def _add(table: np.ndarray, at: np.ndarray | slice, more: np.ndarray) -> None:
    """table[at] += more for distinct places; integers that could leave 64 bits raise."""
    total = table[at] + more
    if total.size and max(int(total.max()), -int(total.min())) >= 1 << 62:
        raise OverflowError("a sum of limbs exceeds 62 bits")
    table[at] = total


def _spread_counts(slot: np.ndarray, x: np.ndarray, values: list[np.ndarray], n_nodes: int, width: int) -> Iterator[tuple[int, np.ndarray]]:
    """For each column of x the counts and exact sums by (node, bin): small tables, and no row is repeated."""
    top = [float(np.abs(v).max()) * len(v) < 2.0**53 for v in values]
    real = [v.astype(np.float64) if t else v for v, t in zip(values, top)]
    base, turned = slot * width, np.ascontiguousarray(x.T)
    for j in range(x.shape[1]):
        at = base + turned[j]
        out = [np.bincount(at, minlength=n_nodes * width)]
        for v, t in zip(real, top):
            out.append(np.bincount(at, weights=v, minlength=n_nodes * width).astype(np.int64) if t else _exact_bincount(at, v, n_nodes * width))
        yield j, np.stack(out)


#: Rows from which sums are taken feature by feature; fewer are cheaper by whole blocks.
MANY = 1 << 9


def totals(df: DataFrame, edges: list[list[float]], draw: sampling.Draw, k: int, trees: int, classes: int, r: int, rounding: str) -> tuple[int, list[int]]:
    """Count, and exact sums of g and h by class, of a tree's whole sample. df: chunks of gradients."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, sums = 0, [0] * (2 * classes)
        for c in chunks.each(batches, edges):
            amp = draw.amounts(c["key"], sampling.sizes_of(c["g"], trees)[:, k])
            live = np.flatnonzero(amp > 0)
            n += len(live)
            for i, (t, j) in enumerate([(t, j) for t in ("g", "h") for j in range(classes)]):
                high, low = _limbs(c[t][live, k * classes + j] * amp[live], r, rounding)
                sums[i] += int(high.sum()) * 2**32 + int(low.sum())
        yield pa.RecordBatch.from_arrays([pa.array([n]), pa.array([[str(s) for s in sums]], pa.list_(pa.string()))], names=["n", "sums"])

    found = df.mapInArrow(run, "n long, sums array<string>").collect()  # a row of each task
    return sum(x["n"] for x in found), [sum(int(x["sums"][i]) for x in found) for i in range(2 * classes)]


def cell_messages(df: DataFrame, draws: list[sampling.Draw], edges: list[list[float]], asked: list[tuple[int, Callable[[np.ndarray], np.ndarray], list[int], list[tuple[int, int]]]], classes: int, width: int, r: int, rounding: str = "floor") -> DataFrame:
    """block, at, sums: for each block of features the cells that have rows, and their count and summed limbs, packed.

    df: chunks of gradients, `classes` numbers of each tree. draws: the samples of all trees of the epoch.
    asked: number of a tree, a bin matrix to each row's node, the nodes to build, the spans of features to build. A cell
    is (slot * BLOCK + feature in its block) * width + bin; slots number the nodes of all asked trees in order.
    A task sends a block's cells once, or once in ROWS_AT_ONCE rows where all its tables are more than it may hold.
    """
    features, fields = len(edges), 1 + 4 * classes
    slots = sum(len(a[2]) for a in asked)
    hold = slots * features * width * fields <= HELD

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, np.ndarray] = {}

        def packed(tables: Iterator[tuple[int, np.ndarray]]) -> Iterator[pa.RecordBatch]:
            rows, size = [], 0
            for b, table in tables:
                at = np.flatnonzero(table[0]).astype(np.int32)
                if len(at):
                    rows.append((b, at.tobytes(), np.ascontiguousarray(table[:, at]).tobytes()))
                    size += len(rows[-1][2])
                if size > 1 << 22:
                    yield batch_of(rows)
                    rows, size = [], 0
            if rows:
                yield batch_of(rows)

        def batch_of(rows: list[tuple]) -> pa.RecordBatch:
            b, at, sums = zip(*rows)
            return pa.RecordBatch.from_arrays([pa.array(b, pa.int32()), pa.array(at, pa.binary()), pa.array(sums, pa.binary())], names=["block", "at", "sums"])

        def count(x: np.ndarray, g: np.ndarray, h: np.ndarray, amp: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
            seen, base = [], 0
            for k, place, nodes, spans in asked:
                slot_of = np.full(max(nodes) + 2, -1, dtype=np.int64)
                slot_of[nodes] = np.arange(len(nodes))
                node = place(x)
                slot = np.where(node < len(slot_of), slot_of[np.minimum(node, len(slot_of) - 1)], -1)
                live = (slot >= 0) & (amp[:, k] > 0)
                live = slice(None) if live.all() else np.flatnonzero(live)
                if len(slot[live]):
                    values = [v for t in (g, h) for j in range(classes) for v in _limbs(t[live, k * classes + j] * amp[live, k], r, rounding)]
                    seen.append((base, len(nodes), slot[live], x[live], values, spans))
                base += len(nodes)
            for first in range(0, features, BLOCK):
                b = first // BLOCK
                table = held.get(b)
                if table is None:
                    table = np.zeros((fields, slots * BLOCK * width), np.int64)
                for base, n_nodes, slot, mine, values, spans in seen:
                    part = slice(base * BLOCK * width, (base + n_nodes) * BLOCK * width)
                    size = n_nodes * BLOCK * width
                    for lo, hi in [(max(a, first), min(z, first + BLOCK)) for a, z in spans]:
                        if len(slot) >= MANY and lo < hi:
                            if any(float(np.abs(v).max()) * len(v) >= 2.0**62 for v in values):
                                raise OverflowError("a sum of limbs exceeds 62 bits")
                            shaped = table[:, part].reshape(fields, n_nodes, BLOCK, width)
                            for j, sums in _spread_counts(slot, mine[:, lo:hi], values, n_nodes, width):
                                _add(shaped, (slice(None), slice(None), lo - first + j), sums.reshape(fields, n_nodes, width))
                            continue
                        step = AT_ONCE // BLOCK
                        for i in range(0, len(slot) if lo < hi else 0, step):
                            at = ((slot[i : i + step, None] * BLOCK + np.arange(lo - first, hi - first)) * width + mine[i : i + step, lo:hi]).ravel()
                            table[0, part] += np.bincount(at, minlength=size)
                            for f, v in enumerate(values):
                                some = v[i : i + step]
                                if float(np.abs(some).max()) * len(at) >= 2.0**62:
                                    raise OverflowError("a sum of limbs exceeds 62 bits")
                                _add(table[f + 1], part, _exact_bincount(at, np.repeat(some, hi - lo), size))
                if hold:
                    held[b] = table
                else:
                    yield b, table

        waiting, rows = [], 0
        for c in chunks.each(batches, edges):
            sizes = sampling.sizes_of(c["g"], len(draws))
            amp = np.column_stack([d.amounts(c["key"], s) for d, s in zip(draws, sizes.T)])
            drawn = (amp > 0).any(axis=1)
            waiting.append(tuple(a if drawn.all() else a[drawn] for a in (c["x"], c["g"], c["h"], amp)))
            rows += len(waiting[-1][0])
            if rows >= ROWS_AT_ONCE:
                yield from packed(count(*map(np.concatenate, zip(*waiting))))
                waiting, rows = [], 0
        if waiting:
            yield from packed(count(*map(np.concatenate, zip(*waiting))))
        yield from packed(held.items())

    return df.mapInArrow(run, "block int, at binary, sums binary")


def open_message(at: bytes, sums: bytes, fields: int) -> tuple[np.ndarray, np.ndarray]:
    where = np.frombuffer(at, np.int32)
    return where, np.frombuffer(sums, np.int64).reshape(fields, len(where)).T


def add_messages(rows: pa.Table, slots: int, features: int, width: int, classes: int) -> dict[int, np.ndarray]:
    """The tables [feature, bin, field] of the slots that have rows, from messages that the driver took."""
    fields = 1 + 4 * classes
    blocks = -(-features // BLOCK)
    whole = np.zeros((blocks, slots * BLOCK * width, fields), np.int64)
    for b, at, sums in zip(*(rows.column(c).to_pylist() for c in ("block", "at", "sums"))):
        where, more = open_message(at, sums, fields)
        _add(whole[b], where, more)
    by_slot = whole.reshape(blocks, slots, BLOCK, width, fields).transpose(1, 0, 2, 3, 4).reshape(slots, blocks * BLOCK, width, fields)[:, :features]
    return {s: by_slot[s] for s in range(slots) if by_slot[s, ..., 0].any()}


def build(df: DataFrame, classes: int = 1, first: int = 0, count: int | None = None, default_bins: list[int] | None = None) -> DataFrame:
    """node, fid, bin, cnt, g0, h0, ... from rows with node, bins and limbs.

    first, count: the features to build, of one party. default_bins: with it, entries in a feature's default bin are
    skipped and that bin is restored as the node's total less its other bins.
    """
    bins = F.col("bins") if count is None else F.slice("bins", first + 1, count)
    names = [f"{n}{j}_{p}" for n in ("g", "h") for j in range(classes) for p in ("hi", "lo")]
    flat = df.select("node", F.posexplode(bins).alias("k", "bin"), *names).withColumn("fid", F.col("k") + first)
    if default_bins is not None:
        usual = F.array(*[F.lit(default_bins[first + i]) for i in range(count if count is not None else len(default_bins))])
        flat = flat.where(F.col("bin") != F.get(usual, F.col("k")))
    cells = flat.groupBy("node", "fid", "bin").agg(F.count("*").alias("cnt"), *_sums(classes))
    value = lambda n, j: codec.unlimb(F.col(f"{n}{j}_hi"), F.col(f"{n}{j}_lo")).alias(f"{n}{j}")
    cells = cells.select("node", "fid", "bin", "cnt", *[value(n, j) for n in ("g", "h") for j in range(classes)])
    if default_bins is None:
        return cells
    totals = df.groupBy("node").agg(F.count("*").alias("cnt"), *_sums(classes)).select("node", "cnt", *[value(n, j) for n in ("g", "h") for j in range(classes)])
    fields = ["cnt", *[f"{n}{j}" for n in ("g", "h") for j in range(classes)]]
    n_features = count if count is not None else len(default_bins)
    grid = totals.select("node", F.posexplode(F.array(*[F.lit(default_bins[first + i]) for i in range(n_features)])).alias("k", "bin"), *[F.col(c).alias(f"t_{c}") for c in fields])
    rest = cells.groupBy("node", "fid").agg(*[F.sum(c).alias(c) for c in fields])
    restored = grid.withColumn("fid", F.col("k") + first).join(rest, ["node", "fid"], "left")
    restored = restored.select("node", "fid", "bin", *[(F.col(f"t_{c}") - F.coalesce(c, F.lit(0))).cast("bigint" if c == "cnt" else "decimal(38,0)").alias(c) for c in fields]).where("cnt > 0")
    return cells.unionByName(restored)


def subtract(parent: DataFrame, small: DataFrame, sibling_of: dict[int, int], classes: int = 1) -> DataFrame:
    """Cells of the siblings: parent cells less those of the built child. sibling_of: built node -> its sibling."""
    fields = ["cnt", *[f"{n}{j}" for n in ("g", "h") for j in range(classes)]]
    up = F.create_map(*[F.lit(x) for s in sibling_of for x in (s, (s - 1) // 2)])
    over = F.create_map(*[F.lit(x) for s, o in sibling_of.items() for x in ((s - 1) // 2, o)])
    child = small.where(F.col("node").isin(*sibling_of)).select(up[F.col("node")].alias("node"), "fid", "bin", *[F.col(c).alias(f"s_{c}") for c in fields])
    joined = parent.where(F.col("node").isin(*{(s - 1) // 2 for s in sibling_of})).join(child, ["node", "fid", "bin"], "left")
    kept = [(F.col(c) - F.coalesce(f"s_{c}", F.lit(0))).cast("bigint" if c == "cnt" else "decimal(38,0)").alias(c) for c in fields]
    return joined.select(over[F.col("node")].alias("node"), "fid", "bin", *kept).where("cnt > 0")


def cumsum(cells: DataFrame, classes: int = 1) -> DataFrame:
    """Left sums of every bin and the node's totals: cnt_l, g0_l, ..., cnt_t, g0_t, ..."""
    feature = Window.partitionBy("node", "fid")
    upto = feature.orderBy("bin").rowsBetween(Window.unboundedPreceding, 0)
    fields = ["cnt", *[f"{n}{j}" for n in ("g", "h") for j in range(classes)]]
    return cells.select("node", "fid", "bin", *[F.sum(c).over(upto).alias(f"{c}_l") for c in fields], *[F.sum(c).over(feature).alias(f"{c}_t") for c in fields])


def candidates(cells: DataFrame, r: int, reg_lambda: float, classes: int = 1, min_child_rows: int = 1) -> DataFrame:
    """Adds gain to every bin that leaves rows on both sides."""
    left = cumsum(cells, classes).where((F.col("cnt_l") >= min_child_rows) & (F.col("cnt_t") - F.col("cnt_l") >= min_child_rows))
    if classes == 1:
        v = lambda c: codec.real(F.col(c), r)
        return left.withColumn("gain", splits.gain(v("g0_l"), v("h0_l"), v("g0_t"), v("h0_t"), reg_lambda))
    v = lambda n, s: F.array(*[codec.real(F.col(f"{n}{j}_{s}"), r) for j in range(classes)])
    return left.withColumn("gain", splits.gain_mo(v("g", "l"), v("h", "l"), v("g", "t"), v("h", "t"), reg_lambda))


def best(found: DataFrame) -> DataFrame:
    """One candidate for each node: largest gain, then smallest fid, then smallest bin."""
    order = F.struct(F.col("gain"), -F.col("fid"), -F.col("bin"))
    return found.groupBy("node").agg(F.max_by(F.struct(*found.columns), order).alias("x")).select("x.*")
