"""Trees, and the array arithmetic of a layer that the driver holds."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators import histogram


@dataclass
class Node:
    node: int
    count: int
    g: list[float]
    h: list[float]
    fid: int | None = None
    bin: int | None = None
    gain: float = 0.0


@dataclass
class Tree:
    tree: int
    class_id: int
    nodes: dict[int, Node] = field(default_factory=dict)

    def weight(self, node: int, reg_lambda: float) -> list[float]:
        n = self.nodes[node]
        return [-g / (h + reg_lambda) for g, h in zip(n.g, n.h)]

    def leaf_column(self, value: Callable[[int], Column], bins: str = "bins") -> Column:
        """What `value` gives for a row's leaf: one nested CASE, a comparison for each layer."""

        def at(node: int) -> Column:
            n = self.nodes[node]
            if n.fid is None:
                return value(node)
            return F.when(F.get(bins, F.lit(n.fid)) <= n.bin, at(2 * node + 1)).otherwise(at(2 * node + 2))

        return at(0)

    def node_column(self, bins: str = "bins") -> Column:
        """The leaf, or deepest grown node, of a row."""
        return self.leaf_column(F.lit, bins)

    def walk(self, x: np.ndarray) -> np.ndarray:
        """The leaf of each row of a bin matrix."""
        return self.walker()(x)

    def walker(self) -> Callable[[np.ndarray], np.ndarray]:
        """The same as a function that carries the splits alone: one step for each layer."""
        top = max(self.nodes, default=0) + 1
        fid, cut = np.full(top, -1, dtype=np.int64), np.zeros(top, dtype=np.int64)
        for i, n in self.nodes.items():
            if n.fid is not None:
                fid[i], cut[i] = n.fid, n.bin
        depth = top.bit_length()

        def run(x: np.ndarray) -> np.ndarray:
            node = np.zeros(len(x), dtype=np.int64)
            live, flat, n = None, np.ascontiguousarray(x).reshape(-1), x.shape[1]
            start = np.arange(len(x)) * n
            for _ in range(depth):
                inner = fid[node if live is None else node[live]] >= 0
                if not inner.all():
                    live = np.flatnonzero(inner) if live is None else live[inner]
                    if not len(live):
                        break
                at, first = (node, start) if live is None else (node[live], start[live])
                step = 2 * at + 1 + (flat.take(first + fid.take(at)) > cut.take(at))
                if live is None:
                    node = step
                else:
                    node[live] = step
            return node

        return run


def grid(cells: pa.Table, bins: int, features: int, classes: int) -> dict[int, np.ndarray]:
    """For each node an integer array [feature, bin, field]: count, then high and low limbs of each sum."""
    names = ["cnt", *[f"{n}{j}_{p}" for n in ("g", "h") for j in range(classes) for p in ("hi", "lo")]]
    node, fid, b = (cells.column(c).to_numpy() for c in ("node", "fid", "bin"))
    values = np.column_stack([cells.column(c).to_numpy() for c in names]).astype(np.int64)
    width = max(bins, 64)  # bins by plain arithmetic may number more than the quantiles'
    out = {}
    for n in np.unique(node):
        here = node == n
        table = np.zeros((features, width, len(names)), dtype=np.int64)
        table[fid[here], b[here]] = values[here]
        out[int(n)] = table
    return out


def _real(limbs: np.ndarray, r: int) -> np.ndarray:
    """Doubles nearest to high * 2^32 + low at r fractional bits, of the last axis' pairs."""
    return (limbs[..., 0::2].astype(np.float64) * 2.0**32 + limbs[..., 1::2]) / 2.0**r


def gain_of(g_l: np.ndarray, h_l: np.ndarray, g_t: np.ndarray, h_t: np.ndarray, reg_lambda: float) -> np.ndarray:
    """Half of what the children's scores add to the parent's; the last axis holds the classes."""
    score = lambda g, h: (g * g / (h + reg_lambda)).sum(axis=-1)
    return 0.5 * (score(g_l, h_l) + score(g_t - g_l, h_t - h_l) - score(g_t, h_t))


def best_local(cells: dict[int, np.ndarray], r: int, reg_lambda: float, classes: int, min_child_rows: int, allowed: set[int] | None = None) -> list[dict]:
    """The best split of each node: largest gain, then smallest fid, then smallest bin. Sums are exact integers."""
    out = []
    for node, table in cells.items():
        left = table.cumsum(axis=1)
        total = left[:, -1:, :]
        n_l, n_t = left[..., 0], total[..., 0]
        g_l, h_l = _real(left[..., 1 : 1 + 2 * classes], r), _real(left[..., 1 + 2 * classes :], r)
        g_t, h_t = _real(total[..., 1 : 1 + 2 * classes], r), _real(total[..., 1 + 2 * classes :], r)
        gain = gain_of(g_l, h_l, g_t, h_t, reg_lambda)
        seen = table[..., 0] > 0  # a cell that no row is in repeats the candidate before it
        ok = seen & (n_l >= min_child_rows) & (n_t - n_l >= min_child_rows)
        if allowed is not None:
            ok &= np.isin(np.arange(len(ok)), list(allowed))[:, None]
        if not ok.any():
            continue
        gain = np.where(ok, gain, -np.inf)
        fid, b = np.unravel_index(int(np.argmax(gain)), gain.shape)
        row = {"node": node, "fid": int(fid), "bin": int(b), "gain": float(gain[fid, b]), "cnt_l": int(n_l[fid, b]), "cnt_t": int(n_t[fid, 0])}
        whole = lambda x, k: int(x[k]) * 2**32 + int(x[k + 1])
        for side, x in (("l", left[fid, b]), ("t", total[fid, 0])):
            for j in range(classes):
                row[f"g{j}_{side}"], row[f"h{j}_{side}"] = whole(x, 1 + 2 * j), whole(x, 1 + 2 * classes + 2 * j)
        out.append(row)
    return out


def best_in_blocks(cells: DataFrame, r: int, reg_lambda: float, classes: int, min_child_rows: int, bins: int, block: int = 64) -> list[dict]:
    """The best split of each node where a layer's cells are too many for the driver: each block of features by itself.

    A block's cells meet in one task (nodes x block x bins of them, whatever the rows); its best rows come back.
    """
    names = [f"{n}{j}_{s}" for s in ("l", "t") for n in ("g", "h") for j in range(classes)]
    schema = "node int, fid int, bin int, gain double, cnt_l long, cnt_t long, sums array<string>"

    def run(key: tuple, f: pd.DataFrame) -> pd.DataFrame:
        first = int(key[0]) * block
        f = f.assign(fid=f["fid"] - first).drop(columns="block")
        found = best_local(grid(pa.Table.from_pandas(f, preserve_index=False), bins, block, classes), r, reg_lambda, classes, min_child_rows)
        rows = [(x["node"], x["fid"] + first, x["bin"], x["gain"], x["cnt_l"], x["cnt_t"], [str(x[n]) for n in names]) for x in found]
        return pd.DataFrame(rows, columns=["node", "fid", "bin", "gain", "cnt_l", "cnt_t", "sums"])

    each = cells.withColumn("block", F.floor(F.col("fid") / block)).groupBy("block").applyInPandas(run, schema)
    return _first_of_blocks(each, names)


def best_of_messages(messages: DataFrame, allowed: list[set[int] | None], slots: int, features: int, width: int, r: int, reg_lambda: float, classes: int, min_child_rows: int) -> list[dict]:
    """The best split of each slot, as `node`, from packed cells too many for the driver: a block's come in a row to one task.

    allowed: the features that a slot may split on.
    """
    names = [f"{n}{j}_{s}" for s in ("l", "t") for n in ("g", "h") for j in range(classes)]
    fields, block = 1 + 4 * classes, histogram.BLOCK

    def best(b: int, table: np.ndarray) -> pa.RecordBatch:
        shaped, first, rows = table.reshape(slots, block, width, fields), b * block, []
        shaped = shaped[:, : features - first]
        for s in np.flatnonzero(shaped[..., 0].any(axis=(1, 2))):
            mine = None if allowed[s] is None else {j - first for j in allowed[s]}
            for x in best_local({int(s): shaped[s]}, r, reg_lambda, classes, min_child_rows, mine):
                rows.append((x["node"], x["fid"] + first, x["bin"], x["gain"], x["cnt_l"], x["cnt_t"], [str(x[n]) for n in names]))
        kinds = [pa.int32(), pa.int32(), pa.int32(), pa.float64(), pa.int64(), pa.int64(), pa.list_(pa.string())]
        columns = list(zip(*rows)) or [()] * len(kinds)
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds)], names=["node", "fid", "bin", "gain", "cnt_l", "cnt_t", "sums"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, table = None, None
        for batch in batches:
            for b, at, sums in zip(*(batch.column(c).to_pylist() for c in ("block", "at", "sums"))):
                if b != now:
                    if now is not None:
                        yield best(now, table)
                    now, table = b, np.zeros((slots * block * width, fields), np.int64)
                histogram._add(table, *histogram.open_message(at, sums, fields))
        if now is not None:
            yield best(now, table)

    each = messages.repartition("block").sortWithinPartitions("block").mapInArrow(run, "node int, fid int, bin int, gain double, cnt_l long, cnt_t long, sums array<string>")
    return _first_of_blocks(each, names)


def _first_of_blocks(each: DataFrame, names: list[str]) -> list[dict]:
    best: dict[int, dict] = {}
    for row in each.collect():  # a row for each node and block
        x = row.asDict()
        x |= {n: int(v) for n, v in zip(names, x.pop("sums"))}
        held = best.get(x["node"])
        if held is None or (-x["gain"], x["fid"], x["bin"]) < (-held["gain"], held["fid"], held["bin"]):
            best[x["node"]] = x
    return list(best.values())
