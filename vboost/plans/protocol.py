"""The federated exchange on ciphers: packed rows, cipher histograms, masked and compressed split infos.

Cipher sums have no built-in aggregate. A task folds its rows by (node, feature, bin) first and sends one cipher for
each cell; only these partial cells are shuffled, sorted, and folded again as they stream by. Python runs on Arrow or
pandas batches alone. Every frame carries how many cipher operations made its rows, so that a ledger is a sum over
what was kept and repeated tasks count once.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import codec
from ..functions.codec import Budget
from ..he.base import Backend
from ..sources.io import cut
from .params import guard


def lists_of(c: np.ndarray) -> pa.ListArray:
    """Arrays of as many ciphers a row, from bytes by [row, cipher, byte]."""
    n, each, width = c.shape
    flat = pa.Array.from_buffers(pa.binary(), n * each, [None, pa.py_buffer(np.arange(n * each + 1, dtype=np.int32) * width), pa.py_buffer(np.ascontiguousarray(c))])
    return pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * each), flat)


def matrix_of(column: pa.ListArray) -> np.ndarray:
    """The bytes of such arrays again."""
    flat, n = column.flatten(), len(column)
    ends = np.frombuffer(flat.buffers()[1], np.int32)[flat.offset : flat.offset + len(flat) + 1]
    data = np.frombuffer(flat.buffers()[2], np.uint8)[ends[0] : ends[-1]]
    if (np.diff(ends) != ends[1] - ends[0]).any():
        raise ValueError("ciphers of one kind differ in width")
    return data.reshape(n, len(flat) // n, -1)


def _encrypted(g: np.ndarray, h: np.ndarray, key: Backend, budget: Budget, packing: bool) -> np.ndarray:
    """Ciphers of the rows' gradients, a column for each class: one packed, two apart, or n_k for several classes."""
    classes, found = g.shape[1], codec.fields(g, h, budget)
    if found is not None:
        up, down = found
        if classes == 1 and not packing:
            return np.stack([key.encrypt_fields(x, [0]) for x in found], axis=1)
        out = []
        for first in range(0, classes, budget.slots):
            some = range(first, min(classes, first + budget.slots))
            shifts = [(some[-1] - j) * budget.b_gh + s for j in some for s in (budget.b_h, 0)]
            out.append(key.encrypt_fields(np.column_stack([x[:, j] for j in some for x in (up, down)]), shifts))
        return np.stack(out, axis=1)
    if classes > 1:
        plain = [codec.pack_mo(x.tolist(), y.tolist(), budget) for x, y in zip(g, h)]
    elif packing:
        plain = [[codec.pack(float(x), float(y), budget)] for x, y in zip(g[:, 0], h[:, 0])]
    else:
        plain = [codec.apart(float(x), float(y), budget) for x, y in zip(g[:, 0], h[:, 0])]
    return np.frombuffer(b"".join(key.encrypt(m) for row in plain for m in row), np.uint8).reshape(len(g), len(plain[0]), -1)


def encrypt_rows(df: DataFrame, key: Backend, budget: Budget, packing: bool = True, classes: int = 1) -> DataFrame:
    """inst_id, c array<binary>: one cipher packed, two apart, or n_k for a vector of classes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = batch.num_rows
            if not n:
                continue
            number = lambda c: (c.flatten() if classes > 1 else c).to_numpy(zero_copy_only=False).astype(np.float64).reshape(n, classes)
            c = _encrypted(number(batch.column("g")), number(batch.column("h")), key, budget, packing)
            yield pa.RecordBatch.from_arrays([batch.column("inst_id").cast(pa.int64()), lists_of(c)], names=["inst_id", "c"])

    # encryption is dear: dealt over all tasks, not over the few that a small file is read by
    rows = df.select("inst_id", "g", "h").repartition(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), "inst_id")
    out = rows.mapInArrow(run, "inst_id long, c array<binary>")
    guard("passive", "enc_gh", out.columns)
    return out


CELL = "node int, fid int, bin int, cnt long, c array<binary>, adds long, inversions long"
_NAMES = ["node", "fid", "bin", "cnt", "c", "adds", "inversions"]
#: In place of a feature, the sums of a whole node.
WHOLE = -1


def _fold_rows(public: Backend, block: int, default_bins: list[int] | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cells: dict[tuple[int, int, int], list] = {}

        def put(node: np.ndarray, names: np.ndarray, fid: int, bins: np.ndarray, c: np.ndarray) -> None:
            low, span = int(bins.min()), int(bins.max()) - int(bins.min()) + 1
            at = node * span + (bins - low)
            counts = np.bincount(at)
            made = [public.fold_by(at, c[:, i]) for i in range(c.shape[1])]
            for k in made[0]:
                key = (int(names[k // span]), fid, low + k % span)
                n, sums, held = int(counts[k]), [m[k] for m in made], cells.get(key)
                if held is None:
                    cells[key] = [n, sums]
                else:
                    held[0] += n
                    held[1] = [public.add(x, y) for x, y in zip(held[1], sums)]

        def flush() -> pa.RecordBatch:
            rows = [(*k, n, c, (n - 1) * len(c), 0) for k, (n, c) in cells.items()]
            cells.clear()
            kinds = [pa.int32(), pa.int32(), pa.int32(), pa.int64(), pa.list_(pa.binary()), pa.int64(), pa.int64()]
            return pa.RecordBatch.from_arrays([pa.array(x, kind) for x, kind in zip(zip(*rows), kinds)], names=_NAMES)

        for batch in batches:
            n = batch.num_rows
            if not n:
                continue
            names, node = np.unique(batch.column("node").to_numpy(zero_copy_only=False), return_inverse=True)
            bins = batch.column("bins").flatten().to_numpy(zero_copy_only=False).astype(np.int64).reshape(n, -1)
            c = matrix_of(batch.column("c"))
            for fid in range(bins.shape[1]):
                some = slice(None) if default_bins is None else np.flatnonzero(bins[:, fid] != default_bins[fid])
                if default_bins is None or len(some):
                    put(node[some], names, fid, bins[some, fid], c[some])
                if len(cells) > block:
                    yield flush()
            if default_bins is not None:
                put(node, names, WHOLE, np.zeros(n, np.int64), c)
        if cells:
            yield flush()

    return run


def _fold_sorted(public: Backend):
    """Folds neighbouring rows of one cell as they stream by."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: list | None = None
        for f in frames:
            out = []
            for row in f[_NAMES].itertuples(index=False):
                if held is not None and tuple(held[:3]) == row[:3]:
                    held[3] += row.cnt
                    held[4] = [public.add(x, y) for x, y in zip(held[4], row.c)]
                    held[5] += row.adds + len(row.c)
                else:
                    if held is not None:
                        out.append(held)
                    held = list(row)
            yield pd.DataFrame(out, columns=_NAMES)
        if held is not None:
            yield pd.DataFrame([held], columns=_NAMES)

    return run


def _restore(public: Backend, default_bins: list[int]):
    """The skipped bins of a node: its whole sums less its other bins, one group for each node."""

    def run(f: pd.DataFrame) -> pd.DataFrame:
        whole = f[f["fid"] == WHOLE].iloc[0]
        out = list(f.loc[f["fid"] != WHOLE, _NAMES].itertuples(index=False, name=None))
        by = dict(list(f[f["fid"] != WHOLE].groupby("fid")))
        for fid, b in enumerate(default_bins):
            others = by.get(fid)
            if others is None:
                out.append((whole["node"], fid, b, whole["cnt"], list(whole["c"]), whole["adds"] if fid == 0 else 0, 0))
                continue
            left = int(whole["cnt"] - others["cnt"].sum())
            if left <= 0:
                continue
            rest = [public.fold([c[i] for c in others["c"]]) for i in range(len(whole["c"]))]
            adds = (len(others) - 1) * len(rest) + (whole["adds"] if fid == 0 else 0)
            out.append((whole["node"], fid, b, left, public.sub_all(list(whole["c"]), rest), adds, len(rest)))
        return pd.DataFrame(out, columns=_NAMES)

    return run


def cipher_histogram(rows: DataFrame, public: Backend, default_bins: list[int] | None = None, block: int = 65_536) -> DataFrame:
    """Cells of a passive party from node, bins and c. The partial fold holds `block` cells.

    default_bins: with it, entries in a feature's default bin are skipped, and that bin is restored by homomorphic
    subtraction.
    """
    partial = rows.select(F.col("node").cast("int"), "bins", "c").mapInArrow(_fold_rows(public, block, default_bins), CELL)
    cells = partial.repartition("node", "fid", "bin").sortWithinPartitions("node", "fid", "bin").mapInPandas(_fold_sorted(public), CELL)
    return cells if default_bins is None else cells.groupBy("node").applyInPandas(_restore(public, default_bins), CELL)


def cipher_subtract(parent: DataFrame, small: DataFrame, sibling_of: dict[int, int], public: Backend) -> DataFrame:
    """Cells of the siblings of built children, by homomorphic subtraction. sibling_of: built node -> its sibling."""
    up = F.create_map(*[F.lit(x) for s in sibling_of for x in (s, (s - 1) // 2)])
    over = F.create_map(*[F.lit(x) for s, o in sibling_of.items() for x in ((s - 1) // 2, o)])
    child = small.where(F.col("node").isin(*sibling_of)).select(up[F.col("node")].alias("node"), "fid", "bin", F.col("cnt").alias("cnt2"), F.col("c").alias("c2"))
    above = parent.where(F.col("node").isin(*{(s - 1) // 2 for s in sibling_of})).select("node", "fid", "bin", "cnt", "c")
    joined = above.join(child, ["node", "fid", "bin"], "left").withColumn("node", over[F.col("node")])

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            out, pairs = [], []
            for node, fid, b, n, c, m, d in f[["node", "fid", "bin", "cnt", "c", "cnt2", "c2"]].itertuples(index=False):
                if d is None:
                    out.append([node, fid, b, n, list(c), 0, 0])
                elif n > m:
                    out.append([node, fid, b, int(n - m), None, 0, len(c)])
                    pairs.append((out[-1], list(c), list(d)))
            made = iter(public.sub_all([x for _, c, _ in pairs for x in c], [x for _, _, d in pairs for x in d]))
            for row, c, _ in pairs:
                row[4] = [next(made) for _ in c]
            yield pd.DataFrame(out, columns=_NAMES)

    return joined.mapInPandas(run, CELL)


INFO = "split_uid string, node int, fid int, bin int, sample_count long, c array<binary>, adds long"


def split_infos(cells: DataFrame, public: Backend, secret: str) -> DataFrame:
    """Prefix sums of each feature under opaque ids, in the order of a keyed digest. fid and bin stay with the party."""

    def run(f: pd.DataFrame) -> pd.DataFrame:
        f = f.sort_values("bin")
        acc, count, out = None, 0, []
        for node, fid, b, n, c in f[["node", "fid", "bin", "cnt", "c"]].itertuples(index=False):
            adds = 0 if acc is None else len(c)
            acc = list(c) if acc is None else [public.add(x, y) for x, y in zip(acc, c)]
            count += n
            out.append((node, fid, b, count, acc, adds))
        return pd.DataFrame(out[:-1], columns=["node", "fid", "bin", "sample_count", "c", "adds"])  # the last bin leaves no row right

    summed = cells.groupBy("node", "fid").applyInPandas(run, "node int, fid int, bin int, sample_count long, c array<binary>, adds long")
    uid = F.sha2(F.concat_ws("/", F.lit(secret), "node", "fid", "bin"), 256)
    return summed.select(uid.alias("split_uid"), "node", "fid", "bin", "sample_count", "c", "adds")


def compress_infos(infos: DataFrame, public: Backend, budget: Budget, classes: int = 1) -> DataFrame:
    """Packages of as many infos of a node as a cipher holds: pkg_id, node, members, c, shifts. For one-cipher infos."""
    order = F.row_number().over(Window.partitionBy("node").orderBy("split_uid"))
    numbered = infos.select("split_uid", "node", "sample_count", "c", F.floor((order - 1) / budget.members(classes)).cast("int").alias("k"))

    def run(f: pd.DataFrame) -> pd.DataFrame:
        f = f.sort_values("split_uid")
        acc = None
        for c in f["c"]:
            acc = c[0] if acc is None else public.add(public.shift(acc, classes * budget.b_gh), c[0])
        members = [{"split_uid": u, "sample_count": int(n)} for u, n in zip(f["split_uid"], f["sample_count"])]
        node, k = int(f["node"].iloc[0]), int(f["k"].iloc[0])
        return pd.DataFrame([(f"{node}/{k}", node, members, acc, len(f) - 1)], columns=["pkg_id", "node", "members", "c", "shifts"])

    return numbered.groupBy("node", "k").applyInPandas(run, "pkg_id string, node int, members array<struct<split_uid:string,sample_count:long>>, c binary, shifts long")


SUMS = "split_uid string, node int, sample_count long, g array<string>, h array<string>, dec long"


def open_packages(packages: DataFrame, key: Backend, budget: Budget, classes: int = 1) -> DataFrame:
    """The active party's side: one decryption a package. Sums are exact integers at r bits, as decimal strings."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            out = []
            for node, members, c in zip(f["node"], f["members"], f["c"]):
                opened = codec.decompress(key.decrypt(c), len(members), budget, classes)
                for i, (m, total) in enumerate(zip(members, opened)):
                    sums = codec.unpack_mo([total], m["sample_count"], classes, budget)
                    out.append((m["split_uid"], node, m["sample_count"], [str(g) for g, _ in sums], [str(h) for _, h in sums], int(i == 0)))
            yield pd.DataFrame(out, columns=["split_uid", "node", "sample_count", "g", "h", "dec"])

    return packages.mapInPandas(run, SUMS)


def open_infos(infos: DataFrame, key: Backend, budget: Budget, packing: bool = True, classes: int = 1) -> DataFrame:
    """Infos that are not compressed: packed, apart, or vectors of classes."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            out = []
            for uid, node, n, c in f[["split_uid", "node", "sample_count", "c"]].itertuples(index=False):
                plain = [key.decrypt(x) for x in c]
                if classes > 1:
                    sums = codec.unpack_mo(plain, n, classes, budget)
                elif packing:
                    sums = [codec.unpack(plain[0], n, budget)]
                else:
                    sums = [(plain[0] - n * budget.offset, plain[1])]
                out.append((uid, node, n, [str(g) for g, _ in sums], [str(h) for _, h in sums], len(c)))
            yield pd.DataFrame(out, columns=["split_uid", "node", "sample_count", "g", "h", "dec"])

    return infos.mapInPandas(run, SUMS)


def compressible(budget: Budget, packing: bool, compress: bool, classes: int, mo_compress: bool = True) -> bool:
    """Whether infos go as packages: one cipher each, and room for two or more in a cipher."""
    return compress and packing and (classes == 1 or mo_compress and budget.n_k(classes) == 1 and budget.members(classes) > 1)


Send = Callable[[DataFrame], DataFrame]


def exchange_infos(infos: DataFrame, key: Backend, budget: Budget, packing: bool, compress: bool, classes: int, send: Send | None = None) -> DataFrame:
    """What the active party reads of a passive party's infos. send: what a message passes on its way."""
    keep = send or (lambda sent: sent)
    if compress:
        return open_packages(keep(compress_infos(infos, key.public(), budget, classes)), key, budget, classes)
    return open_infos(keep(infos.select("split_uid", "node", "sample_count", "c")), key, budget, packing, classes)


def passive_sums(rows: DataFrame, key: Backend, budget: Budget, secret: str, packing: bool = True, compress: bool = True, classes: int = 1, default_bins: list[int] | None = None) -> DataFrame:
    """The whole exchange for one passive party and layer: node, fid, bin, sample_count and exact sums g, h.

    rows: inst_id, node, bins, g, h. The join that gives fid and bin back stands for the passive party's private table.
    """
    public = key.public()
    enc = encrypt_rows(rows, key, budget, packing, classes)
    live = enc.hint("merge").join(rows.select("inst_id", "node", "bins"), "inst_id")  # never a broadcast of ciphers
    infos = cut(split_infos(cipher_histogram(live, public, default_bins), public, secret))
    packed = compressible(budget, packing, compress, classes)

    def send(sent: DataFrame) -> DataFrame:
        guard("active", "split_info", [c for c in sent.columns if c != "shifts"])
        return sent

    opened = exchange_infos(infos, key, budget, packing, packed, classes, send)
    return opened.join(infos.select("split_uid", "fid", "bin"), "split_uid").select("node", "fid", "bin", "sample_count", "g", "h")
