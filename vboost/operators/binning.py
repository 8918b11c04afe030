"""Quantile binning. Edges are at most (bins - 1) numbers a feature; a value's bin is the number of edges below it."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def fit(df: DataFrame, columns: list[str], max_bin: int = 32, method: str = "approx_percentile", block: int = 256) -> list[list[float]]:
    """Distinct inner quantiles of each column, nulls and NaN left out.

    approx_percentile: mergeable sketches, one aggregate for a block of columns. percentile: exact and interpolated.
    exact_rank: the value at each rank, by a sort of each column (small inputs and oracles). summaries: the same by
    `Summary`, made on Arrow batches and merged by feature; for at most some dozens of columns.
    """
    steps = [i / max_bin for i in range(1, max_bin)]
    out: list[list[float]] = []
    if "features" in df.columns:
        return _fit_wide(df, len(columns), steps, method)
    value = lambda c: F.when(~F.isnan(F.col(c).cast("double")), F.col(c).cast("double"))
    if method == "summaries":
        return _fit_summaries(df, columns, steps)
    if method == "exact_rank":
        return [[r["edge"] for r in rank_edges(df, c, max_bin).orderBy("edge").collect()] for c in columns]
    for at in range(0, len(columns), block):
        some = columns[at : at + block]
        probes = F.array(*map(F.lit, steps))
        ask = (lambda c: F.percentile_approx(value(c), steps, 10_000)) if method == "approx_percentile" else (lambda c: F.percentile(value(c), probes))
        row = df.agg(*[ask(c).alias(str(i)) for i, c in enumerate(some)]).first()
        out += [sorted(set(row[str(i)] or [])) for i in range(len(some))]
    return out


class Summary:
    """A mergeable summary of values: at most KEPT distinct ones with their counts for each level, exact while that holds them.

    A level's two summaries make one of the next, so a value's rank is off by at most (1 + levels) / KEPT of the rows.
    """

    KEPT = 1 << 15

    def __init__(self) -> None:
        self.levels: list[tuple[np.ndarray, np.ndarray] | None] = []

    def add(self, values: np.ndarray, counts: np.ndarray | None = None) -> None:
        """counts: of values; by default each stands once, and they are sorted without their places."""
        if counts is None:
            values = np.sort(values)
            first = np.flatnonzero(np.r_[True, values[1:] != values[:-1]]) if len(values) else np.zeros(0, np.int64)
            values, counts = values[first], np.diff(first, append=len(values))
        values, counts = self._small(values, counts)
        for k in range(len(self.levels) + 1):
            if k == len(self.levels):
                self.levels.append(None)
            held = self.levels[k]
            if held is None:
                self.levels[k] = (values, counts)
                return
            self.levels[k] = None
            values, counts = self._small(np.concatenate([held[0], values]), np.concatenate([held[1], counts]))

    @staticmethod
    def _joined(values: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if not (values[1:] > values[:-1]).all():
            order = np.argsort(values, kind="stable")
            values, counts = values[order], counts[order]
        first = np.flatnonzero(np.r_[True, values[1:] != values[:-1]]) if len(values) else np.zeros(0, np.int64)
        return values[first], np.add.reduceat(counts, first) if len(first) else counts

    def _small(self, values: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Equal values as one, and if too many are left, neighbours as the largest of them."""
        values, counts = self._joined(values, counts)
        if len(values) > self.KEPT:
            upto = np.cumsum(counts)
            last = np.searchsorted(upto, np.arange(1, self.KEPT + 1) * (upto[-1] / self.KEPT), side="left").clip(max=len(upto) - 1)
            last = last[np.r_[True, last[1:] != last[:-1]]]
            values, counts = values[last], np.diff(upto[last], prepend=0)
        return values, counts

    def whole(self) -> tuple[np.ndarray, np.ndarray]:
        held = [x for x in self.levels if x is not None] or [(np.zeros(0), np.zeros(0, np.int64))]
        return self._joined(*map(np.concatenate, zip(*held)))

    def quantiles(self, steps: list[float]) -> list[float]:
        """The distinct values at ranks ceil(step n)."""
        values, counts = self.whole()
        if not len(values):
            return []
        upto = np.cumsum(counts)
        ranks = np.maximum(np.ceil(np.array(steps) * upto[-1]), 1)
        return np.unique(values[np.searchsorted(upto, ranks, side="left")]).tolist()


#: Values of a column that are sorted at once.
SORTED = 1 << 16


def _fit_summaries(df: DataFrame, columns: list[str], steps: list[float]) -> list[list[float]]:
    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found, waiting, n = [Summary() for _ in columns], [], 0

        def take() -> None:
            for j, s in enumerate(found):
                x = np.concatenate([b.column(j).to_numpy(zero_copy_only=False).astype(np.float64) for b in waiting])
                x = x[~np.isnan(x)] + 0.0  # one zero
                s.add(x)

        for batch in batches:
            waiting.append(batch)
            n += batch.num_rows
            if n >= SORTED:
                take()
                waiting, n = [], 0
        if n:
            take()
        for j, s in enumerate(found):
            values, counts = s.whole()
            if len(values):
                yield pa.RecordBatch.from_arrays([pa.array([j], pa.int32()), pa.array([values.tobytes()], pa.binary()), pa.array([counts.tobytes()], pa.binary())], names=["fid", "v", "c"])

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, Summary()
        done = lambda: pa.RecordBatch.from_arrays([pa.array([now], pa.int32()), pa.array([held.quantiles(steps)], pa.list_(pa.float64()))], names=["fid", "e"])
        for batch in batches:
            for i in range(batch.num_rows):
                fid, v, c = batch.column(0)[i].as_py(), np.frombuffer(batch.column(1)[i].as_buffer(), np.float64), np.frombuffer(batch.column(2)[i].as_buffer(), np.int64)
                if fid != now:
                    if now is not None:
                        yield done()
                    now, held = fid, Summary()
                held.add(v, c)
        if now is not None:
            yield done()

    made = df.select(*[F.col(c).cast("double") for c in columns]).mapInArrow(make, "fid int, v binary, c binary")
    merged = made.repartition("fid").sortWithinPartitions("fid").mapInArrow(merge, "fid int, e array<double>")
    found = {r["fid"]: list(r["e"]) for r in merged.collect()}  # a row for each feature
    return [found.get(j, []) for j in range(len(columns))]


def _fit_wide(df: DataFrame, n: int, steps: list[float], method: str) -> list[list[float]]:
    """The same of an array column `features`: values are dealt by feature, so no aggregate holds many columns."""
    if method == "exact_rank":
        raise ValueError("exact ranks need a column for each feature")

    def turn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                x = np.ascontiguousarray(_matrix(batch.column(0), batch.num_rows).T)
                lists = pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * x.shape[1]), pa.array(x.ravel()))
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(x), dtype=np.int32)), lists], names=["fid", "values"])

    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = df.select("features").mapInArrow(turn, "fid int, values array<double>").repartition(parts, "fid").sortWithinPartitions("fid")
    flat = dealt.select("fid", F.explode("values").alias("v")).where(~F.isnan("v"))
    ask = F.percentile_approx("v", steps, 10_000) if method == "approx_percentile" else F.percentile("v", F.array(*map(F.lit, steps)))
    found = {r["fid"]: sorted(set(r["e"] or [])) for r in flat.groupBy("fid").agg(ask.alias("e")).collect()}
    return [found.get(j, []) for j in range(n)]


def rank_edges(df: DataFrame, column: str, max_bin: int) -> DataFrame:
    """The distinct values at ranks ceil(i n / bins): edge. Ranks come from counts of distinct values."""
    per = df.where(F.col(column).isNotNull()).groupBy(F.col(column).cast("double").alias("v")).agg(F.count("*").alias("c"))
    # running sums within ranges of the value, carried over from range to range: no task orders all values
    edge = per.agg(F.min("v").alias("lo"), F.max("v").alias("hi"), F.sum("c").alias("n"))
    cell = F.floor((F.col("v") - F.col("lo")) / F.greatest(F.col("hi") - F.col("lo"), F.lit(1e-300)) * 4095).cast("int")
    placed = per.crossJoin(F.broadcast(edge)).withColumn("cell", cell)  # one row
    sizes = placed.groupBy("cell").agg(F.sum("c").alias("size"))
    before = sizes.select("cell", F.coalesce(F.sum("size").over(Window.orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))  # at most 4096 rows
    inner = Window.partitionBy("cell").orderBy("v").rowsBetween(Window.unboundedPreceding, 0)
    ranked = placed.join(F.broadcast(before), "cell").withColumn("upto", F.col("before") + F.sum("c").over(inner))
    last, first = F.floor(F.col("upto") * max_bin / F.col("n")), F.floor((F.col("upto") - F.col("c")) * max_bin / F.col("n"))
    return ranked.where((last > first) & (first < max_bin - 1) & (F.col("upto") * max_bin >= F.col("n"))).where(F.greatest(first + 1, F.lit(1)) <= max_bin - 1).select(F.col("v").alias("edge"))


def bin_column(x: Column, edges: list[float]) -> Column:
    """The bin as a balanced CASE: five comparisons for 32 bins, inside code generation."""

    def half(lo: int, hi: int) -> Column:
        if lo == hi:
            return F.lit(lo)
        mid = (lo + hi) // 2
        return F.when(x > edges[mid], half(mid + 1, hi)).otherwise(half(lo, mid))

    return F.when(x.isNull() | F.isnan(x.cast("double")), F.lit(0)).otherwise(half(0, len(edges)))


def _matrix(column: pa.Array, n: int) -> np.ndarray:
    """Rows of an array column as a matrix; nulls are NaN."""
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(n, -1)


def code(edges: list[list[float]]) -> type:
    """The type of a packed bin."""
    return np.uint8 if max(map(len, edges), default=0) < 1 << 8 else np.uint16


def bins_of(batch: pa.RecordBatch, first: int, cuts: list[np.ndarray], one: bool, kind: type) -> np.ndarray:
    """The bin matrix of a batch whose values stand from column `first` on: a column each, or with `one` in an array column."""
    n = batch.num_rows
    out = np.zeros((n, len(cuts)), dtype=kind)
    every = _matrix(batch.column(first), n) if one and n else None
    for j, e in enumerate(cuts):
        x = batch.column(first + j).to_numpy(zero_copy_only=False).astype(np.float64) if every is None else every[:, j]
        out[:, j] = np.where(np.isnan(x), 0, np.searchsorted(e, x, side="left"))
    return out


def apply(df: DataFrame, columns: list[str], edges: list[list[float]], keep: list[str], packed: bool = False) -> DataFrame:
    """`keep` columns and bins array<int>, by vectorised search over Arrow batches; missing values go to bin 0.

    The values are a column each, or one array column `features`. packed: bins as the bytes of `code`, in a column x.
    """
    cuts = [np.array(e) for e in edges]
    one = "features" in df.columns
    kind = code(edges) if packed else np.int32

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = batch.num_rows
            out = bins_of(batch, len(keep), cuts, one, kind)
            if packed:
                ends = np.arange(n + 1, dtype=np.int32) * (len(cuts) * out.itemsize)
                rows = pa.Array.from_buffers(pa.binary(), n, [None, pa.py_buffer(ends), pa.py_buffer(out)])
                yield pa.RecordBatch.from_arrays([*batch.columns[: len(keep)], rows], names=[*keep, "x"])
                continue
            lists = pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * len(cuts)), pa.array(out.ravel()))
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(keep)], lists], names=[*keep, "bins"])

    rows = df.select(*keep, "features") if one else df.select(*keep, *[F.col(c).cast("double") for c in columns])
    fields = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in rows.schema.fields[: len(keep)])
    return rows.mapInArrow(run, f"{fields}, {'x binary' if packed else 'bins array<int>'}")
