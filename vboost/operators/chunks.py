"""Instances in chunks: a row of a frame holds thousands of them as bytes, which pass between Spark and Python whole.

What a layer needs of an instance is about its features' bins and a few numbers; as rows of their own, each pass over
them costs more than the counting. Columns: held (set aside for tests), n, key (inst_id modulo 1000003, 32 bits), y,
x (the bin matrix), score (null: zeros).
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import objective
from ..sources.io import small_batches
from . import binning, sampling

SCHEMA = "held boolean, n int, key binary, y binary, x binary, score binary"
GRADIENTS = "n int, key binary, x binary, g binary, h binary"
#: Bytes and rows after which a chunk is closed.
BYTES, ROWS = 1 << 20, 1 << 15


def of(df: DataFrame, columns: list[str], edges: list[list[float]], held: Column | None = None) -> DataFrame:
    """Chunks of a frame with inst_id, y and the values; rows without y are left out. held: which rows are set aside."""
    cuts, kind, one = [np.array(e) for e in edges], binning.code(edges), "features" in df.columns
    small_batches(df.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        waiting: dict[bool, list[tuple]] = {False: [], True: []}

        def closed(aside: bool) -> pa.RecordBatch:
            key, y, x = map(np.concatenate, zip(*waiting[aside]))
            waiting[aside] = []
            return batch_of(held=aside, n=len(y), key=key, y=y, x=x, score=None)

        for batch in batches:
            x = binning.bins_of(batch, 3, cuts, one, kind)
            aside, key, y = (batch.column(i).to_numpy(zero_copy_only=False) for i in range(3))
            for flag in (False, True):
                some = np.flatnonzero(aside.astype(bool) == flag)
                if len(some):
                    waiting[flag].append((key[some], y[some], x[some]))
                if sum(len(k) for k, _, _ in waiting[flag]) >= min(ROWS, max(1, BYTES // max(1, len(cuts) * x.itemsize))):
                    yield closed(flag)
        for flag in (False, True):
            if waiting[flag]:
                yield closed(flag)

    key = F.coalesce(F.pmod(F.col("inst_id").try_cast("bigint"), F.lit(1_000_003)), F.lit(-1)).cast("int")
    values = ["features"] if one else [F.col(c).cast("double") for c in columns]
    aside = F.lit(False) if held is None else held
    return df.where("y IS NOT NULL").where(aside.isNotNull()).select(aside.alias("held"), key.alias("key"), F.col("y").cast("double").alias("y"), *values).mapInArrow(run, SCHEMA)


def batch_of(**columns) -> pa.RecordBatch:
    """One chunk: arrays as their bytes."""
    kinds = {"held": pa.bool_(), "n": pa.int32()}
    raw = lambda v: v.tobytes() if isinstance(v, np.ndarray) else v
    return pa.RecordBatch.from_arrays([pa.array([raw(v)], kinds.get(c, pa.binary())) for c, v in columns.items()], names=list(columns))


def each(batches: Iterator[pa.RecordBatch], edges: list[list[float]]) -> Iterator[dict]:
    """The chunks of batches, their bytes as arrays."""
    kinds = {"key": np.int32, "y": np.float64, "x": binning.code(edges), "score": np.float64, "g": np.float64, "h": np.float64}
    for batch in batches:
        for i in range(batch.num_rows):
            c = {f: batch.column(f)[i] for f in batch.schema.names}
            out = {f: np.frombuffer(v.as_buffer(), kinds[f]) if f in kinds and v.is_valid else v.as_py() for f, v in c.items()}
            for f in ("x", "g", "h", "score"):
                if out.get(f) is not None:
                    out[f] = out[f].reshape(out["n"], -1)
            yield out


def rows(df: DataFrame) -> int:
    return df.agg(F.sum("n")).first()[0] or 0


def _scored(c: dict, width: int, add: Callable[[np.ndarray, np.ndarray], None]) -> np.ndarray:
    """A chunk's scores with those of new trees. add: adds to the scores of a bin matrix."""
    out = np.zeros((c["n"], width)) if c["score"] is None else c["score"].copy()
    add(out, c["x"])
    return out


def advanced(df: DataFrame, width: int, add: Callable, edges: list[list[float]]) -> DataFrame:
    """The chunks with the new scores."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for c in each(batches, edges):
            yield batch_of(**(c | {"score": _scored(c, width, add)}))

    return df.mapInArrow(run, SCHEMA)


def scored(df: DataFrame, width: int, add: Callable, edges: list[list[float]], many: bool) -> DataFrame:
    """y and score of each instance."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for c in each(batches, edges):
            s = _scored(c, width, add)
            value = pa.ListArray.from_arrays(pa.array(np.arange(len(s) + 1, dtype=np.int32) * width), pa.array(s.ravel())) if many else pa.array(s[:, 0])
            yield pa.RecordBatch.from_arrays([pa.array(c["y"]), value], names=["y", "score"])

    return df.mapInArrow(run, f"y double, score {'array<double>' if many else 'double'}")


def gradients(df: DataFrame, kind: str, width: int, add: Callable, edges: list[list[float]]) -> DataFrame:
    """Chunks of bins and gradients at the new scores."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for c in each(batches, edges):
            g, h = objective.arrays(kind, c["y"], _scored(c, width, add))
            yield batch_of(n=c["n"], key=c["key"], x=c["x"], g=np.ascontiguousarray(g), h=np.ascontiguousarray(h))

    return df.mapInArrow(run, GRADIENTS)


def settle(df: DataFrame, draws: list[sampling.Draw], edges: list[list[float]]) -> list[sampling.Draw]:
    """The draws with the threshold and the share at it that `sampling.goss` would find: two aggregates for all."""
    if not draws or draws[0].goss is None:
        return draws

    def sizes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for c in each(batches, edges):
            for k, (d, s) in enumerate(zip(draws, sampling.sizes_of(c["g"], len(draws)).T)):
                s = s[d.among(c["key"])]
                yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.ListArray.from_arrays(pa.array([0, len(s)], pa.int32()), pa.array(s))], names=["k", "size"])

    flat = df.select("n", "key", "g").mapInArrow(sizes, "k int, size array<double>").select("k", F.explode("size").alias("size"))
    ask = F.percentile_approx("size", 1 - draws[0].goss[0], 10_000).alias("edge")
    asked = flat.agg(F.lit(0).alias("k"), ask) if len(draws) == 1 else flat.groupBy("k").agg(ask)
    found = {r["k"]: r["edge"] for r in asked.collect()}
    draws = [sampling.replace(d, edge=found.get(k) or 0.0) for k, d in enumerate(draws)]

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = np.zeros((len(draws), 3), np.int64)
        for c in each(batches, edges):
            out += [d.counts(c["key"], s) for d, s in zip(draws, sampling.sizes_of(c["g"], len(draws)).T)]
        yield pa.RecordBatch.from_arrays([pa.array([x.tolist() for x in [out.ravel()]], pa.list_(pa.int64()))], names=["counts"])

    total = np.zeros(3 * len(draws), np.int64)
    for r in df.select("n", "key", "g").mapInArrow(count, "counts array<bigint>").collect():  # a row of each task
        total += np.array(r["counts"], np.int64)
    return [d.settled(*map(int, t)) for d, t in zip(draws, total.reshape(-1, 3))]
