"""Gradient-based one-side sampling, and uniform samples by hash."""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def keyed_hash(seed: int, of: str = "inst_id") -> Column:
    """A number in [0, 1000003) that any SQL engine computes alike."""
    return F.pmod(F.pmod(F.col(of), F.lit(1_000_003)) * 7919 + seed * 104_729, F.lit(1_000_003))


def size_of_gradient(norm: str = "abs") -> Column:
    return F.abs(F.col("g")) if norm == "abs" else F.aggregate("g", F.lit(0.0), lambda a, x: a + F.abs(x))


def amplify(df: DataFrame, factor: float, vector: bool) -> DataFrame:
    for c in ("g", "h"):
        scaled = F.transform(c, lambda x: x * F.col("amp")) if vector else F.col(c) * F.col("amp")
        df = df.withColumn(c, scaled)
    return df


def second_hash(seed: int, of: str = "inst_id") -> Column:
    """Another such number, for a choice that must not follow the first."""
    return F.pmod(F.pmod(F.col(of), F.lit(1_000_003)) * 104_651 + seed * 7919, F.lit(1_000_003))


def goss(df: DataFrame, top_rate: float = 0.2, other_rate: float = 0.1, seed: int = 1, norm: str = "abs", exact: bool = False, rows: int | None = None) -> DataFrame:
    """The survivors with amplified g and h, and amp.

    exact: ceil(a n) rows of the largest gradients and ceil(b n) of the rest by hash, ties by inst_id. Otherwise the
    threshold is a mergeable quantile sketch; of the rows at the threshold as many count as large, by their hash, as
    make up a n, and the rest is kept by another hash: two aggregates and a filter, a n and b n rows in expectation,
    also where all gradients tie.
    """
    factor = (1 - top_rate) / other_rate
    ranked = df.withColumn("size", size_of_gradient(norm)).withColumn("hash", keyed_hash(seed))
    if exact:
        n = rows if rows is not None else df.count()
        most, more = -int(-top_rate * n // 1), -int(-other_rate * n // 1)
        top = ranked.orderBy(F.desc("size"), "inst_id").limit(most)
        rest = ranked.join(top.select("inst_id"), "inst_id", "left_anti").orderBy("hash", "inst_id").limit(more)
        kept = top.withColumn("amp", F.lit(1.0)).unionByName(rest.withColumn("amp", F.lit(factor)))
    else:
        edge = ranked.agg(F.percentile_approx("size", 1 - top_rate, 10_000)).first()[0] or 0.0
        found = ranked.agg(F.count_if(F.col("size") > edge).alias("above"), F.count_if(F.col("size") == edge).alias("at"), F.count("*").alias("n")).first()
        room = min(max(top_rate * found["n"] - found["above"], 0.0) / max(found["at"], 1), 1.0)
        is_top = (F.col("size") > edge) | ((F.col("size") == edge) & (F.col("hash") < int(1_000_003 * room)))
        share = second_hash(seed) < int(1_000_003 * other_rate / (1 - top_rate))
        kept = ranked.where(is_top | share).withColumn("amp", F.when(is_top, 1.0).otherwise(factor))
    return amplify(kept, factor, norm != "abs").drop("size", "hash")


@dataclass(frozen=True)
class Draw:
    """A tree's sample of rows in arrays: a share of them by hash, and of these what `goss` takes once `edge` and `room` are known.

    key: inst_id modulo 1000003; below 0 for ids that are no integers, which no hash takes.
    """

    seed: int
    uniform_seed: int
    rate: float = 1.0
    goss: tuple[float, float] | None = None
    edge: float = 0.0
    room: float = 0.0

    def among(self, key: np.ndarray) -> np.ndarray:
        return np.ones(len(key), bool) if self.rate >= 1 else _below(key, 7919, self.uniform_seed * 104_729, self.rate)

    def counts(self, key: np.ndarray, size: np.ndarray) -> tuple[int, int, int]:
        """Rows above the edge, at it, and all."""
        size = size[self.among(key)]
        return int((size > self.edge).sum()), int((size == self.edge).sum()), len(size)

    def settled(self, above: int, at: int, n: int) -> Draw:
        return replace(self, room=min(max(self.goss[0] * n - above, 0.0) / max(at, 1), 1.0))

    def amounts(self, key: np.ndarray, size: np.ndarray) -> np.ndarray:
        """The amp of each row, 0 where it is not in the sample."""
        among = self.among(key)
        if self.goss is None:
            return among.astype(np.float64)
        top, other = self.goss
        is_top = (size > self.edge) | ((size == self.edge) & _below(key, 7919, self.seed * 104_729, self.room))
        share = _below(key, 104_651, self.seed * 7919, other / (1 - top), 1_000_003 * other / (1 - top))
        return np.where(among, np.where(is_top, 1.0, np.where(share, (1 - top) / other, 0.0)), 0.0)


def _below(key: np.ndarray, times: int, plus: int, rate: float, limit: float | None = None) -> np.ndarray:
    """`keyed_hash` or `second_hash` of the keys under a share of their range."""
    return (key >= 0) & ((key.astype(np.int64) * times + plus) % 1_000_003 < int(1_000_003 * rate if limit is None else limit))


def sizes_of(g: np.ndarray, trees: int) -> np.ndarray:
    """`size_of_gradient` for each tree of an epoch: of its own column, or over all columns where one tree has all."""
    if trees == g.shape[1]:
        return np.abs(g)
    total = np.zeros(len(g))
    for j in range(g.shape[1]):  # in this order
        total = total + np.abs(g[:, j])
    return total[:, None]


def uniform(df: DataFrame, rate: float, seed: int = 1) -> DataFrame:
    return df.where(keyed_hash(seed) < int(1_000_003 * rate))


def some_features(features: int, rate: float, seed: int) -> list[int]:
    """The features that a tree may split on: ceil(rate n) of them, chosen by the seed."""
    order = sorted(range(features), key=lambda j: ((j + 1) * 7919 + (seed + 1) * 104_729) * 2_654_435_761 % (1 << 32))
    return sorted(order[: max(1, -int(-rate * features // 1))])
