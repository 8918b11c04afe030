"""Accuracy measures as plans."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def auc(df: DataFrame, score: str = "score", label: str = "y") -> DataFrame:
    """Mean-rank AUC with ties averaged: one row, auc.

    Distinct scores are counted first; running sums are taken within ranges of the score and carried over from range
    to range, so no task orders all rows.
    """
    per = df.groupBy(F.col(score).alias("s")).agg(F.sum((F.col(label) == 1).cast("long")).alias("p"), F.sum((F.col(label) != 1).cast("long")).alias("q"))
    # pairs in the same of 4096 score cells are ordered inside the cell, other pairs by the cells' totals
    edge = per.agg(F.min("s").alias("lo"), F.max("s").alias("hi"))
    cell = F.floor((F.col("s") - F.col("lo")) / F.greatest(F.col("hi") - F.col("lo"), F.lit(1e-300)) * 4095).cast("int")
    placed = per.crossJoin(F.broadcast(edge)).withColumn("cell", cell)  # one row
    inner = Window.partitionBy("cell").orderBy("s").rowsBetween(Window.unboundedPreceding, -1)
    won = placed.withColumn("below", F.coalesce(F.sum("q").over(inner), F.lit(0))).groupBy("cell").agg(F.sum(F.col("p") * (F.col("below") + F.col("q") / 2)).alias("won"), F.sum("p").alias("p"), F.sum("q").alias("q"))
    outer = Window.orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)  # at most 4096 rows
    total = won.withColumn("lower", F.coalesce(F.sum("q").over(outer), F.lit(0)))
    return total.agg((F.sum(F.col("won") + F.col("p") * F.col("lower")) / (F.sum("p") * F.sum("q"))).alias("auc"))


def accuracy(df: DataFrame, predicted: Column, label: str = "y") -> DataFrame:
    return df.agg(F.avg((predicted == F.col(label)).cast("double")).alias("accuracy"))


def argmax(scores: str = "score") -> Column:
    """First class of the largest score, from 0."""
    return (F.array_position(scores, F.array_max(scores)) - 1).cast("int")


def logloss(df: DataFrame, score: str = "score", label: str = "y") -> DataFrame:
    s = F.col(score)
    return df.agg(F.avg(F.log1p(F.exp(-F.abs(s))) + F.greatest(s, F.lit(0.0)) - s * F.col(label)).alias("logloss"))


def confusion(df: DataFrame, predicted: Column, classes: list[int], label: str = "y") -> DataFrame:
    """Actual classes as rows, predicted as columns p0, p1, ..."""
    out = df.withColumn("predicted", predicted).groupBy(F.col(label).alias("actual")).pivot("predicted", classes).count().fillna(0)
    return out.select("actual", *[F.col(str(c)).alias(f"p{c}") for c in classes])


def quantisation_error(df: DataFrame, column: str, r: int) -> DataFrame:
    """Largest and mean difference of a column from its fixed-point form at r bits."""
    x = F.col(column)
    gap = F.abs(x - F.floor(x * float(2**r)) / float(2**r))
    return df.agg(F.max(gap).alias("largest"), F.avg(gap).alias("mean"))


def trees_to_target(history: list[dict], key: str, target: float) -> int | None:
    """Trees grown when the measure first reached the target."""
    return next((row["trees"] for row in history if row[key] >= target), None)


def speedup(base: float, other: float) -> float:
    return base / other
