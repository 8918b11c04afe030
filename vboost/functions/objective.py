"""Losses: first and second derivatives as columns, and second-order objective values."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def sigmoid(score: Column) -> Column:
    return 1 / (1 + F.exp(-score))


def logistic(df: DataFrame) -> DataFrame:
    """Adds g = p - y and h = p (1 - p) from score and y in {0, 1}."""
    p = sigmoid(F.col("score"))
    return df.withColumn("g", p - F.col("y")).withColumn("h", p * (1 - p))


def squared(df: DataFrame) -> DataFrame:
    return df.withColumn("g", F.col("score") - F.col("y")).withColumn("h", F.lit(1.0))


def softmax_probabilities(scores: Column) -> Column:
    top = F.array_max(scores)
    e = F.transform(scores, lambda s: F.exp(s - top))
    return F.transform(e, lambda x: x / F.aggregate(e, F.lit(0.0), lambda a, v: a + v))


def softmax(df: DataFrame, k: int) -> DataFrame:
    """Adds arrays g_j = p_j - y_j and the diagonal h_j = p_j (1 - p_j) from an array score and a class y."""
    with_p = df.withColumn("p", softmax_probabilities(F.col("score")))
    hot = F.transform(F.sequence(F.lit(0), F.lit(k - 1)), lambda j: F.when(j == F.col("y"), 1.0).otherwise(0.0))
    return with_p.withColumn("g", F.zip_with("p", hot, lambda p, t: p - t)).withColumn("h", F.transform("p", lambda p: p * (1 - p))).drop("p")


def quadratic_loss(df: DataFrame, reg_lambda: float) -> DataFrame:
    """Second-order objective of a frame with g, h, w (the row's leaf weight) and node: the penalty once a leaf."""
    leaf = df.groupBy("node").agg(F.sum(F.col("g") * F.col("w") + 0.5 * F.col("h") * F.col("w") * F.col("w")).alias("fit"), F.first("w").alias("w"))
    return leaf.agg(F.sum(F.col("fit") + 0.5 * reg_lambda * F.col("w") * F.col("w")).alias("objective"))


def quadratic_loss_mo(df: DataFrame, reg_lambda: float) -> DataFrame:
    """The same for vector leaves with a diagonal second derivative."""
    total = lambda a: F.aggregate(a, F.lit(0.0), lambda s, x: s + x)
    row = total(F.zip_with("g", "w", lambda g, w: g * w)) + 0.5 * total(F.zip_with("h", F.transform("w", lambda w: w * w), lambda h, w2: h * w2))
    leaf = df.groupBy("node").agg(F.sum(row).alias("fit"), F.first("w").alias("w"))
    return leaf.agg(F.sum(F.col("fit") + 0.5 * reg_lambda * total(F.transform("w", lambda w: w * w))).alias("objective"))


def exp_array(x: np.ndarray) -> np.ndarray:
    """exp of an array, the same doubles as Spark's `exp`: numpy's own differs in the last bit, and fixed-point sums see it.

    Reduction by multiples of ln 2 in two parts, and the usual rational form of the rest (the published fdlibm constants).
    """
    hi_2, lo_2 = 6.93147180369123816490e-01, 1.90821492927058770002e-10
    with np.errstate(all="ignore"):
        x = np.clip(np.asarray(x, np.float64), -800.0, 800.0)  # beyond, the result is 0 or infinite all the same
        word = np.abs(x).view(np.int64) >> 32
        k = np.where(np.isnan(x), 0.0, np.trunc(1.44269504088896338700 * x + np.copysign(0.5, x)))
        k = np.where(word < 0x3FF0A2B2, np.sign(x), k)  # below 1.5 ln 2
        k = np.where(word > 0x3FD62E42, k, 0.0)  # above 0.5 ln 2
        high, low = x - k * hi_2, k * lo_2
        r = high - low
        t = r * r
        c = r - t * (1.66666666666666019037e-01 + t * (-2.77777777770155933842e-03 + t * (6.61375632143793436117e-05 + t * (-1.65339022054652515390e-06 + t * 4.13813679705723846039e-08))))
        y = np.where(k == 0, 1.0 - ((r * c) / (c - 2.0) - r), 1.0 - ((low - (r * c) / (2.0 - c)) - high))
        return np.where(word < 0x3E300000, 1.0 + x, np.ldexp(y, k.astype(np.int32)))


def arrays(kind: str, y: np.ndarray, score: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """g and h of `logistic`, `squared` or `softmax`, a column for each score, to the last bit."""
    if kind == "squared":
        return score - y[:, None], np.ones_like(score)
    if kind == "logistic":
        p = 1 / (1 + exp_array(-score))
        return p - y[:, None], p * (1 - p)
    e = exp_array(score - score.max(axis=1, keepdims=True))
    total = np.zeros(len(e))
    for j in range(e.shape[1]):  # in this order
        total = total + e[:, j]
    p = e / total[:, None]
    return p - (np.arange(e.shape[1]) == y[:, None]), p * (1 - p)
