"""The baselines and the named variants."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import splits
from .params import FederatedSpec, Params, Party


def base(p: Params) -> Params:
    """No packing, compression, subtraction or sampling."""
    return p.but(packing=False, compress=False, subtract=False, goss=None, mode="joint", output="single")


def lean(p: Params) -> Params:
    return p.but(packing=True, compress=True, subtract=True, mode="joint", output="single")


def mix(p: Params) -> Params:
    return lean(p).but(mode="mix")


def layered(p: Params) -> Params:
    return lean(p).but(mode="layered")


def multi_output(p: Params) -> Params:
    return lean(p).but(output="multi")


def central(p: Params) -> Params:
    """One party holds everything: no sampling, no ciphers."""
    return p.but(goss=None, mode="joint", output="single")


def as_one_party(spec: FederatedSpec) -> FederatedSpec:
    return FederatedSpec((Party("active", "active", tuple(spec.columns)),))


def mllib(df: DataFrame, spec: FederatedSpec, trees: int = 10, depth: int = 5, test: DataFrame | None = None) -> DataFrame:
    """Scores of the library's gradient-boosted trees on test rows, as a check of bands: inst_id, y, score."""
    from pyspark.ml.classification import GBTClassifier
    from pyspark.ml.feature import VectorAssembler
    from pyspark.ml.functions import vector_to_array

    gather = VectorAssembler(inputCols=spec.columns, outputCol="features", handleInvalid="keep")
    ready = lambda x: gather.transform(x.withColumn("label", F.col("y").cast("double")))
    fitted = GBTClassifier(maxIter=trees, maxDepth=depth, seed=1).fit(ready(df))
    return fitted.transform(ready(df if test is None else test)).select("inst_id", "y", vector_to_array("probability")[1].alias("score"))


def brute_split(rows: DataFrame, features: int, reg_lambda: float, bins: int = 64) -> DataFrame:
    """fid, bin, gain of the root's best split: every candidate's sums from the rows again, without prefix sums.

    For tests: features x bins candidates, each one conditional sum of a single aggregate.
    """
    out = None
    for fid in range(features):
        left = lambda b, fid=fid: F.get("bins", F.lit(fid)) <= b
        sums = [F.struct(F.lit(fid).alias("fid"), F.lit(b).alias("bin"), F.count_if(left(b)).alias("n"), F.count_if(F.get("bins", F.lit(fid)) == b).alias("own"), *[F.sum(F.when(left(b), F.col(c)).otherwise(0.0)).alias(f"{c}l") for c in ("g", "h")]) for b in range(bins)]
        one = rows.agg(F.count("*").alias("m"), F.sum("g").alias("gt"), F.sum("h").alias("ht"), F.array(*sums).alias("x")).select("m", "gt", "ht", F.inline("x"))
        out = one if out is None else out.unionByName(one)
    gain = splits.gain(F.col("gl"), F.col("hl"), F.col("gt"), F.col("ht"), reg_lambda)
    return out.where("n > 0 AND n < m AND own > 0").select("fid", "bin", gain.alias("gain")).orderBy(F.desc(F.round("gain", 9)), "fid", "bin").limit(1)
