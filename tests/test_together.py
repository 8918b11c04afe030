"""Trees of an epoch grow side by side over packed bins; wide workloads are arrays."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from vboost.operators import binning, histogram
from vboost.plans import grow
from vboost.plans.grow import train
from vboost.plans.params import FederatedSpec, Params, Party
from vboost.sources import workloads

SPEC = FederatedSpec((Party("a", "active", ("x0", "x1")), Party("p", "passive", ("x2", "x3"))))
DIR = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def data(spark):
    rows = [(i, (i % 5 + i % 7) % 5, float(i % 7), float(i % 3), float(i % 5), float(i % 11)) for i in range(400)]
    return spark.createDataFrame(rows, "inst_id long, y int, x0 double, x1 double, x2 double, x3 double").cache()


def shape(model):
    return [tuple(map(str, r.values())) for r in model.node_rows()]


def jobs(spark):
    return spark.sparkContext._jsc.sc().dagScheduler().numTotalJobs()


def test_an_epoch_of_many_classes_takes_the_jobs_of_one_tree(spark, data):
    def took(epochs):
        before = jobs(spark)
        assert len(train(data, SPEC, Params(trees=epochs, classes=5, max_depth=3)).trees) == 5 * epochs
        return jobs(spark) - before

    one = took(1)
    assert took(2) - one <= 10  # two aggregates and three layers, some of two stages; each of the five trees took more before


@pytest.mark.parametrize("output", ["single", "multi"])
def test_ways_to_sum_agree(data, monkeypatch, output):
    p = Params(trees=2, classes=5, output=output, max_depth=3, subsample=0.9, colsample=0.7)
    want = shape(train(data, SPEC, p))
    monkeypatch.setattr(grow, "LOCAL_CELLS", 0)  # searched by block of features
    assert shape(train(data, SPEC, p)) == want
    monkeypatch.setattr(histogram, "HELD", 0)  # no table is held until the last row
    monkeypatch.setattr(histogram, "ROWS_AT_ONCE", 16)  # and a tree at a time
    assert shape(train(data, SPEC, p)) == want


def test_fixed_point_range_is_kept(data):
    far = data.withColumn("y", F.lit(1e12))
    with pytest.raises(Exception, match="exceeds the fixed-point range"):
        train(far, SPEC, Params(trees=1, objective="squared", goss=None, max_depth=2))
    with pytest.raises(OverflowError):
        histogram._add(np.full(1, 1 << 62), slice(None), np.ones(1, np.int64))


def test_array_features_equal_the_columns(spark):
    names = tuple(f"x{i:04d}" for i in (0, 5, 63, 64, 100, 2143, 2144, 2500, 3071))
    for classes in (1, 10):
        w = workloads.Workload("some", None, names[0::2], names[1::2], classes)
        a, b = w.load(spark, DIR), w.matrix(spark, DIR)
        value = lambda df, x: {r["inst_id"]: (r["y"], *r["v"]) for r in df.select("inst_id", "y", x.alias("v")).collect()}
        assert value(a, F.array(*w.spec.columns)) == value(b, F.col("features"))
        edges = binning.fit(a, w.spec.columns)
        assert edges == binning.fit(b, w.spec.columns)
        old = {r["inst_id"]: list(r["bins"]) for r in binning.apply(a, w.spec.columns, edges, ["inst_id"]).collect()}
        new = {r["inst_id"]: list(r["x"]) for r in binning.apply(b, w.spec.columns, edges, ["inst_id"], packed=True).collect()}
        assert old == new


def test_missing_coordinates_go_to_bin_0(spark, tmp_path):
    rows = [(i, [float(i + j) for j in range(64)]) for i in range(20)] + [(20, None), (21, [1.0, 2.0])]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    w = workloads.Workload("some", None, ("x0000", "x0064"), ("x0063",))
    b = w.matrix(spark, str(tmp_path))
    got = {r["inst_id"]: list(r["x"]) for r in binning.apply(b, w.spec.columns, binning.fit(b, w.spec.columns), ["inst_id"], packed=True).collect()}
    assert len(got) == 22 and got[20] == [0, 0, 0] and got[21][2] == 0 and max(got[19]) > 10


def test_small_files_are_dealt_over_the_cores(spark):
    w = workloads.ALL["w2"]
    rows = w.matrix(spark, DIR)
    assert rows.select("inst_id").rdd.getNumPartitions() >= spark.sparkContext.defaultParallelism
    value = lambda df: sorted(map(tuple, df.select("inst_id", "y", *w.spec.columns).collect()))
    assert value(rows) == value(w.load(spark, DIR))
