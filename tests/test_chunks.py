"""Instances pass between Spark and Python in chunks; their gradients and samples are those of the column plans."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from vboost import experiments
from vboost.functions import objective
from vboost.operators import binning, chunks, sampling
from vboost.sources import workloads

DIR = "/root/testdata/sf0.001"


def test_a_workload_is_a_few_chunks(spark):
    w = workloads.ALL["w2"]
    fit, test, edges = experiments._split(spark, DIR, "w2")
    want = [x.count() for x in workloads.split(w.load(spark, DIR))]
    assert [chunks.rows(x) for x in (fit, test)] == want and sum(want) > 5000
    assert fit.count() + test.count() <= 2 * spark.sparkContext.defaultParallelism  # a row for each instance before
    assert {"n", "x"} <= set(fit.columns) and len(edges) == len(w.spec.columns)


def test_arrays_are_the_columns_to_the_last_bit(spark):
    for spread in (0.01, 1.0, 40.0, 800.0):
        x = spark.range(20_000).select(((F.rand(3) - 0.5) * 2 * spread).alias("x")).select("x", F.exp("x").alias("e")).toArrow()
        assert (objective.exp_array(x.column("x").to_numpy()) == x.column("e").to_numpy()).all()
    edge = np.array([0.0, -0.0, 1e-300, 709.7, 709.8, -708.0, -745.0, -746.0, 1e9, -1e9, np.nan, np.inf, -np.inf])
    want = [r[0] for r in spark.createDataFrame([(float(v),) for v in edge], "x double").select(F.exp("x")).collect()]
    assert np.array_equal(objective.exp_array(edge), np.array(want), equal_nan=True)
    for kind, k, of in (("logistic", 1, objective.logistic), ("squared", 1, objective.squared), ("softmax", 5, lambda d: objective.softmax(d, 5))):
        score = F.array(*[(F.rand(i) - 0.5) * 6 for i in range(k)])
        df = spark.range(3000).select((F.col("id") % (k if k > 1 else 2)).cast("int").alias("y"), (score if k > 1 else score[0]).alias("score"))
        rows = of(df).select("y", "score", "g", "h").collect()
        column = lambda c: np.array([r[c] for r in rows], np.float64).reshape(len(rows), -1)  # noqa: B023, E731
        g, h = objective.arrays(kind, column("y")[:, 0], column("score"))
        assert (g == column("g")).all() and (h == column("h")).all()


@pytest.mark.parametrize("levels", [3, 4000])
def test_draws_are_goss(spark, levels):
    rows = [(7 * i - 300, ((i * 37) % levels) / levels - 0.5, 0.2) for i in range(4000)]
    df = spark.createDataFrame(rows, "inst_id long, g double, h double")
    want = {r["inst_id"]: (r["amp"], r["g"]) for r in sampling.goss(df, 0.2, 0.1, 5).collect()}
    ids, g = np.array([r[0] for r in rows]), np.array([[r[1]] for r in rows])
    raw = lambda a, t: np.ascontiguousarray(a.astype(t)).tobytes()
    frame = spark.createDataFrame([(len(p), raw(ids[p] % 1_000_003, np.int32), b"", raw(g[p], np.float64), raw(g[p], np.float64)) for p in np.array_split(np.arange(4000), 3)], chunks.GRADIENTS)
    (draw,) = chunks.settle(frame.drop("x"), [sampling.Draw(5, 0, 1.0, (0.2, 0.1))], [])
    amp = draw.amounts(ids % 1_000_003, np.abs(g[:, 0]))
    assert {int(i): (a, v * a) for i, a, v in zip(ids, amp, g[:, 0]) if a > 0} == want


def test_summaries_are_quantiles(spark, monkeypatch):
    x = np.random.default_rng(1).normal(size=200_000).round(3)
    steps = [i / 32 for i in range(1, 32)]
    whole, s = np.sort(x), binning.Summary()
    for part in np.array_split(x, 50):
        s.add(part, np.ones(len(part), np.int64))
    assert s.quantiles(steps) == np.unique(whole[np.ceil(np.array(steps) * len(x)).astype(int) - 1]).tolist()  # exact while all distinct values are kept
    monkeypatch.setattr(binning.Summary, "KEPT", 1000)
    s = binning.Summary()
    for part in np.array_split(x, 50):
        s.add(part, np.ones(len(part), np.int64))
    assert sum(s.whole()[1]) == len(x)
    for q, e in zip(steps, s.quantiles(steps)):
        lo, hi = np.searchsorted(whole, e, "left"), np.searchsorted(whole, e, "right")
        assert lo - 0.008 * len(x) <= q * len(x) <= hi + 0.008 * len(x)
    df = spark.createDataFrame([(float(i % 97), None if i % 5 else float(i), float("nan") if i % 2 else -0.0) for i in range(5000)], "a double, b double, c double")
    assert binning.fit(df, ["a", "b", "c"], method="summaries") == binning.fit(df, ["a", "b", "c"])


def test_quality_runs_share_the_cores_and_time_is_taken_alone(spark, monkeypatch):
    at_once, most, train = [], [], experiments.train_packed

    def watched(*args, **kwargs):
        at_once.append(1)
        most.append(len(at_once))
        try:
            return train(*args, **kwargs)
        finally:
            at_once.pop()

    monkeypatch.setattr(experiments, "train_packed", watched)
    got = experiments.quality(spark, DIR, ("base", "lean"), 1, ("w1",)).collect()
    assert [r["variant"] for r in got] == ["base", "lean"] and max(most) == 2  # one after the other before
    made = len(most)
    timed = experiments.tree_time(spark, DIR, ("base", "lean"), 1, ("w1",)).collect()
    assert len(most) == made + 2 and set(most[made:]) == {1} and all(r["tree_seconds"] > 0 for r in timed)
    assert experiments.quality(spark, DIR, ("base", "lean"), 1, ("w1",)).collect() == got and len(most) == made + 2
