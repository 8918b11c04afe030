import pytest
from pyspark.sql import functions as F

from vboost.functions import metrics, objective, splits
from vboost.operators import histogram, sampling
from vboost.plans import baselines, grow
from vboost.plans.grow import train
from vboost.plans.params import FederatedSpec, Params, Party, guard, schedule

SPEC = FederatedSpec((Party("a", "active", ("x0", "x1")), Party("p", "passive", ("x2", "x3"))))


@pytest.fixture(scope="module")
def data(spark):
    rows = [(i, 1 if (i % 7) + 2 * (i % 5) > 6 else 0, float(i % 7), float(i % 3), float(i % 5), float(i % 11)) for i in range(300)]
    return spark.createDataFrame(rows, "inst_id long, y int, x0 double, x1 double, x2 double, x3 double").cache()


def shape(model):
    return {(r["tree"], r["node"], r["fid"], r["bin"], r["count"]) for r in model.node_rows()}


def test_lossless_variants_agree(data, monkeypatch):
    p = Params(trees=2, max_depth=3, goss=None)
    lean = shape(train(data, SPEC, baselines.lean(p)))
    assert lean == shape(train(data, SPEC, baselines.base(p)))
    assert lean == shape(train(data, baselines.as_one_party(SPEC), baselines.central(p)))
    assert lean == shape(train(data, SPEC, baselines.lean(p).but(sparse=True)))
    monkeypatch.setattr(grow, "LOCAL_CELLS", 0)  # all steps distributed
    assert lean == shape(train(data, SPEC, baselines.lean(p)))


def test_mix_and_layered_owners(data):
    m = train(data, SPEC, baselines.mix(Params(trees=2, max_depth=3, goss=None)))
    owners = {t: {r["party"] for r in m.node_rows() if r["tree"] == t and r["party"]} for t in (0, 1)}
    assert owners == {0: {"a"}, 1: {"p"}}
    assert not [r for r in m.ledger.rows if r["tree"] == 0]
    m = train(data, SPEC, baselines.layered(Params(trees=1, goss=None, h_passive=1, h_active=2)))
    assert all((r["party"] == "p") == (r["node"] == 0) for r in m.node_rows() if r["party"])


def test_prediction_and_loss(data):
    m = train(data, SPEC, Params(trees=4, max_depth=3, goss=None), evaluate=True)
    losses = [h["loss"] for h in m.history]
    assert losses == sorted(losses, reverse=True)
    scored = m.predict(data, ["inst_id", "y"])
    assert scored.count() == 300 and metrics.auc(scored).first()[0] > 0.95
    assert abs(metrics.auc(scored).first()[0] - m.history[-1]["quality"]) < 1e-9


def test_multi_output(data):
    rows = data.withColumn("y", (F.col("inst_id") % 3).cast("int"))
    m = train(rows, SPEC, Params(trees=3, classes=3, output="multi", max_depth=3, goss=(0.2, 0.3)))
    assert len(m.trees) == 3
    single = train(rows, SPEC, Params(trees=2, classes=3, output="single", max_depth=2, goss=None))
    assert len(single.trees) == 6
    assert metrics.accuracy(m.predict(rows, ["inst_id", "y"]), metrics.argmax()).first()[0] > 0.9


def test_vector_gain_of_one_class_is_scalar(spark):
    df = spark.createDataFrame([(1.5, 2.0, 3.0, 5.0)], "gl double, hl double, g double, h double")
    a = F.array
    row = df.select(splits.gain(F.col("gl"), F.col("hl"), F.col("g"), F.col("h"), 1.0).alias("s"), splits.gain_mo(a("gl"), a("hl"), a("g"), a("h"), 1.0).alias("v")).first()
    assert row["s"] == row["v"]


def test_leaf_weight_minimises(spark):
    df = spark.createDataFrame([(0, 0.4, 0.2), (0, -0.1, 0.3), (1, 0.5, 0.25)], "node int, g double, h double")
    w = df.groupBy("node").agg((-F.sum("g") / (F.sum("h") + 1)).alias("w"))
    best = objective.quadratic_loss(df.join(w, "node"), 1.0).first()[0]
    for d in (-0.01, 0.01):
        assert objective.quadratic_loss(df.join(w, "node").withColumn("w", F.col("w") + d), 1.0).first()[0] > best


def test_goss_counts(data):
    x = objective.logistic(data.withColumn("score", F.col("x3") / 10))
    kept = sampling.goss(x, 0.2, 0.1, exact=True).collect()
    assert len(kept) == 60 + 30 and {r["amp"] for r in kept} == {1.0, 8.0}
    assert sampling.goss(x, 0.2, 0.1).count() < 150


def test_auc_with_ties(spark):
    rows = [(i % 2 if i % 3 else 1, float(i % 4)) for i in range(40)]
    pairs = [(a > b) + 0.5 * (a == b) for y, a in rows if y for z, b in rows if not z]
    got = metrics.auc(spark.createDataFrame(rows, "y int, score double")).first()[0]
    assert abs(got - sum(pairs) / len(pairs)) < 1e-12


def test_degenerate_inputs(spark, data):
    none = train(data.where("inst_id < 0"), SPEC, Params(trees=2))
    assert none.trees == []
    one = train(data.withColumn("y", F.lit(1)), SPEC, Params(trees=1, goss=None, max_depth=2))
    assert one.predict(data, ["inst_id"]).where("score <= 0").count() == 0
    holes = data.withColumn("x0", F.when(F.col("inst_id") % 2 == 0, F.col("x0")))
    assert train(holes, SPEC, Params(trees=1, goss=None, max_depth=2)).predict(holes, ["inst_id"]).count() == 300


def test_guard_and_spec():
    with pytest.raises(PermissionError):
        guard("active", "split_info", ["split_uid", "fid"])
    with pytest.raises(ValueError):
        FederatedSpec((Party("a", "active", ("x",)), Party("p", "passive", ("x",))))
    plan = schedule(SPEC, Params(mode="layered"))
    assert plan.depth == 5 and plan.eligible(0, 2) == ("p",) and plan.eligible(0, 3) == ("a",)


def test_cells_are_summed_before_the_shuffle(data):
    rows = histogram.fixed_columns(data.select(F.array("x0", "x2").cast("array<int>").alias("bins"), F.lit(0).alias("node"), F.lit(0.5).alias("g"), F.lit(0.25).alias("h")), 53)
    plan = histogram.limb_cells(rows)._jdf.queryExecution().executedPlan().toString()
    assert plan.index("Exchange hashpartitioning") > plan.index("HashAggregate") and "partial_sum" in plan
