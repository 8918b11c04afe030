"""The engine's queries and their SQL."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import ciphered, experiments
from .fixture import BASE_SQL, PLAIN, R, SPEC, base_rows, fixed_rows, tree_frame, tree_sql
from .functions import codec, costs, metrics, objective, splits
from .functions.codec import Budget
from .operators import align, around, binning, histogram, sampling, surface
from .plans import baselines
from .plans.grow import grow_tree, train
from .plans.params import Params, schedule
from .sources import workloads
from .sources.io import load_model, row_counts, save_model, shared_dir, table
from .streaming import jobs

def _shown(cells: DataFrame) -> DataFrame:
    real = lambda c: codec.real(F.col(c), R).alias(c[0])
    return cells.select("fid", "bin", "cnt", real("g0"), real("h0"))


def hist_scalar(spark, sf_dir):
    return _shown(histogram.build(fixed_rows(spark, sf_dir)))


def hist_sparse(spark, sf_dir):
    return _shown(histogram.build(fixed_rows(spark, sf_dir), default_bins=[0, 1, 0]))


def hist_cumsum(spark, sf_dir):
    x = histogram.cumsum(histogram.build(fixed_rows(spark, sf_dir)))
    return x.select("fid", "bin", F.col("cnt_l").cast("bigint").alias("cnt_l"), codec.real(F.col("g0_l"), R).alias("gl"), codec.real(F.col("h0_l"), R).alias("hl"))


def hist_subtract(spark, sf_dir):
    """The sibling's cells by subtraction where the node is split on fid 1 at bin 2."""
    rows = fixed_rows(spark, sf_dir)
    child = F.when(F.get("bins", F.lit(1)) <= 2, 1).otherwise(2)
    small = histogram.build(rows.withColumn("node", child).where("node = 1"))
    return _shown(histogram.subtract(histogram.build(rows), small, {1: 2}))


def hist_mo(spark, sf_dir):
    """Two classes, y and 1 - y, at p = 1/2."""
    rows = base_rows(spark, sf_dir).withColumn("g", F.array("g", -F.col("g"))).withColumn("h", F.array("h", "h"))
    cells = histogram.build(histogram.fixed_columns(rows, R, 2), 2)
    return cells.select("fid", "bin", "cnt", *[codec.real(F.col(c), R).alias(c) for c in ("g0", "g1", "h0", "h1")])


def _candidates(spark, sf_dir):
    return histogram.candidates(histogram.build(fixed_rows(spark, sf_dir)), R, 1.0)


def split_gain_root(spark, sf_dir):
    return _candidates(spark, sf_dir).select("fid", "bin", F.round("gain", 6).alias("gain"))


def best_split_root(spark, sf_dir):
    return histogram.best(_candidates(spark, sf_dir)).select("fid", "bin", F.round("gain", 6).alias("gain"))


def split_gain_mo(spark, sf_dir):
    rows = base_rows(spark, sf_dir).withColumn("g", F.array("g", -F.col("g"))).withColumn("h", F.array("h", "h"))
    found = histogram.candidates(histogram.build(histogram.fixed_columns(rows, R, 2), 2), R, 1.0, 2)
    return found.select("fid", "bin", F.round("gain", 6).alias("gain"))


def leaf_weights(spark, sf_dir):
    """Weights of both children of the root's best split."""
    x = histogram.best(_candidates(spark, sf_dir))
    v = lambda c: codec.real(F.col(c), R)
    left = splits.leaf_weight(v("g0_l"), v("h0_l"), 1.0)
    right = splits.leaf_weight(v("g0_t") - v("g0_l"), v("h0_t") - v("h0_l"), 1.0)
    return x.select(F.round(left, 9).alias("w_left"), F.round(right, 9).alias("w_right"))


def _tree(spark, sf_dir, **changes) -> DataFrame:
    params = PLAIN.but(**changes)
    rows = fixed_rows(spark, sf_dir).drop("node")
    t = grow_tree(rows, SPEC, params, schedule(SPEC, params), changes.get("tree_per_party", 1) - 1)
    return tree_frame(spark, t, params.reg_lambda)


def tree1_joint_depth2(spark, sf_dir):
    return _tree(spark, sf_dir)


def tree1_layered(spark, sf_dir):
    """One layer by the passive party, one by the active."""
    return _tree(spark, sf_dir, mode="layered", h_passive=1, h_active=1)


def tree1_mix(spark, sf_dir, tree: int = 0):
    """A tree of the active party (0) or of the passive party (1) alone."""
    params = PLAIN.but(mode="mix")
    t = grow_tree(fixed_rows(spark, sf_dir).drop("node"), SPEC, params, schedule(SPEC, params), tree)
    return tree_frame(spark, t, 1.0)


def _line_grads(spark, sf_dir):
    workloads.views(spark, sf_dir)
    return spark.sql("SELECT o_orderkey AS inst_id, CAST(o_totalprice / 500000 * 2 - 1 AS DOUBLE) AS score, CASE WHEN o_orderstatus = 'F' THEN 1 ELSE 0 END AS y FROM orders")


def grad_logistic(spark, sf_dir):
    x = objective.logistic(_line_grads(spark, sf_dir))
    return x.select("inst_id", F.round("g", 6).alias("g"), F.round("h", 6).alias("h"))


def grad_softmax(spark, sf_dir):
    x = _line_grads(spark, sf_dir).withColumn("score", F.array(F.col("score"), F.lit(0.0), F.lit(0.5)))
    x = objective.softmax(x, 3)
    return x.select("inst_id", *[F.round(F.get(c, F.lit(j)), 6).alias(f"{c}{j}") for c in ("g", "h") for j in range(3)])


def quad_loss(spark, sf_dir):
    x = base_rows(spark, sf_dir).withColumn("node", F.get("bins", F.lit(1))).withColumn("w", F.col("node") / 10)
    return objective.quadratic_loss(x, 1.0).select(F.round("objective", 6).alias("objective"))


def quad_loss_mo(spark, sf_dir):
    """The vector objective of classes y and 1 - y with opposite weights: twice the scalar one."""
    x = base_rows(spark, sf_dir).withColumn("node", F.get("bins", F.lit(1)))
    x = x.withColumn("g", F.array("g", -F.col("g"))).withColumn("h", F.array("h", "h")).withColumn("w", F.array(F.col("node") / 10, -F.col("node") / 10))
    return objective.quadratic_loss_mo(x, 1.0).select(F.round("objective", 6).alias("objective"))


def leaf_weights_mo(spark, sf_dir):
    """Vector weights of the cells of one feature."""
    rows = base_rows(spark, sf_dir).withColumn("g", F.array("g", -F.col("g"))).withColumn("h", F.array("h", "h"))
    cells = histogram.build(histogram.fixed_columns(rows, R, 2), 2).where("fid = 1")
    v = lambda n: F.array(*[codec.real(F.col(f"{n}{j}"), R) for j in range(2)])
    w = splits.leaf_weight_mo(v("g"), v("h"), 1.0)
    return cells.select("bin", *[(F.round(F.get(w, F.lit(j)), 9) + 0.0).alias(f"w{j}") for j in range(2)])


def quantisation_error(spark, sf_dir):
    """Largest and mean loss of prices as fixed-point numbers of 20 bits."""
    x = table(spark, sf_dir, "orders").select((F.col("o_totalprice") / 500_000).alias("x"))
    return metrics.quantisation_error(x, "x", 20).select(F.round("largest", 12).alias("largest"), F.round("mean", 12).alias("mean"))


def mllib_band(spark, sf_dir, trees: int = 5):
    """Quality of the library's boosted trees beside the central booster's, on the same rows."""
    w = workloads.ALL["w1"]
    fit, test = workloads.split(w.load(spark, sf_dir))
    ours = train(fit, baselines.as_one_party(w.spec), baselines.central(Params(trees=trees))).predict(test, ["inst_id", "y"])
    theirs = baselines.mllib(fit, w.spec, trees, 5, test)
    rows = [(name, metrics.auc(x).first()[0]) for name, x in (("central", ours), ("mllib", theirs))]
    return spark.createDataFrame(rows, "booster string, auc double")


def brute_split_root(spark, sf_dir):
    """The root's best split by scanning the rows of every candidate anew."""
    best = baselines.brute_split(base_rows(spark, sf_dir), 3, 1.0)
    return best.select("fid", "bin", F.round("gain", 6).alias("gain"))


def bit_budget(spark, sf_dir):
    """Bits, slots and ciphers a row for the rows of given tables, with the values of one of their columns as classes."""
    rows = []
    for name, key, label, factor in BUDGETS:
        n, classes = table(spark, sf_dir, name).agg(F.count(key), F.count_distinct(label)).first()
        b = Budget(max(n, 1)).amplified(factor)
        rows.append((name, n, classes, factor, b.b_g, b.b_h, b.b_gh, b.slots, b.n_k(classes)))
    return spark.createDataFrame(rows, "name string, n long, classes long, factor int, b_g int, b_h int, b_gh int, slots int, n_k int")


#: Table, key, label and amplification (8 under sampling).
BUDGETS = (("orders", "o_orderkey", "o_orderstatus", 1), ("orders", "o_orderkey", "o_orderstatus", 8), ("lineitem", "l_orderkey", "l_linenumber", 1), ("part", "p_partkey", "p_brand", 1), ("events", "event_id", "event_type", 8))
BUDGET_SQL = f"""
WITH t AS ({" UNION ALL ".join(f"SELECT '{t}' AS name, count({k}) AS n, count(DISTINCT {c}) AS classes, {f} AS factor FROM {t}" for t, k, c, f in BUDGETS)}),
b AS (SELECT *, 54 + length(bin(greatest(n, 1))) + CASE factor WHEN 8 THEN 3 ELSE 0 END AS b_g FROM t)
SELECT name, CAST(n AS BIGINT) AS n, CAST(classes AS BIGINT) AS classes, CAST(factor AS INT) AS factor, CAST(b_g AS INT) AS b_g, CAST(b_g - 1 AS INT) AS b_h, CAST(2 * b_g - 1 AS INT) AS b_gh,
  CAST(1023 // (2 * b_g - 1) AS INT) AS slots, CAST(ceil(classes / CAST(1023 // (2 * b_g - 1) AS DOUBLE)) AS INT) AS n_k FROM b
"""


def cost_model(spark, sf_dir):
    """The rough costs of a tree over the lines, with as many features as w4 has."""
    n, out = row_counts(spark, sf_dir, lineitem="l_orderkey")["lineitem"], []
    for name, optimised in (("base", False), ("lean", True)):
        c = costs.estimate(n, 2000, optimised=optimised)
        out.append((name, *[round(x, 4) for x in (c.computation, c.endecryption, c.communication)]))
    return spark.createDataFrame(out, "name string, computation double, endecryption double, communication double")


def cost_reduction(spark, sf_dir):
    """What the lean protocol saves of the base's costs over the orders, with as many features as w4 has."""
    n = row_counts(spark, sf_dir, orders="o_orderkey")["orders"]
    return spark.createDataFrame([tuple(round(v, 4) for v in costs.reduction(n, 2000).values())], "computation double, endecryption double, communication double")


def goss_survivors(spark, sf_dir):
    x = objective.logistic(_line_grads(spark, sf_dir))
    x = x.withColumn("g", F.round("g", 6))
    return sampling.goss(x, 0.2, 0.1, seed=3, exact=True).select("inst_id", "amp")


def goss_sums(spark, sf_dir):
    x = objective.logistic(_line_grads(spark, sf_dir)).withColumn("g", F.round("g", 6))
    return sampling.goss(x, 0.2, 0.1, seed=3, exact=True).agg(F.count("*").alias("n"), F.round(F.sum("g"), 4).alias("g"))


GOSS_SQL = """
WITH x AS (SELECT o_orderkey AS inst_id, round(1 / (1 + exp(-(o_totalprice / 500000 * 2 - 1))) - (CASE WHEN o_orderstatus = 'F' THEN 1 ELSE 0 END), 6) AS g, (o_orderkey * 7919 + 3 * 104729) % 1000003 AS k FROM orders),
n AS (SELECT count(*) AS n FROM x), a AS (SELECT *, row_number() OVER (ORDER BY abs(g) DESC, inst_id) AS rn FROM x),
t AS (SELECT a.*, rn <= ceil(n * 2 / 10.0) AS top FROM a CROSS JOIN n),
o AS (SELECT t.*, row_number() OVER (PARTITION BY top ORDER BY k, inst_id) AS rk FROM t),
kept AS (SELECT inst_id, g, CASE WHEN top THEN CAST(1 AS DOUBLE) ELSE CAST(8 AS DOUBLE) END AS amp FROM o CROSS JOIN n WHERE top OR rk <= ceil(n / 10.0))
"""


def auc_rank(spark, sf_dir):
    return metrics.auc(_line_grads(spark, sf_dir).withColumn("score", F.floor(F.col("score") * 50) / 50)).select(F.round("auc", 9).alias("auc"))


def accuracy(spark, sf_dir):
    return metrics.accuracy(_line_grads(spark, sf_dir), (F.col("score") > 0).cast("int")).select(F.round("accuracy", 9).alias("accuracy"))


def confusion(spark, sf_dir):
    return metrics.confusion(_line_grads(spark, sf_dir), (F.col("score") > 0).cast("int"), [0, 1])


def align_orders_lineitem(spark, sf_dir):
    one = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("inst_id"))
    return align.intersect_digest(one, table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("inst_id")))


def align_docs_labels(spark, sf_dir):
    one = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("inst_id"))
    return align.intersect_digest(one, table(spark, sf_dir, "labels").select(F.col("doc_id").alias("inst_id")))


def align_lost_ids(spark, sf_dir):
    one = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("inst_id"))
    return one.join(align_orders_lineitem(spark, sf_dir), "inst_id", "left_anti")


def align_dh(spark, sf_dir):
    """Customers with orders, by twice-blinded ids."""
    one = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("inst_id"))
    return align.intersect_dh(one, table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("inst_id")))


def bin_percentile(spark, sf_dir):
    edges = binning.fit(table(spark, sf_dir, "orders"), ["o_totalprice"], 8, "percentile")[0]
    return spark.createDataFrame([(i, round(e, 8)) for i, e in enumerate(edges)], "k int, edge double")


def bin_edges_rank(spark, sf_dir):
    return binning.rank_edges(table(spark, sf_dir, "lineitem"), "l_quantity", 8)


def bin_approx(spark, sf_dir):
    edges = binning.fit(table(spark, sf_dir, "lineitem"), ["l_quantity", "l_extendedprice"], 32)
    return spark.createDataFrame([(j, i, e) for j, x in enumerate(edges) for i, e in enumerate(x)], "fid int, k int, edge double")


EDGES = [50_000.0 * i for i in range(1, 10)]


def bin_apply_orders(spark, sf_dir):
    return table(spark, sf_dir, "orders").select("o_orderkey", binning.bin_column(F.col("o_totalprice"), EDGES).alias("bin"))


def bin_apply_arrow(spark, sf_dir):
    x = binning.apply(table(spark, sf_dir, "orders"), ["o_totalprice"], [EDGES], ["o_orderkey"])
    return x.select("o_orderkey", F.get("bins", F.lit(0)).alias("bin"))


def features(spark, sf_dir, name):
    w = workloads.ALL[name]
    x = w.load(spark, sf_dir)
    return x.select("inst_id", "y", *[F.round(F.col(c), 8).alias(c) for c in (*w.active, *w.passive)])


def features_wide(spark, sf_dir, name):
    """Sums of all features and label counts of a wide workload."""
    w = workloads.ALL[name]
    return workloads.totals(w, w.load(spark, sf_dir))


_FLIPPED = "CASE WHEN (CAST(embedding[1] AS DOUBLE) + embedding[2] + embedding[3] - embedding[4] + 4 * CAST(embedding[5] AS DOUBLE) * embedding[6] > 0) <> (" + workloads.flip(8, "vec_id") + ") THEN 1 ELSE 0 END"
WIDE_W7 = workloads.totals_sql(3072, "list_position(embedding[1:10], list_max(embedding[1:10])) - 1")
WIDE_W4 = workloads.totals_sql(2000, _FLIPPED)


def trained(spark, sf_dir, variant: str, name: str = "w1", trees: int = 2) -> DataFrame:
    """Scores of the workload's test rows under a named variant."""
    w = workloads.ALL[name]
    p = getattr(baselines, variant)(Params(trees=trees, classes=w.classes))
    fit, test = workloads.split(w.load(spark, sf_dir))
    model = train(fit, baselines.as_one_party(w.spec) if variant == "central" else w.spec, p)
    return model.predict(test, ["inst_id", "y"])


def base_equals_lean(spark, sf_dir):
    """Node rows that differ between the base protocol's tree and the lean one without sampling: none."""
    w = workloads.ALL["w1"]
    data = w.load(spark, sf_dir)
    found = []
    for p in (baselines.base(Params(trees=1, max_depth=3)), baselines.lean(Params(trees=1, max_depth=3, goss=None)), baselines.lean(Params(trees=1, max_depth=3, goss=None, sparse=True))):
        m = train(data, w.spec, p)
        found.append({(r["node"], r["fid"], r["bin"], r["count"]) for r in m.node_rows()})
    return spark.createDataFrame([(len(found[0] ^ found[1]), len(found[0] ^ found[2]))], "lean long, sparse long")


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A lean model of three trees on the credit-like workload; all its rows scored."""
    w = workloads.ALL["w1"]
    data = w.load(spark, sf_dir)
    return train(data, w.spec, Params(trees=3)).predict(data, ["inst_id", "y"])


def sink_model_store(spark, sf_dir):
    """Nodes of a trained model as written, partitioned by tree, and read back."""
    w = workloads.ALL["w1"]
    m = train(w.load(spark, sf_dir), w.spec, Params(trees=2, max_depth=2))
    path = f"{shared_dir(spark)}/model-{uuid.uuid4().hex}"
    save_model(spark, m.node_rows(), path)
    back = load_model(spark, path)
    assert back == m.node_rows()
    return spark.createDataFrame([(r["tree"], r["node"], r["party"], r["count"]) for r in back], "tree int, node int, party string, rows long")


def around_query(spark, sf_dir, name):
    workloads.views(spark, sf_dir)
    return spark.sql(around.statement(name, "spark"))


NAMED: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    **{f.__name__: f for f in (hist_scalar, hist_sparse, hist_cumsum, hist_subtract, hist_mo, split_gain_root, best_split_root, split_gain_mo, leaf_weights, tree1_joint_depth2, tree1_layered)},
    **{f.__name__: f for f in (grad_logistic, grad_softmax, quad_loss, quad_loss_mo, leaf_weights_mo, quantisation_error, mllib_band, brute_split_root, bit_budget, cost_model, cost_reduction, goss_survivors, goss_sums, auc_rank, accuracy, confusion)},
    **{f.__name__: f for f in (align_orders_lineitem, align_docs_labels, align_lost_ids, align_dh, bin_percentile, bin_edges_rank, bin_approx, bin_apply_orders, bin_apply_arrow, base_equals_lean)},
    "tree1_mix_active": partial(tree1_mix, tree=0),
    "tree1_mix_passive": partial(tree1_mix, tree=1),
    **{f"{n}_features": partial(features, name=n) for n in ("w1", "w2", "w3", "w5", "w6", "w8", "w9", "w10")},
    **{f"{n}_features": partial(features_wide, name=n) for n in ("w4", "w7")},
    **{f"train_{v}": partial(trained, variant=v) for v in ("base", "lean", "mix", "layered", "central")},
    "train_mo": partial(trained, variant="multi_output", name="w5"),
    "sink_model_store": sink_model_store,
    **{n: partial(around_query, name=n) for n in around.STATEMENTS},
    **jobs.QUERIES,
    **ciphered.QUERIES,
    **surface.QUERIES,
    **experiments.QUERIES,
    "pack_unpack_roundtrip": surface.udf_unpack,
}


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(NAMED)


def oracle_sql() -> dict[str, str]:
    w = f"WITH {BASE_SQL} "
    cells = w + "SELECT fid, bin, cnt, g, h FROM c"
    grads = "WITH x AS (SELECT o_orderkey AS inst_id, o_totalprice / 500000 * 2 - 1 AS score, CASE WHEN o_orderstatus = 'F' THEN 1 ELSE 0 END AS y FROM orders) "
    soft = "exp(score) + 1 + exp(CAST(0.5 AS DOUBLE))"
    hot = lambda j: f"(CASE WHEN y = {j} THEN 1 ELSE 0 END)"
    p = [f"(exp(score) / ({soft}))", f"(1 / ({soft}))", f"(exp(CAST(0.5 AS DOUBLE)) / ({soft}))"]
    out = {
        "hist_scalar": cells,
        "hist_sparse": cells,
        "hist_cumsum": w + "SELECT fid, bin, CAST(cnt_l AS BIGINT) AS cnt_l, gl, hl FROM s",
        "hist_subtract": w + "SELECT f.fid, f.bin, count(*) AS cnt, sum(CAST(0.5 AS DOUBLE) - f.y) AS g, sum(CAST(0.25 AS DOUBLE)) AS h FROM f JOIN b USING (inst_id) WHERE b1 > 2 GROUP BY 1, 2",
        "hist_mo": w + "SELECT fid, bin, cnt, g AS g0, 0 - g AS g1, h AS h0, h AS h1 FROM c",
        "split_gain_root": w + "SELECT fid, bin, round(gain, 6) AS gain FROM gain",
        "best_split_root": w + "SELECT fid, bin, round(gain, 6) AS gain FROM gain ORDER BY gain DESC, fid, bin LIMIT 1",
        "split_gain_mo": w + "SELECT fid, bin, round(2 * gain, 6) AS gain FROM gain",
        "leaf_weights": w + "SELECT round(-gl / (hl + 1), 9) AS w_left, round(-(gt - gl) / (ht - hl + 1), 9) AS w_right FROM gain ORDER BY gain DESC, fid, bin LIMIT 1",
        "tree1_joint_depth2": tree_sql("0, 1, 2", "0, 1, 2"),
        "tree1_layered": tree_sql("1, 2", "0"),
        "tree1_mix_active": tree_sql("0", "0"),
        "tree1_mix_passive": tree_sql("1, 2", "1, 2"),
        "grad_logistic": grads + "SELECT inst_id, round(1 / (1 + exp(-score)) - y, 6) AS g, round(1 / (1 + exp(-score)) * (1 - 1 / (1 + exp(-score))), 6) AS h FROM x",
        "grad_softmax": grads + "SELECT inst_id, " + ", ".join(f"round({p[j]} - {hot(j)}, 6) AS g{j}, round({p[j]} * (1 - {p[j]}), 6) AS h{j}" for j in range(3)) + " FROM x",
        "quad_loss": w + "SELECT round(sum(fit + 0.5 * w * w), 6) AS objective FROM (SELECT b1 / CAST(10 AS DOUBLE) AS w, sum((CAST(0.5 AS DOUBLE) - y) * b1 / 10 + CAST(0.125 AS DOUBLE) * b1 * b1 / 100) AS fit FROM b GROUP BY b1) z",
        "quad_loss_mo": w + "SELECT round(2 * sum(fit + 0.5 * w * w), 6) AS objective FROM (SELECT b1 / CAST(10 AS DOUBLE) AS w, sum((CAST(0.5 AS DOUBLE) - y) * b1 / 10 + CAST(0.125 AS DOUBLE) * b1 * b1 / 100) AS fit FROM b GROUP BY b1) z",
        "leaf_weights_mo": w + "SELECT bin, round(-g / (h + 1), 9) + 0 AS w0, round(g / (h + 1), 9) + 0 AS w1 FROM c WHERE fid = 1",
        "quantisation_error": "SELECT round(max(x - floor(x * 1048576) / 1048576), 12) AS largest, round(avg(x - floor(x * 1048576) / 1048576), 12) AS mean FROM (SELECT o_totalprice / 500000 AS x FROM orders) z",
        "brute_split_root": w + "SELECT fid, bin, round(gain, 6) AS gain FROM gain ORDER BY gain DESC, fid, bin LIMIT 1",
        "bit_budget": BUDGET_SQL,
        "cost_model": f"SELECT name, {experiments.MODEL} FROM {experiments.KINDS} CROSS JOIN (SELECT greatest(count(l_orderkey), 1) AS n, 2000 AS d FROM lineitem) z",
        "goss_survivors": GOSS_SQL + "SELECT inst_id, amp FROM kept",
        "goss_sums": GOSS_SQL + "SELECT count(*) AS n, round(sum(g * amp), 4) AS g FROM kept",
        "auc_rank": grads + ", r AS (SELECT y, rank() OVER (ORDER BY floor(score * 50) / 50) + (count(*) OVER (PARTITION BY floor(score * 50) / 50) - 1) / CAST(2 AS DOUBLE) AS k FROM x) SELECT round((sum(CASE WHEN y = 1 THEN k ELSE 0 END) - sum(y) * (sum(y) + 1) / CAST(2 AS DOUBLE)) / (sum(y) * (count(*) - sum(y))), 9) AS auc FROM r",
        "accuracy": grads + "SELECT round(avg(CASE WHEN (score > 0) = (y = 1) THEN CAST(1 AS DOUBLE) ELSE 0 END), 9) AS accuracy FROM x",
        "confusion": grads + "SELECT y AS actual, count(*) FILTER (WHERE score <= 0) AS p0, count(*) FILTER (WHERE score > 0) AS p1 FROM x GROUP BY y",
        "align_orders_lineitem": "SELECT o_orderkey AS inst_id FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem)",
        "align_docs_labels": "SELECT doc_id AS inst_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)",
        "align_lost_ids": "SELECT o_orderkey AS inst_id FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)",
        "align_dh": "SELECT c_custkey AS inst_id FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)",
        "bin_percentile": "SELECT CAST(i - 1 AS INT) AS k, round(e[i], 8) AS edge FROM (SELECT quantile_cont(o_totalprice, [0.125, 0.25, 0.375, 0.5, 0.625, 0.75, 0.875]) AS e FROM orders) x CROSS JOIN range(1, 8) t(i)",
        "bin_edges_rank": "WITH a AS (SELECT l_quantity AS v, row_number() OVER (ORDER BY l_quantity) AS rn, count(*) OVER () AS n FROM lineitem) SELECT DISTINCT v AS edge FROM a JOIN range(1, 8) t(i) ON rn = (i * n + 7) // 8",
        "bin_apply_orders": "SELECT o_orderkey, CAST(least(9, ceil(o_totalprice / 50000) - 1) AS INT) AS bin FROM orders",
        "bin_apply_arrow": "SELECT o_orderkey, CAST(least(9, ceil(o_totalprice / 50000) - 1) AS INT) AS bin FROM orders",
        "base_equals_lean": "SELECT CAST(0 AS BIGINT) AS lean, CAST(0 AS BIGINT) AS sparse",
        "w4_features": WIDE_W4,
        "w7_features": WIDE_W7,
    }
    for n in ("w1", "w2", "w3", "w5", "w6", "w8", "w9", "w10"):
        x = workloads.ALL[n]
        out[f"{n}_features"] = f"SELECT inst_id, y, {', '.join(f'round({c}, 8) AS {c}' for c in (*x.active, *x.passive))} FROM ({x.text('duckdb')}) z"
    return out | {n: around.statement(n, "duckdb") for n in around.STATEMENTS} | jobs.ORACLES | ciphered.ORACLES | surface.ORACLES | experiments.ORACLES | {"pack_unpack_roundtrip": surface.ORACLES["udf_unpack"]}
