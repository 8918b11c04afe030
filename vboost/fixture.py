"""The fixture of exact first-tree sums, its rows, and its trees in SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import histogram
from .plans.params import FederatedSpec, Params, Party
from .plans.tree import Tree
from .sources import workloads

R = 53
#: Bins by plain arithmetic, a planted label, and the first tree's exact gradients (p = 1/2).
BASE_SQL = """
b AS (SELECT o_orderkey AS inst_id, CASE WHEN (o_totalprice > 250000) <> (((o_orderkey * 7919 + 104729) % 100) < 12) THEN 1 ELSE 0 END AS y,
  CAST(least(31, floor(o_totalprice / CAST(500000.0 AS DOUBLE) * 32)) AS INT) AS b0, CAST(substr(o_orderpriority, 1, 1) AS INT) AS b1, CAST(floor(dayofyear(o_orderdate) / 12) AS INT) AS b2 FROM orders),
f AS (SELECT inst_id, y, 0 AS fid, b0 AS bin FROM b UNION ALL SELECT inst_id, y, 1, b1 FROM b UNION ALL SELECT inst_id, y, 2, b2 FROM b),
c AS (SELECT fid, bin, count(*) AS cnt, sum(CAST(0.5 AS DOUBLE) - y) AS g, sum(CAST(0.25 AS DOUBLE)) AS h FROM f GROUP BY fid, bin),
s AS (SELECT fid, bin, sum(cnt) OVER w AS cnt_l, sum(g) OVER w AS gl, sum(h) OVER w AS hl, sum(cnt) OVER v AS cnt_t, sum(g) OVER v AS gt, sum(h) OVER v AS ht FROM c
  WINDOW w AS (PARTITION BY fid ORDER BY bin ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), v AS (PARTITION BY fid)),
gain AS (SELECT *, 0.5 * (gl * gl / (hl + 1) + (gt - gl) * (gt - gl) / (ht - hl + 1) - gt * gt / (ht + 1)) AS gain FROM s WHERE cnt_t > cnt_l)
"""
SPEC = FederatedSpec((Party("active", "active", ("b0",)), Party("passive", "passive", ("b1", "b2"))))
PLAIN = Params(goss=None, max_depth=2, trees=1)


def base_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """inst_id, y, bins, g, h, node of the base fixture."""
    workloads.views(spark, sf_dir)
    b = spark.sql(f"WITH {BASE_SQL.split('f AS (SELECT inst_id')[0].strip().rstrip(',')} SELECT * FROM b")
    return b.select("inst_id", "y", F.array("b0", "b1", "b2").alias("bins"), (0.5 - F.col("y")).cast("double").alias("g"), F.lit(0.25).cast("double").alias("h"), F.lit(0).alias("node"))


def fixed_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    return histogram.fixed_columns(base_rows(spark, sf_dir), R)


def tree_frame(spark: SparkSession, tree: Tree, reg_lambda: float) -> DataFrame:
    data = [(i, n.fid, n.bin, n.count, round(tree.weight(i, reg_lambda)[0], 9)) for i, n in sorted(tree.nodes.items())]
    return spark.createDataFrame(data, "node int, fid int, bin int, cnt long, w double")


def tree_sql(root: str, below: str) -> str:
    """A depth-2 tree in SQL; root and below: the feature numbers that may split there."""
    return f"""
WITH {BASE_SQL},
r AS (SELECT fid, bin FROM gain WHERE fid IN ({root}) ORDER BY round(gain, 9) DESC, fid, bin LIMIT 1),
n1 AS (SELECT f.*, CASE WHEN (CASE r.fid WHEN 0 THEN b0 WHEN 1 THEN b1 ELSE b2 END) <= r.bin THEN 1 ELSE 2 END AS node FROM f JOIN b USING (inst_id) CROSS JOIN r),
c1 AS (SELECT node, fid, bin, count(*) AS cnt, sum(CAST(0.5 AS DOUBLE) - y) AS g, sum(CAST(0.25 AS DOUBLE)) AS h FROM n1 GROUP BY 1, 2, 3),
s1 AS (SELECT node, fid, bin, sum(cnt) OVER w AS cnt_l, sum(g) OVER w AS gl, sum(h) OVER w AS hl, sum(cnt) OVER v AS cnt_t, sum(g) OVER v AS gt, sum(h) OVER v AS ht FROM c1
  WINDOW w AS (PARTITION BY node, fid ORDER BY bin ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), v AS (PARTITION BY node, fid)),
k1 AS (SELECT *, 0.5 * (gl * gl / (hl + 1) + (gt - gl) * (gt - gl) / (ht - hl + 1) - gt * gt / (ht + 1)) AS gain FROM s1 WHERE cnt_t > cnt_l AND fid IN ({below})),
q1 AS (SELECT * FROM k1 WHERE gain > 0 QUALIFY row_number() OVER (PARTITION BY node ORDER BY round(gain, 9) DESC, fid, bin) = 1),
t AS (SELECT 0 AS node, count(*) AS cnt, sum(CAST(0.5 AS DOUBLE) - y) AS g, sum(CAST(0.25 AS DOUBLE)) AS h FROM b),
one AS (SELECT node, count(*) AS cnt, sum(CAST(0.5 AS DOUBLE) - y) AS g, sum(CAST(0.25 AS DOUBLE)) AS h FROM n1 WHERE fid = 0 GROUP BY node),
two AS (SELECT 2 * node + 1 AS node, cnt_l AS cnt, gl AS g, hl AS h FROM q1 UNION ALL SELECT 2 * node + 2, cnt_t - cnt_l, gt - gl, ht - hl FROM q1)
SELECT t.node, r.fid, r.bin, CAST(cnt AS BIGINT) AS cnt, round(-g / (h + 1), 9) AS w FROM t CROSS JOIN r
UNION ALL SELECT one.node, q1.fid, q1.bin, CAST(cnt AS BIGINT), round(-g / (h + 1), 9) FROM one LEFT JOIN q1 USING (node)
UNION ALL SELECT node, NULL, NULL, CAST(cnt AS BIGINT), round(-g / (h + 1), 9) FROM two
"""
