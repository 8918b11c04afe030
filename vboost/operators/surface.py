"""Operators around the methods that one SQL text for two engines cannot show: formats, layouts, hints, nested types,
Python functions over packed integers, and their plans."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..fixture import BASE_SQL, R, base_rows, fixed_rows
from ..functions import codec
from ..functions.codec import Budget
from ..he.base import Mock
from ..plans import protocol
from ..sources.io import bucketed, shared_dir, table
from . import histogram

#: A small budget, whose sums other engines hold in 128 bits.
SMALL = Budget(1 << 21, 20)


def src_csv_json_orc(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers written to and read from three formats under their schema; rows and sums of each."""
    df = table(spark, sf_dir, "customer")
    out = None
    for kind in ("csv", "json", "orc"):
        path = f"{shared_dir(spark)}/{kind}-{uuid.uuid4().hex}"
        df.write.format(kind).save(path)
        back = spark.read.schema(df.schema).format(kind).load(path)
        row = back.select(F.lit(kind).alias("format"), "c_custkey", "c_mktsegment").groupBy("format").agg(F.count("*").alias("n"), F.sum("c_custkey").alias("keys"), F.countDistinct("c_mktsegment").alias("segments"))
        out = row if out is None else out.unionByName(row)
    return out


def sink_bucketed(spark, sf_dir):
    """Two parties' frames bucketed by instance: their join has no exchange (`plan_of` shows it)."""
    one = bucketed(table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("inst_id"), "o_totalprice"), "inst_id")
    two = bucketed(table(spark, sf_dir, "lineitem").groupBy(F.col("l_orderkey").alias("inst_id")).agg(F.sum("l_quantity").alias("q")), "inst_id")
    return one.hint("merge").join(two, "inst_id").select("inst_id", "o_totalprice", F.round("q", 2).alias("q"))


def plan_of(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def _lines_of_parts(spark, sf_dir, hint: str) -> DataFrame:
    joined = table(spark, sf_dir, "lineitem").join(table(spark, sf_dir, "part").hint(hint), F.col("l_partkey") == F.col("p_partkey"))
    return joined.groupBy("p_brand").agg(F.count("*").alias("n"))


def join_shuffle_hash(spark, sf_dir):
    return _lines_of_parts(spark, sf_dir, "shuffle_hash")


def join_merge_hint(spark, sf_dir):
    return _lines_of_parts(spark, sf_dir, "merge")


def agg_sort_fallback(spark, sf_dir):
    """A customer's order keys as one sorted string: an aggregate over lists, bounded by a customer's orders."""
    keys = F.sort_array(F.collect_list("o_orderkey"))
    return table(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.array_join(F.transform(keys, lambda k: k.cast("string")), ",").alias("orders"))


def agg_approx_distinct(spark, sf_dir):
    """Distinct users by a sketch, beside the exact number."""
    return table(spark, sf_dir, "events").agg(F.approx_count_distinct("user_id", 0.01).alias("about"), F.countDistinct("user_id").alias("exact"))


def agg_percentiles(spark, sf_dir):
    x = table(spark, sf_dir, "orders").groupBy("o_orderstatus").agg(F.percentile("o_totalprice", F.array(F.lit(0.25), F.lit(0.5), F.lit(0.9))).alias("p"))
    return x.select("o_orderstatus", *[F.round(F.get("p", F.lit(i)), 6).alias(n) for i, n in enumerate(("q25", "q50", "q90"))])


def fn_array(spark, sf_dir):
    e = F.transform("embedding", lambda x: x.cast("double"))
    total = lambda a: F.aggregate(a, F.lit(0.0), lambda s, x: s + x)
    return table(spark, sf_dir, "embeddings").select(
        "vec_id",
        F.round(total(F.zip_with(e, e, lambda a, b: a * b)), 5).alias("norm2"),
        (F.array_position("embedding", F.array_max("embedding")) - 1).cast("int").alias("top"),
        F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"),
        F.round(total(F.slice(e, 1, 3)), 6).alias("head"),
    )


def fn_map(spark, sf_dir):
    """Sparse rows as maps: entries in the usual bin are left out and looked up as such."""
    codes = F.map_from_arrays(F.array(F.lit("flag"), F.lit("state"), F.lit("number")), F.array(F.ascii("l_returnflag"), F.ascii("l_linestatus"), F.col("l_linenumber")))
    rows = table(spark, sf_dir, "lineitem").withColumn("m", F.map_filter(codes, lambda k, v: ~((k == "number") & (v == 1))))
    return rows.groupBy(F.coalesce(F.try_element_at("m", F.lit("number")), F.lit(1)).alias("number"), F.size("m").alias("entries")).agg(F.count("*").alias("n"))


def fn_struct(spark, sf_dir):
    """Split infos nested by node and opened again."""
    info = F.struct(F.col("bin"), F.col("cnt"))
    nested = histogram.build(fixed_rows(spark, sf_dir)).groupBy("fid").agg(F.sort_array(F.collect_list(info)).alias("members"))  # at most a feature's bins
    return nested.select("fid", F.inline("members"))


def _int(raw: bytes) -> int:
    return int.from_bytes(raw, "big")


def pack_udf():
    @F.pandas_udf("binary")
    def pack(g: pd.Series, h: pd.Series) -> pd.Series:
        return pd.Series([codec.pack(a, b, SMALL).to_bytes(16, "big") for a, b in zip(g, h)])

    return pack


def udf_pack(spark, sf_dir):
    """Gradient and hessian of each order in one integer, in hexadecimal."""
    return base_rows(spark, sf_dir).select("inst_id", F.lower(F.hex(pack_udf()("g", "h"))).alias("packed"))


def udaf_he_sum(spark, sf_dir):
    """Sums of packed integers by a grouped function: no partial step, so one bin's rows meet (small data only)."""

    @F.pandas_udf("binary")
    def total(x: pd.Series) -> bytes:
        return sum(map(_int, x)).to_bytes(16, "big")

    packed = base_rows(spark, sf_dir).select(F.get("bins", F.lit(1)).alias("bin"), pack_udf()("g", "h").alias("x"))
    return packed.groupBy("bin").agg(total("x").alias("x")).select("bin", F.lower(F.hex("x")).alias("packed"))


def udf_unpack(spark, sf_dir):
    """The same sums, folded in tasks first, and opened to gradient and hessian."""

    @F.pandas_udf("struct<g:double,h:double>")
    def unpack(x: pd.Series, n: pd.Series) -> pd.DataFrame:
        sums = [codec.unpack(_int(a), int(b), SMALL) for a, b in zip(x, n)]
        return pd.DataFrame({"g": [g / 2.0**SMALL.r for g, _ in sums], "h": [h / 2.0**SMALL.r for _, h in sums]})

    return _packed_cells(spark, sf_dir).select("fid", "bin", "cnt", unpack("x", "cnt").alias("s")).select("fid", "bin", "cnt", "s.g", "s.h")


def _packed_cells(spark, sf_dir) -> DataFrame:
    mock = Mock(127)
    rows = base_rows(spark, sf_dir)
    enc = protocol.encrypt_rows(rows, mock, SMALL).join(rows.select("inst_id", "node", "bins"), "inst_id")
    return protocol.cipher_histogram(enc, mock).select("fid", "bin", "cnt", F.get("c", F.lit(0)).alias("x"))


def udf_partial_fold(spark, sf_dir):
    """Cells of packed integers: a fold in each task, one shuffle of cells, a streaming fold of what arrives."""
    return _packed_cells(spark, sf_dir).select("fid", "bin", "cnt", F.lower(F.expr("right(hex(x), 32)")).alias("packed"))


def expand_package(spark: SparkSession) -> None:
    """Register the table function that opens a package into its members, for SQL's LATERAL."""

    class Expand:
        def eval(self, package: bytes, members: int, bits: int) -> Iterator[tuple[int, str]]:
            value = int.from_bytes(package, "big")
            for k in range(members - 1, -1, -1):
                yield members - 1 - k, str(value >> (k * bits) & ((1 << bits) - 1))

    spark.udtf.register("expand_package", F.udtf(Expand, returnType="place int, value string"))


def udtf_expand_package(spark, sf_dir):
    """Six order prices in cents, packed to one binary by the Horner fold, and opened in SQL."""
    expand_package(spark)

    @F.pandas_udf("binary")
    def package(x: pd.Series) -> pd.Series:
        def fold(values: list[int]) -> bytes:
            acc = 0
            for v in values:
                acc = acc << 40 | int(v)
            return acc.to_bytes(30, "big")

        return pd.Series([fold(v) for v in x])

    cents = F.floor(F.col("o_totalprice") * 100).cast("long")
    groups = table(spark, sf_dir, "orders").groupBy(F.floor(F.col("o_orderkey") / 6).alias("pkg")).agg(F.transform(F.sort_array(F.collect_list(F.struct("o_orderkey", cents.alias("v")))), lambda s: s["v"]).alias("v"))
    groups.select("pkg", F.size("v").alias("n"), package("v").alias("c")).createOrReplaceTempView("packages")
    return spark.sql("SELECT pkg, x.place, CAST(x.value AS BIGINT) AS cents FROM packages, LATERAL expand_package(c, n, 40) x")


def sql_surface(spark, sf_dir):
    """Gains from cells in SQL text."""
    real = lambda c: codec.real(F.col(c), R).alias(c[0])
    histogram.build(fixed_rows(spark, sf_dir)).select("fid", "bin", "cnt", real("g0"), real("h0")).createOrReplaceTempView("cells")
    return spark.sql("""
        WITH s AS (SELECT fid, bin, sum(cnt) OVER w AS n_l, sum(g) OVER w AS gl, sum(h) OVER w AS hl, sum(cnt) OVER v AS n_t, sum(g) OVER v AS gt, sum(h) OVER v AS ht FROM cells
          WINDOW w AS (PARTITION BY fid ORDER BY bin ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), v AS (PARTITION BY fid))
        SELECT fid, bin, round(0.5 * (gl * gl / (hl + 1) + (gt - gl) * (gt - gl) / (ht - hl + 1) - gt * gt / (ht + 1)), 6) AS gain FROM s WHERE n_t > n_l""")


def bin_range_join(spark, sf_dir):
    """Orders by price range: a join on a coarse equal key and the range, in place of a comparison with every edge."""
    edges = spark.range(10).select(F.col("id").cast("int").alias("bin"), (F.col("id") * 50_000.0).alias("lo"), ((F.col("id") + 1) * 50_000.0).alias("hi"))
    near = edges.select("bin", "lo", "hi", F.explode(F.sequence(F.floor(F.col("lo") / 25_000), F.floor((F.col("hi") - 0.01) / 25_000))).alias("cell"))
    orders = table(spark, sf_dir, "orders").select("o_totalprice", F.floor(F.col("o_totalprice") / 25_000).alias("cell"))
    return orders.join(F.broadcast(near), "cell").where("o_totalprice >= lo AND o_totalprice < hi").groupBy("bin").agg(F.count("*").alias("n"))


QUERIES = {
    f.__name__: f
    for f in (
        src_csv_json_orc, sink_bucketed, join_shuffle_hash, join_merge_hint, agg_sort_fallback, agg_approx_distinct, agg_percentiles, fn_array, fn_map, fn_struct,
        udf_pack, udf_unpack, udf_partial_fold, udaf_he_sum, udtf_expand_package, sql_surface, bin_range_join,
    )
}
_PACKED = f"CAST(floor(({{g}} + 1) * 1048576) AS HUGEINT) * (CAST(1 AS HUGEINT) << {SMALL.b_h}) + CAST(floor(0.25 * 1048576) AS HUGEINT)"
_HEX = "lpad(lower(to_hex({x})), 32, '0')"
_LINES = "SELECT p_brand, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1"
ORACLES = {
    "src_csv_json_orc": "SELECT f AS format, count(*) AS n, CAST(sum(c_custkey) AS BIGINT) AS keys, count(DISTINCT c_mktsegment) AS segments FROM customer CROSS JOIN (VALUES ('csv'), ('json'), ('orc')) t(f) GROUP BY f",
    "sink_bucketed": "SELECT o_orderkey AS inst_id, o_totalprice, round(q, 2) AS q FROM orders JOIN (SELECT l_orderkey, sum(l_quantity) AS q FROM lineitem GROUP BY 1) x ON o_orderkey = l_orderkey",
    "join_shuffle_hash": _LINES,
    "join_merge_hint": _LINES,
    "agg_sort_fallback": "SELECT o_custkey, string_agg(CAST(o_orderkey AS VARCHAR), ',' ORDER BY o_orderkey) AS orders FROM orders GROUP BY 1",
    "agg_percentiles": "SELECT o_orderstatus, round(quantile_cont(o_totalprice, 0.25), 6) AS q25, round(quantile_cont(o_totalprice, 0.5), 6) AS q50, round(quantile_cont(o_totalprice, 0.9), 6) AS q90 FROM orders GROUP BY 1",
    "fn_array": "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 5) AS norm2, CAST(list_position(embedding, list_max(embedding)) - 1 AS INT) AS top, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INT) AS positive, round(CAST(embedding[1] AS DOUBLE) + embedding[2] + embedding[3], 6) AS head FROM embeddings",
    "fn_map": "SELECT l_linenumber AS number, CAST(CASE WHEN l_linenumber = 1 THEN 2 ELSE 3 END AS INT) AS entries, count(*) AS n FROM lineitem GROUP BY 1, 2",
    "fn_struct": f"WITH {BASE_SQL} SELECT fid, bin, cnt FROM c",
    "udf_pack": f"WITH {BASE_SQL} SELECT inst_id, {_HEX.format(x=_PACKED.format(g='CAST(0.5 AS DOUBLE) - y'))} AS packed FROM b",
    "udf_unpack": f"WITH {BASE_SQL} SELECT fid, bin, cnt, g, h FROM c",
    "udf_partial_fold": f"WITH {BASE_SQL}, p AS (SELECT fid, bin, count(*) AS cnt, sum({_PACKED.format(g='CAST(0.5 AS DOUBLE) - y')}) AS x FROM f GROUP BY 1, 2) SELECT fid, bin, cnt, {_HEX.format(x='CAST(x AS HUGEINT)')} AS packed FROM p",
    "udaf_he_sum": f"WITH {BASE_SQL}, p AS (SELECT b1 AS bin, sum({_PACKED.format(g='CAST(0.5 AS DOUBLE) - y')}) AS x FROM b GROUP BY 1) SELECT bin, {_HEX.format(x='CAST(x AS HUGEINT)')} AS packed FROM p",
    "udtf_expand_package": "SELECT CAST(floor(o_orderkey / 6) AS BIGINT) AS pkg, CAST(row_number() OVER (PARTITION BY floor(o_orderkey / 6) ORDER BY o_orderkey) - 1 AS INT) AS place, CAST(floor(o_totalprice * 100) AS BIGINT) AS cents FROM orders",
    "sql_surface": f"WITH {BASE_SQL} SELECT fid, bin, round(gain, 6) AS gain FROM gain",
    "bin_range_join": "SELECT CAST(floor(o_totalprice / 50000) AS INT) AS bin, count(*) AS n FROM orders WHERE o_totalprice < 500000 GROUP BY 1",
}
