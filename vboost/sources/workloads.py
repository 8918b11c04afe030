"""Experiment workloads on the given tables: party columns and labels planted across the parties.

The SQL keeps to what Spark and DuckDB compute alike, so the same text is the plan here and the oracle there.
"""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.params import FederatedSpec, Party
from .io import small_batches, spread

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "labels")


def flip(percent: int, of: str = "inst_id") -> str:
    return f"(((({of} % 1000003) * 7919 + 104729) % 100) < {percent})"


def _planted(condition: str, percent: int) -> str:
    return f"CAST(CASE WHEN ({condition}) <> {flip(percent)} THEN 1 ELSE 0 END AS INT)"


D = "CAST({} AS DOUBLE)".format

_ORDER_COLUMNS = f"""
  {D('o_totalprice')} AS o_totalprice, {D('dayofyear(o_orderdate)')} AS o_day, {D('year(o_orderdate)')} AS o_year,
  {D('substr(o_orderpriority, 1, 1)')} AS o_prio, {D("CASE o_orderstatus WHEN 'F' THEN 0 WHEN 'O' THEN 1 ELSE 2 END")} AS o_status"""

_SEGMENT = "CASE c_mktsegment WHEN 'AUTOMOBILE' THEN 0 WHEN 'BUILDING' THEN 1 WHEN 'FURNITURE' THEN 2 WHEN 'HOUSEHOLD' THEN 3 ELSE 4 END"

W1 = f"""
WITH n AS (SELECT o_custkey, count(*) AS c_orders FROM orders GROUP BY o_custkey), x AS (
  SELECT o.o_orderkey AS inst_id, {_ORDER_COLUMNS},
    {D('c_acctbal')} AS c_acctbal, {D('c_nationkey')} AS c_nation, {D('n_regionkey')} AS c_region, {D(_SEGMENT)} AS c_segment, {D('c_orders')} AS c_orders
  FROM orders o JOIN customer c ON o.o_custkey = c.c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN n ON n.o_custkey = o.o_custkey)
SELECT *, {_planted(f"CAST(2.0 AS DOUBLE) * o_totalprice / {D('500000')} + {D('2')} * (c_acctbal + {D('1000')}) / {D('11000')} + (CASE WHEN c_segment >= 3 THEN {D('1')} ELSE {D('0')} END) * (CASE WHEN o_prio <= 2 THEN {D('1')} ELSE {D('-0.5')} END) > {D('2')}", 12)} AS y FROM x
"""

#: A line has no key: 60 bits of a digest of its whole row, without any sort over the table.
_LINE_ROW = "concat_ws('/', l_orderkey, l_partkey, l_suppkey, l_linenumber, CAST(round(l_quantity * 100) AS BIGINT), CAST(round(l_extendedprice * 100) AS BIGINT), CAST(round(l_discount * 100) AS BIGINT), CAST(round(l_tax * 100) AS BIGINT), l_returnflag, l_linestatus, CAST(l_shipdate AS DATE))"
_DIGEST = {"spark": f"CAST(conv(substr(md5({_LINE_ROW}), 1, 15), 16, 10) AS BIGINT)", "duckdb": f"CAST('0x' || substr(md5({_LINE_ROW}), 1, 15) AS BIGINT)"}
_LINES = f"""
SELECT {{digest}} AS inst_id,
  l_quantity, l_extendedprice, l_discount, l_tax, {D('l_linenumber')} AS l_linenumber, {D('ascii(l_returnflag)')} AS l_flag, {D('ascii(l_linestatus)')} AS l_state,
  {D('year(l_shipdate)')} AS l_year, {D('month(l_shipdate)')} AS l_month, {D('dayofyear(l_shipdate)')} AS l_day,
  {D('p_size')} AS p_size, p_retailprice, {D('ascii(p_type)')} AS p_kind, {D("replace(p_brand, 'Brand#', '')")} AS p_brand_no, s_acctbal, {D('s_nationkey')} AS s_nation,
  {_ORDER_COLUMNS.strip()}, c_acctbal, {D('ascii(c_mktsegment)')} AS c_segment, {D('c_nationkey')} AS c_nation
FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey
"""

W2 = f"""
WITH x AS ({_LINES})
SELECT *, {_planted(f"{D('2')} * l_quantity / {D('50')} + {D('1.5')} * p_size / {D('50')} + (l_discount / {D('0.1')}) * (c_acctbal + {D('1000')}) / {D('11000')} > {D('2')}", 12)} AS y FROM x
"""

W3 = f"""
WITH x AS ({_LINES})
SELECT *, l_extendedprice * ({D('1')} - l_discount) AS l_net, l_tax * l_extendedprice AS l_duty, l_extendedprice / l_quantity AS l_unit,
  {_planted(f"(l_quantity - {D('25.5')}) / {D('24.5')} * (p_size - {D('25.5')}) / {D('24.5')} + {D('0.6')} * (l_extendedprice - {D('50000')}) / {D('50000')} * (o_totalprice - {D('250000')}) / {D('250000')} + {D('0.3')} * (c_acctbal - {D('4500')}) / {D('5500')} > {D('0')}", 15)} AS y FROM x
"""

_SPANS = (2, 5, 10, 20, 50)
_OVER = "OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN {} PRECEDING AND CURRENT ROW)"
_LAGS = ", ".join(f"coalesce(lag(value, {k}) OVER (PARTITION BY user_id ORDER BY ts, event_id), {D('0')}) AS e_lag{k}" for k in range(1, 6))
_STATS = ", ".join(f"{f}(value) {_OVER.format(k)} AS u_{f}{k}" for k in _SPANS for f in ("avg", "min", "max", "sum"))
W5 = f"""
WITH e AS (SELECT event_id AS inst_id, value AS e_value, {D('hour(ts)')} AS e_hour, {D('minute(ts)')} AS e_minute, {D('floor(second(ts))')} AS e_second, {D('dayofyear(ts)')} AS e_day,
  {D('user_id')} AS u_user, {{k}} AS u_k, {D('ascii(event_type)')} AS u_type, {_LAGS}, {_STATS},
  {D('count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)')} AS u_seen FROM events),
x AS (SELECT *, {D('e_day % 7')} AS e_week, e_hour * 60 + e_minute AS e_clock, e_value * e_value AS e_square, {D('floor(e_value / 10)')} AS e_tens, e_value - floor(e_value / 10) * 10 AS e_units,
  {D('floor(e_hour / 6)')} AS e_quarter, {", ".join(f"e_value - e_lag{k} AS e_diff{k}" for k in range(1, 6))}, e_value * e_hour AS e_vh, e_value * e_minute AS e_vm, e_value / (1 + e_hour) AS e_vr FROM e)
SELECT *, CAST(CASE WHEN {flip(2)} THEN inst_id % 11 ELSE least(CAST(floor({D('11')} * least({D('0.5')} * e_hour / {D('23')} + {D('0.5')} * u_k / {D('99')}, {D('0.999999')})) AS INT), 10) END AS INT) AS y FROM x
"""

_LINE_MORE = {
    "l_net": f"l_extendedprice * ({D('1')} - l_discount)", "l_duty": "l_tax * l_extendedprice", "l_unit": "l_extendedprice / l_quantity", "l_q2": "l_quantity * l_quantity",
    "l_qd": "l_quantity * l_discount", "l_qt": "l_quantity * l_tax", "l_dt": "l_discount * l_tax", "l_pd": "l_extendedprice * l_discount", "l_qn": "l_quantity + l_linenumber", "l_pn": "l_extendedprice / l_linenumber",
    "l_kilo": D("floor(l_extendedprice / 1000)"), "l_rest": "l_extendedprice - floor(l_extendedprice / 1000) * 1000", "l_half": D("floor((l_month - 1) / 6)"), "l_week": D("floor(l_day / 7)"), "l_since": "(l_year - 1992) * 12 + l_month", "l_fs": "l_flag * l_state", "l_tens": D("floor(l_quantity / 10)"),
}
_OTHER_MORE = {
    "p_unit": "p_retailprice / p_size", "p_mass": "p_retailprice * p_size", "p_tens": D("floor(p_size / 10)"), "s_gap": "s_acctbal - c_acctbal", "s_sum": "s_acctbal + c_acctbal", "o_share": "p_retailprice / o_totalprice", "o_kilo": D("floor(o_totalprice / 1000)"),
    "o_since": "(o_year - 1992) * 366 + o_day", "o_week": D("floor(o_day / 7)"), "o_ps": "o_prio * 3 + o_status", "c_nb": "c_nation - s_nation", "c_kilo": D("floor(c_acctbal / 1000)"), "p_sb": "p_size * p_brand_no",
}
_MORE = ", ".join(f"{v} AS {k}" for k, v in {**_LINE_MORE, **_OTHER_MORE}.items())
W6 = f"""
WITH x AS ({_LINES})
SELECT *, {_MORE}, CAST(CASE WHEN {flip(15)} THEN inst_id % 7 ELSE least(CAST(floor({D('7')} * ({D('0.5')} * (l_quantity - {D('1')}) / {D('49')} + {D('0.5')} * (p_size - {D('1')}) / {D('49')})) AS INT), 6) END AS INT) AS y FROM x
"""

W8 = f"""
WITH p AS (SELECT l_orderkey, {D('count(*)')} AS q_lines, sum(l_quantity) AS q_quantity, max(l_discount) AS q_discount, {D('count(DISTINCT l_partkey)')} AS q_parts FROM lineitem GROUP BY l_orderkey),
x AS (SELECT o_orderkey AS inst_id, {_ORDER_COLUMNS}, q_lines, q_quantity, q_discount, q_parts FROM orders JOIN p ON o_orderkey = l_orderkey)
SELECT *, {_planted(f"o_totalprice / {D('500000')} + q_quantity / {D('200')} > {D('1')}", 12)} AS y FROM x
"""

_GRAMS = {"the": " the ", "of": " of ", "de": " de ", "und": " und ", "la": " la "}
W9 = f"""
WITH t AS (SELECT doc_id AS inst_id, n_chars, lang, length(text) AS n, length(regexp_replace(text, '[.,;:!?]', ''{{g}})) AS plain, length(regexp_replace(text, '[0-9]', ''{{g}})) AS undigited,
  length(replace(text, ' ', '')) AS packed, length(regexp_replace(text, '[#*$%&|<>]', ''{{g}})) AS unsigned_n, length(replace(text, chr(10), '')) AS unbroken, {{distinct}} AS words,
  {", ".join(f"length(text) - length(replace(text, '{v}', '')) AS has_{k}" for k, v in _GRAMS.items())}, source FROM documents)
SELECT inst_id, {D('n_chars')} AS a_chars, {D('n - plain')} / n AS a_marks, {D("replace(source, 'src', '')")} AS a_source, {D("CASE lang WHEN 'en' THEN 0 WHEN 'de' THEN 1 WHEN 'fr' THEN 2 ELSE 3 END")} AS a_lang,
  {D('n - undigited')} / n AS b_digits, {D('n - packed')} / n AS b_spaces, {D('n - unsigned_n')} / n AS b_signs, {D('n - unbroken')} / n AS b_breaks, {D('words')} / (n - packed + 1) AS b_distinct,
  {", ".join(f"{D(f'has_{k}')} / n AS b_{k}" for k in _GRAMS)}, quality AS y, toxic
FROM t JOIN labels ON inst_id = doc_id WHERE n > 0
"""

W10 = f"""
SELECT p_partkey AS inst_id, {D('p_size')} AS p_size, {D('ascii(p_type)')} AS p_kind, p_retailprice, CAST(replace(p_brand, 'Brand#', '') AS INT) - 1 AS y FROM part
"""

_LINE_ACTIVE = ("l_quantity", "l_extendedprice", "l_discount", "l_tax")
_LINE_PASSIVE = ("p_size", "p_retailprice", "p_kind", "p_brand_no", "s_acctbal", "s_nation", "o_totalprice", "o_prio", "o_status", "o_day", "o_year", "c_acctbal", "c_segment", "c_nation")
_ORDER_ACTIVE = ("o_totalprice", "o_day", "o_year", "o_prio", "o_status")


_EVENT_ACTIVE = ("e_value", "e_hour", "e_minute", "e_second", "e_day", "e_week", "e_clock", "e_square", "e_tens", "e_units", "e_quarter", *[f"e_lag{k}" for k in range(1, 6)], *[f"e_diff{k}" for k in range(1, 6)], "e_vh", "e_vm", "e_vr")


@dataclass(frozen=True)
class Workload:
    name: str
    sql: str | None
    active: tuple[str, ...]
    passive: tuple[str, ...]
    classes: int = 1

    @property
    def spec(self) -> FederatedSpec:
        return FederatedSpec((Party("active", "active", self.active), Party("passive", "passive", self.passive)))

    def load(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        if self.sql is None:
            return _wide(spark, sf_dir, self)
        views(spark, sf_dir)
        return spark.sql(self.text("spark"))

    def matrix(self, spark: SparkSession, sf_dir: str, keep: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
        """inst_id, y, held, and the features: a column each, or for wide workloads one array column `features`, in the spec's order.

        held: the test rows of `split`. keep: what writes rows that are read several times. Of lines it gets the joined
        columns alone, and what is reckoned from a row is reckoned again; products of embeddings are never kept.
        """
        held = (part() >= 80).alias("held")
        if self.sql is None:
            return _wide_matrix(spark, sf_dir, self).select("*", held)
        text = self.text("spark")
        for t in (t for t in TABLES if re.search(rf"\b{t}\b", text)):
            rows = spark.read.parquet(f"{sf_dir}/{t}.parquet")
            (spread(rows) if t in ("orders", "lineitem") else rows).createOrReplaceTempView(t)
        lines = _LINES.replace("{digest}", _DIGEST["spark"])
        if keep is None or f"({lines})" not in text:
            rows = spark.sql(text).select("inst_id", "y", *self.spec.columns, held)
            return rows if keep is None else keep(rows)
        keep(spark.sql(lines).select("*", held)).createOrReplaceTempView("vboost_lines")
        return spark.sql(text.replace(f"({lines})", "(SELECT * FROM vboost_lines)")).select("inst_id", "y", *self.spec.columns, "held")

    def text(self, engine: str) -> str:
        k = D("get_json_object(props, '$.k')") if engine == "spark" else D("json_extract_string(props, '$.k')")
        distinct = "size(array_distinct(split(text, ' ')))" if engine == "spark" else "len(list_distinct(string_split(text, ' ')))"
        return self.sql.replace("{k}", k).replace("{g}", "" if engine == "spark" else ", 'g'").replace("{distinct}", distinct).replace("{digest}", _DIGEST[engine])


def views(spark: SparkSession, sf_dir: str) -> None:
    for t in TABLES:
        spark.read.parquet(f"{sf_dir}/{t}.parquet").createOrReplaceTempView(t)


def _wide(spark: SparkSession, sf_dir: str, w: Workload) -> DataFrame:
    """Embedding coordinates and their pairwise products, as many as the workload names, and a planted label."""
    e = lambda i: F.get("embedding", F.lit(i)).cast("double")
    pairs = [(i, j) for i in range(64) for j in range(i, 64)]
    made = []
    for c in sorted(w.active + w.passive):
        k = int(c[1:])
        if k < 64:
            x = e(k)
        else:  # products of two coordinates, then of these with the first
            i, j = pairs[(k - 64) % len(pairs)]
            x = e(i) * e(j) if k - 64 < len(pairs) else e(i) * e(j) * e(0)
        made.append(x.alias(c))
    return spark.read.parquet(f"{sf_dir}/embeddings.parquet").select(F.col("vec_id").alias("inst_id"), *made, _wide_label(w).alias("y"))


def _wide_label(w: Workload) -> Column:
    e = lambda i: F.get("embedding", F.lit(i)).cast("double")
    if w.classes > 1:
        first = F.transform(F.slice("embedding", 1, w.classes), lambda x: x)
        return (F.array_position(first, F.array_max(first)) - 1).cast("int")
    return F.when((e(0) + e(1) + e(2) - e(3) + 4 * e(4) * e(5) > 0) != F.expr(flip(8, "vec_id")), 1).otherwise(0)


def _wide_matrix(spark: SparkSession, sf_dir: str, w: Workload) -> DataFrame:
    """The same features by array products on Arrow batches: thousands of columns take Spark long to plan."""
    pairs = np.array([(i, j) for i in range(64) for j in range(i, 64)])
    k = np.array([int(c[1:]) for c in w.spec.columns])
    i, j = np.where(k < 64, (k, k), pairs[(k - 64) % len(pairs)].T)
    squared, cubed = k >= 64, k - 64 >= len(pairs)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = batch.num_rows
            for at in range(0, n, 256):
                some = batch.slice(at, 256)
                e = some.column("e").flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(some.num_rows, 64)
                x = np.where(squared, e[:, i] * e[:, j], e[:, i])
                x[:, cubed] *= e[:, :1]
                lists = pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * x.shape[1]), pa.array(x.ravel()))
                yield pa.RecordBatch.from_arrays([some.column("inst_id"), some.column("y"), lists], names=["inst_id", "y", "features"])

    small_batches(spark)
    e = F.transform(F.sequence(F.lit(0), F.lit(63)), lambda q: F.get("embedding", q).cast("double"))
    rows = spread(spark.read.parquet(f"{sf_dir}/embeddings.parquet")).select(F.col("vec_id").alias("inst_id"), _wide_label(w).alias("y"), e.alias("e"))
    return rows.mapInArrow(run, f"inst_id {rows.schema['inst_id'].dataType.simpleString()}, y int, features array<double>")


def wide(name: str, features: int, classes: int = 1) -> Workload:
    names = [f"x{i:04d}" for i in range(features)]
    return Workload(name, None, tuple(names[0::2]), tuple(names[1::2]), classes)


ALL = {
    "w1": Workload("w1", W1, _ORDER_ACTIVE, ("c_acctbal", "c_nation", "c_region", "c_segment", "c_orders")),
    "w2": Workload("w2", W2, _LINE_ACTIVE, _LINE_PASSIVE),
    "w3": Workload("w3", W3, (*_LINE_ACTIVE, "l_linenumber", "l_flag", "l_state", "l_year", "l_month", "l_day", "l_net", "l_duty", "l_unit"), _LINE_PASSIVE),
    "w4": wide("w4", 2000),
    "w5": Workload("w5", W5, _EVENT_ACTIVE, ("u_user", "u_k", "u_type", "u_seen", *[f"u_{f}{k}" for k in _SPANS for f in ("avg", "min", "max", "sum")]), 11),
    "w6": Workload("w6", W6, (*_LINE_ACTIVE, "l_linenumber", "l_flag", "l_state", "l_year", "l_month", "l_day", *_LINE_MORE), (*_LINE_PASSIVE, *_OTHER_MORE), 7),
    "w7": wide("w7", 3072, 10),
    "w8": Workload("w8", W8, _ORDER_ACTIVE, ("q_lines", "q_quantity", "q_discount", "q_parts")),
    "w9": Workload("w9", W9, ("a_chars", "a_marks", "a_source", "a_lang"), ("b_digits", "b_spaces", "b_signs", "b_breaks", "b_distinct", *[f"b_{k}" for k in _GRAMS])),
    "w10": Workload("w10", W10, ("p_size",), ("p_kind", "p_retailprice"), 25),
}


def part() -> Column:
    """A number from 0 to 99 by a digest of the id: stable across runs and engines."""
    return F.conv(F.substring(F.md5(F.col("inst_id").cast("string")), 1, 8), 16, 10).cast("long") % 100


def split(df: DataFrame, share: int = 80) -> tuple[DataFrame, DataFrame]:
    """Training and test rows by `part`."""
    return df.where(part() < share), df.where(part() >= share)


def replicated(df: DataFrame, times: int) -> DataFrame:
    """The frame `times` over, for scale runs; copies get ids of their own."""
    if times == 1:
        return df
    return df.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(times - 1)))).withColumn("inst_id", F.col("inst_id") * times + F.col("copy")).drop("copy")


def totals(w: Workload, df: DataFrame) -> DataFrame:
    """Sums of every feature of a wide workload by number, and its label counts as fid = -1 - y: fid, total."""
    columns = sorted(w.active + w.passive)
    sums = df.agg(*[F.sum(c).alias(c) for c in columns]).select(F.array(*columns).alias("x"))
    out = sums.select(F.posexplode("x").alias("fid", "total")).select("fid", (F.round("total", 5) + 0.0).alias("total"))
    return out.union(df.groupBy((-1 - F.col("y")).cast("int").alias("fid")).agg(F.count("*").cast("double").alias("total")))


def totals_sql(features: int, y: str) -> str:
    return f"""
WITH p AS (SELECT i, j, row_number() OVER (ORDER BY i, j) + 63 AS k FROM range(64) a(i) JOIN range(64) b(j) ON i <= j),
q AS (SELECT k, i, j, 0 AS three FROM p UNION ALL SELECT k + 2080, i, j, 1 FROM p),
e AS (SELECT list_transform(embedding, lambda v: CAST(v AS DOUBLE)) AS e, {y} AS y FROM embeddings)
SELECT CAST(k AS INT) AS fid, round(sum(e[k + 1]), 5) + 0 AS total FROM e CROSS JOIN range(64) r(k) GROUP BY k
UNION ALL SELECT CAST(k AS INT), round(sum(e[i + 1] * e[j + 1] * CASE WHEN three = 1 THEN e[1] ELSE 1 END), 5) + 0 FROM e CROSS JOIN q WHERE k < {features} GROUP BY k
UNION ALL SELECT CAST(-1 - y AS INT), CAST(count(*) AS DOUBLE) FROM e GROUP BY y
"""
