"""Streaming feature windows and online scoring. The queries drain the table once and return what the sink holds."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

from ..operators import binning
from ..plans.grow import train
from ..plans.params import FederatedSpec, Params, Party
from ..sources.io import shared_dir

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a stream. Watermarks need a timestamp with a zone: the session's is taken as UTC."""
    raw = spark.readStream.schema(SCHEMA).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run the stream to its end into the shared folder; batches are files, so a restart repeats none."""
    spark = stream.sparkSession
    at = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    if mode == "append":
        q = stream.writeStream.format("parquet").option("checkpointLocation", f"{at}-state").option("path", at).trigger(availableNow=True).start()
    else:

        def upsert(batch: DataFrame, epoch: int) -> None:
            batch.write.mode("overwrite").parquet(f"{at}/{epoch}")

        q = stream.writeStream.outputMode(mode).foreachBatch(upsert).option("checkpointLocation", f"{at}-state").trigger(availableNow=True).start()
    q.awaitTermination()
    if mode == "append":
        return spark.read.schema(stream.schema).parquet(at)
    last = max((q.lastProgress or {}).get("batchId", 0), 0)
    return spark.read.schema(stream.schema).parquet(f"{at}/{last}")


def _epoch(c: str):
    return F.unix_timestamp(c).alias(c)


def st_tumbling(spark, sf_dir):
    w = events(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n"))
    return drained(w.select(F.col("w.start").alias("start"), "event_type", "n"), "complete").select(_epoch("start"), "event_type", "n")


def st_sliding(spark, sf_dir):
    w = events(spark, sf_dir).groupBy(F.window("ts", "1 day", "12 hours").alias("w")).agg(F.count("*").alias("n"))
    return drained(w.select(F.col("w.start").alias("start"), "n"), "complete").select(_epoch("start"), "n")


def st_dedup(spark, sf_dir):
    return drained(events(spark, sf_dir).withWatermark("ts", "40 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id"))


def st_static_join(spark, sf_dir):
    customers = spark.read.parquet(f"{sf_dir}/customer.parquet").select("c_custkey", "c_mktsegment")
    joined = events(spark, sf_dir).join(customers, F.col("user_id") == F.col("c_custkey"))
    return drained(joined.select("event_id", "c_mktsegment"))


def st_session(spark, sf_dir):
    """Sessions of a user with gaps below six hours."""
    w = events(spark, sf_dir).withWatermark("ts", "1 hour").groupBy("user_id", F.session_window("ts", "6 hours").alias("w")).agg(F.count("*").alias("n"))
    return drained(w.select("user_id", F.col("w.start").alias("start"), "n"), "complete").select("user_id", _epoch("start"), "n")


def st_stream_join(spark, sf_dir):
    """Clicks followed by a purchase of the same user within an hour: both sides with watermarks."""
    side = lambda kind, p: events(spark, sf_dir).where(F.col("event_type") == kind).withWatermark("ts", "40 days").select(F.col("event_id").alias(f"{p}_id"), F.col("user_id").alias(f"{p}_user"), F.col("ts").alias(f"{p}_ts"))
    joined = side("click", "c").join(side("purchase", "p"), F.expr("c_user = p_user AND p_ts >= c_ts AND p_ts <= c_ts + INTERVAL 1 HOUR"))
    return drained(joined.select("c_id", "p_id"))


def _score_frame(df: DataFrame) -> DataFrame:
    """The features of an event that the online model reads."""
    return df.select(F.col("event_id").alias("inst_id"), "value", F.hour("ts").cast("double").alias("hour"), F.minute("ts").cast("double").alias("minute"), F.dayofyear("ts").cast("double").alias("day"))


def online_model(spark, sf_dir, trees: int = 3):
    """A small model of a planted label: large values late in the day."""
    history = _score_frame(spark.read.parquet(f"{sf_dir}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp")))
    data = history.withColumn("y", (F.col("value") / 100 + F.col("hour") / 24 > 0.8).cast("int"))
    spec = FederatedSpec((Party("shop", "active", ("value", "hour")), Party("web", "passive", ("minute", "day"))))
    return data, train(data, spec, Params(trees=trees, max_depth=3, goss=None))


def _scored(df: DataFrame, model) -> DataFrame:
    bins = F.array(*[binning.bin_column(F.col(c), e) for c, e in zip(model.spec.columns, model.edges)])
    return df.withColumn("bins", bins).select("inst_id", model.score_column().alias("score"))


def st_score(spark, sf_dir):
    """Online scoring: the trained model as one expression over the stream, beside the batch scores of the same events."""
    data, model = online_model(spark, sf_dir)
    streamed = drained(_scored(_score_frame(events(spark, sf_dir)), model))
    both = streamed.join(model.predict(data, ["inst_id"]).withColumnRenamed("score", "batch"), "inst_id")
    return both.agg(F.count("*").alias("n"), F.count_if(F.abs(F.col("score") - F.col("batch")) > 1e-12).alias("differing"))


def sink_stream_upsert(spark, sf_dir):
    """Scored events through foreachBatch: a batch's files are named by its number, so writing it again changes nothing."""
    _, model = online_model(spark, sf_dir, 1)
    at = f"{shared_dir(spark)}/upsert-{uuid.uuid4().hex}"

    def write(batch: DataFrame, epoch: int) -> None:
        for _ in range(2):  # as after a failure between the write and the commit
            batch.write.mode("overwrite").parquet(f"{at}/batch={epoch}")

    stream = _scored(_score_frame(events(spark, sf_dir)), model)
    stream.writeStream.foreachBatch(write).option("checkpointLocation", f"{at}-state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(at).agg(F.count("*").alias("n"), F.countDistinct("inst_id").alias("ids"))


def st_late_data(spark, sf_dir):
    """Days of events that arrive in the wrong order: what the watermark closed stays closed, and the rest is dropped.

    The second half of the year's events arrives first, the first half after it in another batch.
    """
    at = f"{shared_dir(spark)}/late-{uuid.uuid4().hex}"
    rows = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    middle = rows.agg(F.percentile_approx(F.unix_timestamp("ts"), 0.5, 10_000)).first()[0]
    halves = (F.unix_timestamp("ts") > middle, F.unix_timestamp("ts") <= middle)
    state, out = f"{at}-state", f"{at}-out"
    for k, half in enumerate(halves):
        rows.where(half).coalesce(1).write.mode("append").parquet(f"{at}-in")
        stream = spark.readStream.schema(rows.schema).parquet(f"{at}-in").withWatermark("ts", "1 hour")
        days = stream.groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")
        days.writeStream.format("parquet").option("checkpointLocation", state).option("path", out).trigger(availableNow=True).start().awaitTermination()
    found = spark.read.schema("start timestamp, n long").parquet(out)
    late = rows.where(halves[1]).count()
    return found.agg(F.count("*").alias("days"), F.sum("n").alias("counted")).withColumn("late", F.lit(late))


class RunningMean(StatefulProcessor):
    """Count and sum of each user's values; a row for each batch and user."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.held = handle.getValueState("held", "n long, total double")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:  # noqa: N802, N803
        n, total = self.held.get() if self.held.exists() else (0, 0.0)
        for f in rows:
            n, total = n + len(f), total + float(f["value"].sum())
        self.held.update((n, total))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "mean": [total / n]})

    def close(self) -> None:
        pass


def st_state_stats(spark, sf_dir):
    """Running mean of each user's values in managed state; the last row of each user."""
    key, kind = "spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"
    had = spark.conf.get(key)
    spark.conf.set(key, kind)
    try:
        stream = events(spark, sf_dir).select("user_id", "value").groupBy("user_id").transformWithStateInPandas(RunningMean(), "user_id long, n long, mean double", "Update", "None")
        at = f"{shared_dir(spark)}/state-{uuid.uuid4().hex}"
        write = lambda batch, epoch: batch.write.mode("overwrite").parquet(f"{at}/batch={epoch}")
        stream.writeStream.outputMode("update").foreachBatch(write).option("checkpointLocation", f"{at}-state").trigger(availableNow=True).start().awaitTermination()
    finally:
        spark.conf.set(key, had)
    rows = spark.read.parquet(at)
    return rows.groupBy("user_id").agg(F.max("n").alias("n"), F.round(F.max_by("mean", "n"), 6).alias("mean"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (st_tumbling, st_sliding, st_session, st_stream_join, st_dedup, st_static_join, st_score, sink_stream_upsert, st_late_data, st_state_stats)}
ORACLES = {
    "st_tumbling": "SELECT CAST(epoch(date_trunc('day', ts)) AS BIGINT) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2",
    "st_sliding": "SELECT start, count(*) AS n FROM (SELECT CAST(floor(epoch(ts) / 43200) AS BIGINT) * 43200 - unnest([0, 43200]) AS start FROM events) x GROUP BY 1",
    "st_session": "WITH a AS (SELECT user_id, ts, epoch(ts) - epoch(lag(ts) OVER (PARTITION BY user_id ORDER BY ts)) AS gap FROM events), b AS (SELECT user_id, ts, sum(CASE WHEN gap IS NULL OR gap > 21600 THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS k FROM a) SELECT user_id, CAST(floor(epoch(min(ts))) AS BIGINT) AS start, count(*) AS n FROM b GROUP BY user_id, k",
    "st_stream_join": "SELECT a.event_id AS c_id, b.event_id AS p_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR",
    "st_dedup": "SELECT DISTINCT event_id FROM events",
    "st_static_join": "SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey",
    "st_score": "SELECT count(*) AS n, CAST(0 AS BIGINT) AS differing FROM events",
    "sink_stream_upsert": "SELECT count(*) AS n, count(DISTINCT event_id) AS ids FROM events",
    "st_state_stats": "SELECT user_id, count(*) AS n, round(avg(value), 6) AS mean FROM events GROUP BY 1",
}
