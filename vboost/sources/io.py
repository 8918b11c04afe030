"""Tables, reliable intermediate files, and the model store."""

from __future__ import annotations

import json
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def row_counts(spark: SparkSession, sf_dir: str, **keys: str) -> dict[str, int]:
    """Rows of tables by their keys, at least 1: table=key column."""
    return {t: max(table(spark, sf_dir, t).agg(F.count(c)).first()[0], 1) for t, c in keys.items()}


def shared_dir(spark: SparkSession) -> str:
    """The folder that the driver and all executors see; one of our own only in local mode, where the session names none."""
    sc = spark.sparkContext
    named = sc.getConf().get("spark.checkpoint.dir")
    if named:
        return named.rstrip("/")
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        if not sc.master.startswith("local[") and sc.master != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        sc.setCheckpointDir(f"/tmp/checkpoints/{sc.applicationId}")
    return sc._jsc.sc().getCheckpointDir().get()


_SHIPPED: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Send the package to the executors once a session, for those that do not have it on their path."""
    sc = spark.sparkContext
    if sc.applicationId in _SHIPPED:
        return
    root = Path(__file__).resolve().parents[1]
    target = Path(tempfile.mkdtemp()).resolve() / f"{root.name}.zip"
    with zipfile.ZipFile(target, "w") as z:
        for f in sorted(root.rglob("*.py")):
            z.write(f, f"{root.name}/{f.relative_to(root)}")
    sc.addPyFile(str(target))
    _SHIPPED.add(sc.applicationId)


def cut(df: DataFrame) -> DataFrame:
    """The frame as written to and read from the shared folder: no lineage, no loss with an executor."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/vboost-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def spread(df: DataFrame) -> DataFrame:
    """A scan, dealt over the cores if it has fewer partitions: a small file with heavy rows is read by one task."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df if df._jdf.queryExecution().toRdd().getNumPartitions() >= cores else df.repartition(cores)


def small_batches(spark: SparkSession, most: int = 1 << 23) -> None:
    """Bound the session's Arrow batches by bytes, unless it has a lower bound already: rows may have thousands of features."""
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    now = spark.conf.get(key, None)
    if now is None or not now.isdigit() or int(now) > most:
        spark.conf.set(key, str(most))


def bucketed(df: DataFrame, by: str) -> DataFrame:
    """The frame as a table in the shared folder, bucketed and sorted by a key: joins on it need no exchange."""
    spark = df.sparkSession
    name = f"vboost_{uuid.uuid4().hex}"
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    rows = df.repartition(n, by)
    rows.write.bucketBy(n, by).sortBy(by).option("path", f"{shared_dir(spark)}/{name}").saveAsTable(name)
    table = spark.table(name)
    table.bucketed_name = name
    return table


def drop_bucketed(df: DataFrame) -> None:
    """Forget a bucketed table and delete its files."""
    spark, name = df.sparkSession, getattr(df, "bucketed_name", None)
    if name is None:
        return
    spark.sql(f"DROP TABLE IF EXISTS {name}")
    path = spark._jvm.org.apache.hadoop.fs.Path(f"{shared_dir(spark)}/{name}")
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def save_model(spark: SparkSession, nodes: list[dict], path: str) -> None:
    """Node rows partitioned by tree."""
    rows = [(n["tree"], n["class_id"], n["node"], json.dumps(n)) for n in nodes]
    spark.createDataFrame(rows, "tree int, class_id int, node int, body string").repartition(1).write.mode("overwrite").partitionBy("tree").parquet(path)


def load_model(spark: SparkSession, path: str) -> list[dict]:
    rows = spark.read.parquet(path).orderBy("tree", "class_id", F.col("node")).collect()
    return [json.loads(r["body"]) for r in rows]
