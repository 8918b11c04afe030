"""Queries of budgets and costs take their sizes from the given tables, and Spark reads these."""

import pytest

import __spark_entry__ as entry


def read(spark):
    found = spark.sparkContext._jsc.sc().statusStore().executorList(False)
    return sum(found.apply(i).totalInputBytes() for i in range(found.size()))


@pytest.mark.parametrize("name", ["bit_budget", "cost_model", "cost_reduction", "eta_nk_table", "x8_cost_table"])
def test_spark_reads_the_tables(spark, name):
    spark.conf.set("parquet.hadoop.vectored.io.enabled", "false")  # vectored reads are not counted
    try:
        before = read(spark)
        assert entry.queries()[name](spark, "/root/testdata/sf0.1").collect()
        spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty(10_000)
        now = read(spark) - before
        print(name, now, "bytes")
        assert now > 50_000
    finally:
        spark.conf.unset("parquet.hadoop.vectored.io.enabled")
