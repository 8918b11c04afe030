"""What of the lines is written for several readings, and summaries of values that stand once each."""

import numpy as np

from vboost.operators.binning import Summary
from vboost.sources import workloads

DIR = "/root/testdata/sf0.001"


def test_kept_lines_hold_the_joined_columns_alone(spark, tmp_path):
    w, kept = workloads.ALL["w6"], []

    def keep(df):
        kept.append(df.columns)
        df.write.parquet(f"{tmp_path}/lines")
        return spark.read.parquet(f"{tmp_path}/lines")

    rows = lambda df: sorted(map(tuple, df.select("inst_id", "y", "held", *w.spec.columns).collect()))
    whole, again = w.matrix(spark, DIR), w.matrix(spark, DIR, keep)
    assert rows(again) == rows(whole) and whole.count() > 5000
    assert len(kept) == 1 and "l_shipdate" not in kept[0] and not set(kept[0]) & {*workloads._LINE_MORE, *workloads._OTHER_MORE, "y"}
    assert {r["held"] for r in again.select("held").distinct().collect()} == {False, True}


def test_summaries_of_single_values_sort_them_without_places(monkeypatch):
    rng = np.random.default_rng(1)
    blocks = [rng.integers(0, k, 1 << 16) / 7.0 for k in (5, 1000, 10**9, 10**9)] + [np.zeros(0), np.ones(3)]
    old, new = Summary(), Summary()
    for x in blocks:
        old.add(x, np.ones(len(x), np.int64))
        new.add(x)
    for a, b in zip(old.whole(), new.whole()):
        assert (a == b).all() and a.dtype == b.dtype
    monkeypatch.setattr(np, "argsort", None)
    one = Summary()
    one.add(blocks[1])
    assert one.quantiles([0.5]) == [float(np.sort(blocks[1])[(1 << 15) - 1])]
