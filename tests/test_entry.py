import duckdb
import pandas as pd
import pytest

import __spark_entry__ as entry

DIR = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
NAMES = sorted(n for n in entry.oracle_sql() if not n.startswith("op"))


def shown(v):
    if isinstance(v, (list, dict, str)) or hasattr(v, "__len__"):
        return str(v)
    if pd.isna(v):
        return "-"
    return str(float(v)) if isinstance(v, (int, float)) or hasattr(v, "dtype") else str(v)


def rows(frame, columns):
    return sorted(tuple(map(shown, r)) for r in frame[columns].astype(object).values.tolist())


@pytest.fixture(scope="module")
def db():
    out = duckdb.connect()
    for t in TABLES:
        out.sql(f"create view {t} as select * from '{DIR}/{t}.parquet'")
    return out


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, db, name):
    want = db.sql(entry.oracle_sql()[name]).df()
    got = entry.queries()[name](spark, DIR).toPandas()
    columns = sorted(want.columns)
    assert sorted(got.columns) == columns
    assert rows(got, columns) == rows(want, columns)
