import zlib

import duckdb
import numpy as np
import pytest

import __spark_entry__ as entry
import corpus_pipeline
from vboost.llm import op2_mix_sources as op2
from vboost.llm import op7_quality_classifier as op7
from vboost.llm import oracles
from vboost.llm.common import materialise

from test_operators import brute_components, shingles

DIR = "/root/testdata/sf0.001"


def test_all_operators_are_registered():
    names = entry.queries()
    assert all(sum(n.startswith(f"op{k}_") for n in names) == 1 for k in range(1, 11)) and "pipeline" in names


@pytest.mark.parametrize("name", sorted(oracles.SQL))
def test_query_equals_sql(spark, name):
    db = duckdb.connect()
    for t in ("documents", "conversations", "pages", "benchmark", "labels"):
        db.sql(f"create view {t} as select * from '{DIR}/{t}.parquet'")
    want = db.sql(entry.oracle_sql()[name]).df()
    got = entry.queries()[name](spark, DIR).toPandas()
    cols = sorted(want.columns)
    assert sorted(got.columns) == cols
    rows = lambda x: sorted(map(tuple, x[cols].astype(str).values.tolist()))
    assert rows(got) == rows(want)


def rows_of(df):
    return sorted(((r["doc_id"], r["text"]) for r in df.select("doc_id", "text").collect()), key=str)


def test_stages_against_brute_force(spark):
    """Each stage on what the one before it kept, against its operator in plain Python."""
    docs = spark.read.parquet(f"{DIR}/documents.parquet")
    columns, stages = docs.columns, dict(corpus_pipeline.STAGES)
    assert list(stages) == ["quality", "near_duplicates", "decontamination", "mixing", "tokens"]
    labels = spark.read.parquet(f"{DIR}/labels.parquet")
    scores = {r["doc_id"]: r["score"] for r in op7.score_quality(docs, op7.train(docs, labels)).collect()}
    kept = materialise(stages["quality"](spark, docs, DIR))
    assert kept.columns == columns and rows_of(kept) == [x for x in rows_of(docs) if scores[x[0]] >= 0.3]
    want = {i for i, (_, c) in brute_components(rows_of(kept)).items() if i == c}
    single = materialise(stages["near_duplicates"](spark, kept, DIR))
    assert single.columns == columns and {i for i, _ in rows_of(single)} == want and single.count() == len(want)
    items = [(r["text"] or "").lower() for r in spark.read.parquet(f"{DIR}/benchmark.parquet").collect()]
    sets = [shingles(x) for x in items]
    holds = lambda t: any(q and 100 * len(q & shingles((t or "").lower())) >= 80 * len(q) for q in sets)
    clean = materialise(stages["decontamination"](spark, single, DIR))
    assert clean.columns == columns and rows_of(clean) == [x for x in rows_of(single) if not holds(x[1])]
    mixed = materialise(stages["mixing"](spark, clean, DIR))
    rated = op2.mix_sources(clean, labels.select("doc_id", op2.domain_of_labels().alias("domain")), low=1.0, high=4.0)
    copies = {r["doc_id"]: r["copies"] for r in rated.collect()}
    assert mixed.columns == columns and rows_of(mixed) == sorted((x for x in rows_of(clean) for _ in range(copies[x[0]])), key=str)
    assert set(copies.values()) <= {1, 2, 3, 4} and mixed.count() < 1.5 * clean.count()
    import public_tokenizers
    from tokenizers import Tokenizer

    t, start, out = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json")), 0, []
    for i, text in sorted(rows_of(mixed)):
        ids = [*t.encode(text or "", add_special_tokens=False).ids, 0]
        out.append((i, start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
        start += len(ids)
    assert sorted(tuple(r) for r in stages["tokens"](spark, mixed, DIR).collect()) == sorted(out)


def test_mixing_aims_at_the_operators_targets(spark, monkeypatch):
    asked, mix = [], op2.mix_sources
    monkeypatch.setattr(op2, "mix_sources", lambda docs, labelled, targets=None, *a, **k: asked.append(targets or op2.TARGETS) or mix(docs, labelled, targets, *a, **k))
    corpus_pipeline.mixing(spark, spark.read.parquet(f"{DIR}/documents.parquet"), DIR)
    assert asked == [{"clean": 0.80, "noisy": 0.15, "harsh": 0.05}]
