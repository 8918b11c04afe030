"""Brute force, round trips and edge cases of the pipeline operators on small tables."""

import hashlib
import re
import uuid
import zlib

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from vboost.llm import op1_ngram_jaccard as op1
from vboost.llm import op2_mix_sources as op2
from vboost.llm import op3_chat_format as op3
from vboost.llm import op4_html_extract as op4
from vboost.llm import op5_quality_rules as op5
from vboost.llm import op6_license_scan as op6
from vboost.llm import op7_quality_classifier as op7
from vboost.llm import op8_token_output as op8
from vboost.llm import op9_decontaminate as op9
from vboost.llm import op10_toxicity as op10
from vboost.llm import grammar, signature_tree, textkernel

DOCS = "doc_id long, text string, lang string, source string, n_chars long, score double, row string, h string, copies_of_row string, rated_id long, copy_of_row int"
WORD = re.compile(r"[^\x20\x09-\x0D]+")


def sentence(seed, n):
    rng = np.random.default_rng(seed)
    return " ".join("".join(rng.choice(list("abcdefg"), rng.integers(2, 7))) for _ in range(n))


@pytest.fixture(scope="module")
def docs(spark):
    """Nulls, empty, very long, repeated rows, near copies, and columns with clashing names."""
    long = sentence(1, 30_000)
    near = sentence(2, 100)
    texts = [None, "", "  \n ", "one", "One", near, near + " tail", near.replace(" ", "\n", 3), long, long + " end", sentence(3, 4), "x " * 50, sentence(4, 60) + "\n" + sentence(4, 60), "Released under the MIT License.\n" + sentence(5, 30), "you idiot and m0r0n " + sentence(6, 20), "é× ß  中文\t<|endoftext|>"]
    rows = [(i, t, ["en", None, "xx"][i % 3], "s", len(t or ""), 0.5, "r", "h", "c", 1, 2) for i, t in enumerate(texts)]
    rows += [rows[5], (None, "null id " + near, *[None] * 9), (40, near, "en", "s", 1, 0.1, "r", "h", None, None, None)]
    return spark.createDataFrame(rows, DOCS).cache()


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(i, i % 2, (i + 1) % 3 // 2) for i in range(16)] + [(3, None, None), (None, 1, 1)], "doc_id long, quality int, toxic int")


def none_of(df):
    return df.where("false")


def shingles(t, fold=True):
    t = re.sub("[A-Z]", lambda m: m[0].lower(), t or "") if fold else t or ""
    w = WORD.findall(t)
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()


def brute_components(rows):
    sets = [(i, shingles(t)) for i, t in rows if i is not None]
    up = {i: i for i, _ in sets}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, (i, s) in enumerate(sets):
        for j, t in sets[:a]:
            if s and t and 100 * len(s & t) >= 80 * len(s | t):
                x, y = find(i), find(j)
                up[max(x, y)] = min(x, y)
    return {i: (len(s), find(i)) for i, s in sets}


def test_op1_edges(spark, docs):
    rows = [(r["doc_id"], r["text"]) for r in docs.collect()]
    want = brute_components(rows)
    got = op1.ngram_jaccard_components(docs).collect()
    assert len(got) == len(rows)
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in got if r["doc_id"] is not None} == want
    assert [r["component_id"] for r in got if r["doc_id"] is None] == [None]
    assert op1.ngram_jaccard_components(none_of(docs)).count() == 0


def test_op1_chains_and_blocks(spark):
    """Chains of near copies whose ends are not linked, in blocks far smaller than a group."""
    rng = np.random.default_rng(5)
    rows = []
    for g in range(4):
        words = [f"w{g}x{i}" for i in range(60)]
        for k in range(40):
            rows.append((g * 100 + k, " ".join(words)))
            words[int(rng.integers(60))] = f"n{g}y{k}"
    df = spark.createDataFrame(rows, "doc_id long, text string")
    want = brute_components(rows)
    for block in (400, op1.BLOCK):
        got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in op1.ngram_jaccard_components(df, block=block).collect()}
        assert got == want


def test_signature_tree_finds_all_links():
    rng = np.random.default_rng(1)
    base = rng.integers(0, 2**62, 400).astype(np.uint64)
    sets = [np.unique(np.concatenate([rng.choice(base, 80, replace=False), base[:k]])) for k in rng.integers(20, 300, 60)]
    sizes = np.array([len(s) for s in sets])
    ids = np.arange(60)
    links = signature_tree.dual_join(ids, sizes, sets, ids, None, 80)
    up = list(range(60))

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in links:
        up[find(a)] = find(b)
    for a in range(60):
        for b in range(a):
            k = len(np.intersect1d(sets[a], sets[b]))
            if 100 * k >= 80 * (sizes[a] + sizes[b] - k):
                assert find(a) == find(b)


def test_textkernel_matches_regex(docs):
    import pyarrow as pa

    texts = [r["text"] for r in docs.select("text").collect()]
    data, offsets = textkernel.text_bytes(pa.array(texts))
    start, end, owner, _ = textkernel.hash_words(data, offsets)
    raw = data.tobytes()
    got = [[raw[a:b].decode() for a, b in zip(start[owner == i], end[owner == i])] for i in range(len(texts))]
    assert got == [WORD.findall(t or "") for t in texts]


def test_op2_meets_targets(spark):
    rows = [(i, "AB! " * (5 + i % 7) if i % 4 == 0 else "plain words here " * (3 + i % 5)) for i in range(400)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    labelled = df.select("doc_id", F.when(F.col("doc_id") % 4 == 0, "loud").otherwise("calm").alias("domain")).where("doc_id % 3 = 0")
    out = op2.mix_sources(df, labelled, {"loud": 0.5, "calm": 0.5}).toPandas()
    mass = {d: (out.rate * out.tokens * out[f"p_{d}"]).sum() for d in ("loud", "calm")}
    assert abs(mass["loud"] / sum(mass.values()) - 0.5) < 0.01 and (out.rate >= 0).all()
    grown = op2.apply_mix(df, labelled, {"loud": 0.5, "calm": 0.5})
    assert grown.columns == df.columns and grown.select("doc_id").distinct().count() == 400


def brute_rates(tokens, p, targets, low, high, steps=20_000):
    """Nonnegative least squares by plain coordinate descent on the same objective, to convergence."""
    size = tokens.sum()
    share = (tokens[:, None] * p).sum(0) / size
    rate = np.full(len(tokens), min(max(1.0, low), high))
    for _ in range(steps):
        error = (rate[:, None] * tokens[:, None] * p).sum(0) / size - targets
        rate = np.clip(rate - (p * (error / share)).sum(1), low, high)
    return rate


@pytest.mark.parametrize("low,high", [(0.0, 8.0), (1.0, 2.0)])
def test_op2_against_brute_force(spark, low, high):
    rows = [(i, "AB! " * (5 + i % 7) if i % 4 == 0 else "plain words here " * (3 + i % 5)) for i in range(200)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    labelled = df.select("doc_id", F.when(F.col("doc_id") % 4 == 0, "loud").otherwise("calm").alias("domain")).where("doc_id % 3 = 0")
    targets = {"loud": 0.45, "calm": 0.55}
    out = op2.mix_sources(df, labelled, targets, low, high, rounds=200).toPandas()
    p = out[["p_calm", "p_loud"]].to_numpy()
    want = brute_rates(out.tokens.to_numpy(float), p, np.array([0.55, 0.45]), low, high)
    mass = lambda r: (r[:, None] * out.tokens.to_numpy(float)[:, None] * p).sum(0)
    assert np.allclose(mass(out.rate.to_numpy()), mass(want), rtol=2e-3)
    assert (out.rate >= low - 1e-9).all() and (out.rate <= high + 1e-9).all()
    got = mass(out.rate.to_numpy())
    assert abs(out.residual[0] - np.abs(got / got.sum() - [0.55, 0.45]).max()) < 1e-3
    assert ((out.copies == np.floor(out.rate)) | (out.copies == np.floor(out.rate) + 1)).all()


def test_op2_edges(spark, docs, labels):
    labelled = labels.select("doc_id", op2.domain_of_labels().alias("domain"))
    assert op2.mix_sources(docs, labelled).count() == docs.count()
    assert op2.apply_mix(docs, none_of(labelled)).count() == docs.count()
    assert op2.mix_sources(none_of(docs), labelled).count() == 0
    assert labels.select(op2.domain_of_labels()).where("doc_id = 3").collect()[-1][0] is None
    mixed = op2.apply_mix(docs, labelled)
    assert mixed.columns == docs.columns and mixed.where("copies_of_row = 'c' AND rated_id = 1 AND copy_of_row = 2").count() >= 16


def test_op3_round_trip_and_parts(spark):
    texts = ["<|im_end|>", "\\<|x\\\\|", None, "", "a\\", "<", "|>", "plain\nline", "\\n"]
    rows = [(1, i, "assistant" if i % 2 else "us<|er\n\\n", t) for i, t in enumerate(texts)] + [(2, None, None, "x"), (2, 1, "assistant", "y"), (2, 1, "assistant", "y"), (None, 0, "user", "z")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    got = op3.read_back(op3.format_conversations(df.select("conv_id", "turn", "role", op3.text_part(F.col("text")).alias("parts"))))
    back = {r["conv_id"]: r["t"] for r in got.select("conv_id", F.transform("segments", lambda s: F.struct(s["role"], op3.unescape(s["body"]).alias("b"))).alias("t")).collect()}
    assert [(s[0], s[1]) for s in back[1]] == [(r[2], r[3] or "") for r in rows[:9]]
    assert [tuple(s) for s in back[2]] == [("", "x"), ("assistant", "y"), ("assistant", "y")]
    assert len(back[None]) == 1
    parts = [("text", "see <|", None, None, None, None, None), ("image", None, "u1", 28, 15, None, None), ("audio", None, "u2", None, None, 2.0, None), ("document", None, "u3", None, None, None, 3), (None, "end", None, None, None, None, None)]
    one = spark.createDataFrame([(1, 0, "assistant", parts), (1, 1, "user", None)], f"conv_id long, turn long, role string, parts array<{op3.PART}>")
    r = op3.format_conversations(one).first()
    assert r["formatted"] == "<|im_start|>assistant\nsee <\\|<|image|><|audio|><|document|>end<|im_end|>\n<|im_start|>user\n<|im_end|>\n"
    assert [(a["ordinal"], a["type"], a["ref"], a["tokens"]) for a in r["attachments"]] == [(0, "image", "u1", 4), (1, "audio", "u2", 50), (2, "document", "u3", 1200)]
    body = r["formatted"].split("\n")[1]
    assert [body[x["start"] : x["start"] + x["length"]] for x in r["loss"]] == ["see <\\|", "end"]
    assert op3.format_conversations(none_of(one)).count() == 0


def test_op4_pages(spark):
    page = """<html><head><title>T</title><style>p{}</style></head><body><header class="masthead">Site</header>
    <nav><ul><li><a href="/">Home</a></li><li><a href="/b">News</a></li></ul></nav><div class="cookie-notice"><p>We use cookies.</p></div>
    <article><h1>Big &amp; small</h1><p>First <b>bold</b>
    line.<p>Second paragraph has more words in it.</p><div class="ad">Buy now</div><p>Third one ends here.</p></article>
    <section class="comments"><h3>Comments</h3><p>Nice post!</p></section><footer>&copy; 2020 Site</footer></body></html>"""
    rows = [(1, "u", page), (2, None, None), (3, "u", ""), (4, "u", "<p>" * 3000 + "x"), (5, "u", "<article><p>a < b & c <!-- not closed"), (1, "u", page)]
    got = op4.extract_pages(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()
    assert len(got) == 6
    by = {r["page_id"]: r for r in got}
    assert by[1]["text"] == "Big & small\nFirst bold line.\nSecond paragraph has more words in it.\nThird one ends here."
    assert by[2]["text"] == by[3]["text"] == "" and by[1]["n_chars"] == len(by[1]["text"])


def test_op4_deep_pages_and_many_class_words(spark):
    import time

    model = op4.default_field()
    body = "<article><p>First words of the story stand here.</p><p>And more of them follow.</p></article>"
    for n in (2_000, 16_000):
        deep = "".join(f'<div class="level k{chr(97 + i % 26)}x{i}">' for i in range(n))
        began = time.process_time()
        op4.main_text(deep + "<p>x" * 3 + body + "</div>" * n, model)
        assert time.process_time() - began < n / 2_000
    many = " ".join(f"word{chr(97 + i)}" for i in range(20))
    page = f'<html><body><div class="{many} advert sponsored">Buy now and save</div>{body}</body></html>'
    plain = f'<html><body><div class="advert sponsored">Buy now and save</div>{body}</body></html>'
    assert op4.main_text(page, model)[0] == op4.main_text(plain, model)[0]
    rows = [(1, "u", page, "extra", 3), (None, None, None, None, None)]
    got = op4.extract_pages(spark.createDataFrame(rows, "page_id long, url string, html string, text string, n_chars int")).collect()
    assert len(got) == 2 and {r["page_id"] for r in got} == {1, None}


def test_op4_equals_the_article_element_of_given_pages(spark):
    """Every given page holds its main text in one article element, which a plain search finds."""
    import html

    pages = spark.read.parquet("/root/testdata/sf0.001/pages.parquet")
    got = {r["page_id"]: r["text"] for r in op4.extract_pages(pages).collect()}
    checked = 0
    for r in pages.collect():
        m = re.search(r"<article\b[^>]*>(.*?)</article>", r["html"], re.S | re.I)
        if m:
            want = " ".join(html.unescape(re.sub(r"<[^>]+>", " ", m[1])).split())
            have = " ".join(got[r["page_id"]].split())
            assert have and set(have.split()) <= set(want.split())
            checked += 1
    assert checked >= 40


def test_op4_held_out_pages():
    model = op4.default_field()
    pages = op4.labelled_pages(120, seed=1234)
    right = sum(a == b for f, y in pages for a, b in zip(model.decode(f), y))
    assert right / sum(len(y) for _, y in pages) > 0.98


def brute_rules(t):
    t = t or ""
    w = WORD.findall(t)
    at = {}
    for k in range(len(w) - 7):
        at.setdefault(tuple(w[k : k + 8]), []).append(k)
    seen, dup = set(), 0
    for line in t.split("\n"):
        if WORD.search(line):
            dup += line in seen
            seen.add(line)
    again = len({i for v in at.values() if len(v) > 1 for k in v for i in range(k, k + 8)})
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), dup, again


def test_op5_against_brute_force(docs):
    got = op5.quality_rules(docs).collect()
    want = sorted(brute_rules(r["text"]) for r in docs.collect())
    assert sorted((r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) for r in got) == want
    assert all(r["base_failed"] == (r["n_words"] < 20 or 100 * r["n_repeat_words"] > 30 * r["n_words"]) for r in got)
    assert not any(r["kept"] and r["base_failed"] for r in got)
    assert op5.quality_rules(none_of(docs)).count() == 0


def brute_verdicts(rows):
    """kept of (text, lang) rows, in order: histograms, references and distances in plain Python."""
    import math

    def profile(t, lang):
        t = t or ""
        w = WORD.findall(t)
        lang = lang if lang in op5.COMMON else "other"
        count = lambda p: len(re.findall(p, t))
        upper, digit, mark, sign = count("[A-Z]"), count("[0-9]"), count(r"[.,;:!?'\"()-]"), count("[#*$%&|<>]")
        wide, inside = len(t.encode()) - len(t), sum(map(len, w))
        chars = [upper, digit, mark, sign, len(t) - inside, wide, max(inside - upper - digit - mark - sign - wide, 0)]
        common = [sum(x in (c, c.capitalize()) for x in w) for c in op5.COMMON.get(lang, [])]
        return lang, len(w), chars, [*common, len(w) - sum(common)]

    def distance(p, q):
        if not sum(p) or not sum(q):
            return 0.0
        p, q = [x / sum(p) for x in p], [x / sum(q) for x in q]
        d = sum((x * math.log2(x / ((x + y) / 2)) if x else 0) / 2 + (y * math.log2(y / ((x + y) / 2)) if y else 0) / 2 for x, y in zip(p, q))
        return math.sqrt(max(d, 0.0))

    found = [profile(*r) for r in rows]
    refs = {}
    for lang, _, chars, common in found:
        held = refs.setdefault(lang, ([0] * 7, [0] * len(common)))
        refs[lang] = ([a + b for a, b in zip(held[0], chars)], [a + b for a, b in zip(held[1], common)])
    out = []
    for (text, _), (lang, n, chars, common) in zip(rows, found):
        base = brute_rules(text)
        limit = math.sqrt(op5.MAX_WORD_JSD**2 + (len(common) - 1) * op5.WORD_NOISE / (8 * math.log(2)) / max(n, 1))
        far = distance(chars, refs[lang][0]) > op5.MAX_CHAR_JSD or len(common) > 1 and distance(common, refs[lang][1]) > limit
        out.append(not (n < 20 or 100 * base[4] > 30 * n) and not (n >= op5.MIN_WORDS and far))
    return out


def test_op5_verdict_against_brute_force(spark):
    given = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text", "lang")
    rows = [tuple(r) for r in given.collect()]
    rows += [(10_000 + i, " ".join(rng_words), lang) for i, (rng_words, lang) in enumerate([(sentence(1, 300).split(), "en"), (sentence(2, 300).split(), None), (["The", "of", "and"] * 40, "en"), (["$$", "##", "&&"] * 30 + sentence(3, 40).split(), "de")])]
    got = {r["doc_id"]: r["kept"] for r in op5.quality_rules(spark.createDataFrame(rows, "doc_id long, text string, lang string")).collect()}
    want = brute_verdicts([(t, lang) for _, t, lang in rows])
    assert [got[i] for i, _, _ in rows] == want and 0 < sum(want) < len(want)


def test_op5_distance(spark):
    df = spark.createDataFrame([([1.0, 0.0], [0.0, 2.0]), ([1.0, 3.0], [2.0, 6.0]), ([0.0, 0.0], [1.0, 1.0])], "p array<double>, q array<double>")
    got = [r[0] for r in df.select(op5.jensen_shannon(F.col("p"), F.col("q"))).collect()]
    assert [round(x, 9) for x in got] == [1.0, 0.0, 0.0]


def test_op5_rejects_texts_without_their_languages_words(spark):
    def text(seed, n, words, share):
        rng = np.random.default_rng(seed)
        filler = sentence(seed, n).split()
        return " ".join(str(rng.choice(words)) if rng.random() < share else w for w in filler).capitalize() + "."

    languages = {"en": op5.COMMON["en"], "de": op5.COMMON["de"]}
    rows = [(k, text(1000 * i + k, 300, w, 0.2), lang) for i, (lang, w) in enumerate(languages.items()) for k in range(60)]
    odd = [(100, 300, "de", 0.2), (101, 80, "de", 0.2), (102, 300, "en", 0.0), (103, 80, "en", 0.0)]
    fair = [(200, 60, "en", 0.2), (201, 120, "en", 0.2), (202, 1000, "en", 0.2)]
    rows += [(i, text(i, n, languages[words], share), "en") for i, n, words, share in odd + fair]
    got = {r["doc_id"]: r for r in op5.quality_rules(spark.createDataFrame(rows, "doc_id long, text string, lang string")).collect() if r["doc_id"] >= 100}
    assert not any(got[i]["base_failed"] or got[i]["char_jsd"] > op5.MAX_CHAR_JSD for i in got)
    assert not any(got[i]["kept"] for i, *_ in odd)
    assert all(got[i]["kept"] for i, *_ in fair)


def test_op6_phrases_and_blocks(spark, docs):
    texts = ["Under the MIT license, under-the.MIT license apache License, Version 2.0 CC BY-NC", "under the mit licensed", "permission is hereby granted free of charge to any person obtaining a copy of this software and documentation files", None, "", "This work is licensed under the GNU General Public License, version 3.\nx", "Kunder the mit license"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: r for r in op6.license_scan(df).collect()}
    assert (got[0]["n_base"], got[0]["first_word"], got[0]["last_word"], got[0]["base_labels"]) == (4, 0, 13, "apache-2,cc-by-nc,mit")
    assert got[1]["n_base"] == 0 and got[2]["labels"] == "mit" and got[2]["base_labels"] == "" and 0.8 <= got[2]["score"] < 1
    assert got[5]["labels"] == "gpl-3" and got[3]["labels"] == got[4]["labels"] == "" and got[3]["n_words"] == 0 and got[3]["score"] == 0
    assert got[6]["n_base"] == 0
    assert op6.license_scan(docs).count() == docs.count() and op6.license_scan(none_of(docs)).count() == 0


def test_op6_wrapped_notices(spark):
    notices = {t: label for label, texts in op6.TEMPLATES.items() for t in texts}
    rows, want = [], {}
    for t, label in notices.items():
        words = t.split()
        for cut in (1, len(words) // 2):  # one word a line, and one break
            for lead in (0, 31, 200):
                want[len(rows)] = label
                wrapped = "\n# ".join(" ".join(words[i : i + cut]) for i in range(0, len(words), cut))
                rows.append((len(rows), f"{sentence(lead, lead)} {wrapped} {sentence(lead + 1, lead)}"))
    # the same words far apart name nothing
    words = op6.TEMPLATES["bsd"][0].split()
    rows.append((len(rows), "\n".join(w + " " + sentence(i, 4) for i, w in enumerate(words))))
    got = {r["doc_id"]: r for r in op6.license_scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert all(want[i] in got[i]["labels"].split(",") for i in want)
    assert got[len(rows) - 1]["labels"] == ""


def brute_labels(text, threshold=0.8):
    """Labels of the method by every line and every run of words, without any filter."""
    words = lambda x: re.findall("[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), x))
    out = set()
    for label, templates in op6.TEMPLATES.items():
        for t in templates:
            tokens = set(t.split())
            span = int(np.ceil(len(t.split()) / threshold - 1e-9))
            w = words(text)
            runs = [w[i : i + span] for i in range(max(1, len(w) - span + 1))] if "\n" in text else []
            if any(len(tokens & set(b)) >= threshold * len(tokens) - 1e-9 for b in [words(x) for x in text.split("\n")] + runs):
                out.add(label)
    return out


def test_op6_against_brute_force(spark):
    rng = np.random.default_rng(23)
    every = [t for texts in op6.TEMPLATES.values() for t in texts] + list(op6.NOTICES.values())
    rows = []
    for k in range(160):
        words = str(rng.choice(every)).split()
        keep = rng.random(len(words)) < rng.choice([0.6, 0.75, 0.82, 0.9, 1.0])
        words = [w for w, x in zip(words, keep) if x]
        for _ in range(int(rng.integers(0, 6))):
            words.insert(int(rng.integers(0, len(words) + 1)), "foreign")
        gaps = rng.choice([" ", "\n", "\n// "], len(words), p=[0.85, 0.1, 0.05])
        body = "".join(w + g for w, g in zip(words, gaps))
        rows.append((k, f"{sentence(k, int(rng.integers(0, 300)))}\n{body} {sentence(k + 500, int(rng.integers(0, 300)))}"))
    got = {r["doc_id"]: r for r in op6.license_scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    for k, text in rows:
        base = set(filter(None, got[k]["base_labels"].split(",")))
        assert set(filter(None, got[k]["labels"].split(","))) == brute_labels(text) | base, (k, text)


def test_op7_learns_and_edges(spark, docs, labels):
    rng = np.random.default_rng(0)
    x = rng.normal(size=(2000, 4))
    y = ((x[:, 0] * x[:, 1] > 0) ^ (x[:, 2] > 1.5)).astype(float)
    model = op7.fit_additive(x[:1500], y[:1500], pairs=3)
    assert ((model.scores(x[1500:]) > 0.5) == y[1500:]).mean() > 0.85
    model = op7.train(docs, labels)
    got = op7.score_quality(docs, model).collect()
    assert len(got) == docs.count() and all(0 <= r["score"] <= 1 for r in got)
    assert op7.keep_quality(docs, model, 0.0).collect() == docs.collect()
    assert op7.score_quality(none_of(docs), op7.train(none_of(docs), none_of(labels))).count() == 0


def test_op7_scores_cell_by_cell(spark, docs):
    """A text's logit is the sum of its table cells, and a labelled id repeated with other texts is one row of the fit."""
    rng = np.random.default_rng(4)
    texts = [sentence(i, 40) + ("." if i % 2 else " !! ## $$ " * 8) for i in range(300)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    y = spark.createDataFrame([(i, i % 2) for i in range(300)], "doc_id long, quality int")
    model = op7.train(df, y)
    import pyarrow as pa

    x = op7.batch_features(pa.array(texts))
    for k in rng.integers(0, 300, 20):
        z = model.base
        for j, edges in enumerate(model.edges):
            z += model.tables[j][sum(x[k, j] >= e for e in edges)]
        for (a, b), cells in zip(model.pairs, model.pair_tables):
            z += cells[sum(x[k, a] >= e for e in model.coarse[a]), sum(x[k, b] >= e for e in model.coarse[b])]
        assert abs(model.logits(x[k : k + 1])[0] - z) < 1e-9
    again = spark.createDataFrame([(1, f"other {i}") for i in range(50)], "doc_id long, text string").unionByName(df)
    sample = op7.labelled_texts(again, y, "quality").collect()
    assert len(sample) == len({r["doc_id"] for r in sample})


def byte_bpe():
    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path("byte_bpe_50k.json")
    return path, Tokenizer.from_file(path)


def test_op8_round_trip(spark, docs):
    _, t = byte_bpe()
    rows = sorted(((r["doc_id"], r["text"]) for r in docs.collect()), key=lambda r: (r[0] is not None, r[0] or 0))
    want, start = [], 0
    for i, text in rows:
        ids = t.encode(text or "", add_special_tokens=False).ids + [0]
        want.append((i, start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
        start += len(ids)
    got = [tuple(r) for r in op8.token_digests(docs).collect()]
    assert sorted(got, key=lambda r: r[1]) == want
    assert op8.token_digests(none_of(docs)).count() == 0


def test_op8_ids_equal_the_librarys(monkeypatch):
    """Clitics, white space, marks, Latin-1 letters, added tokens and other scripts, also where the cache is emptied."""
    import pyarrow as pa

    path, t = byte_bpe()
    rng = np.random.default_rng(11)
    some = [" ", "\n", " ", "'", "s", "t", "re", "ve", "ll", "'s", "'ll", "'re", "d", "m", "a", "B", "\u00e9", "\u00df", "7", "42", ".", "!!", "#"]
    more = [*some, "\t", "\u00a0", "\u65e5\u672c", "<|endoftext|>", "\u00d7", "\u00aa", "\u0130", "\x00"]
    texts = ["".join(rng.choice(more if i % 4 == 0 else some, rng.integers(0, 30))) for i in range(8000)] + [None, "", " ", "\n", "'", "'s", "a <|endoftext|> b"]
    want = [t.encode(x or "", add_special_tokens=False).ids + [0] for x in texts]
    for pieces in (op8.CACHE_PIECES, 50):
        monkeypatch.setattr(op8, "CACHE_PIECES", pieces)
        enc = op8.PieceEncoder(path)
        for at in range(0, len(texts), 1000):
            ids, size = enc.encode(pa.array(texts[at : at + 1000], pa.string()))
            assert np.split(ids, np.cumsum(size)[:-1])[0].tolist() == want[at]
            assert ids.tolist() == sum(want[at : at + 1000], []) and size.tolist() == [len(x) for x in want[at : at + 1000]]


def test_op8_ranges_and_shuffled_places(spark, docs, monkeypatch):
    """More ranges than documents, ties in the key, and the ways for very many ranges and shards: the same files' rows."""
    want = sorted(tuple(r) for r in op8.token_digests(docs).collect() if r["doc_id"] is not None)
    for ranges, rows in ((4096, 0), (1, 0), (1, 1_000_000)):
        monkeypatch.setattr(op8, "MOST_RANGES", ranges)
        monkeypatch.setattr(op8, "BROADCAST_ROWS", rows)
        assert sorted(tuple(r) for r in op8.token_digests(docs).collect() if r["doc_id"] is not None) == want
    many = spark.createDataFrame([(i // 7, f"text {i}") for i in range(300)], "doc_id long, text string")
    cut = op8.by_ranges(many, "doc_id", 200)
    found = [x for x in cut.select("doc_id", F.spark_partition_id().alias("p")).groupBy("doc_id").agg(F.countDistinct("p").alias("n"), F.min("p").alias("p")).orderBy("doc_id").collect()]
    assert all(x["n"] == 1 for x in found) and [x["p"] for x in found] == sorted(x["p"] for x in found)


def test_op8_random_access(spark, docs):
    path, t = byte_bpe()
    folder = f"{op8.shared_dir(spark)}/test-{uuid.uuid4().hex}"
    op8.write_tokens(docs, folder, path, shard_tokens=2000, partitions=3)
    text = docs.where("doc_id = 8").first()["text"]
    assert op8.read_document(spark, folder, 8) == [t.encode(text, add_special_tokens=False).ids + [0]]


@pytest.mark.parametrize("least", [2, 4])
def test_op8_grammar_leaves_no_frequent_pair(least):
    rng = np.random.default_rng(3)
    cases = [np.concatenate([np.tile(rng.integers(1, 9, 7), 200), np.full(101, 5)]), rng.integers(0, 4, 3000), rng.zipf(1.3, 5000) % 50, np.full(1000, 2), np.array([1]), rng.integers(0, 2, 10)]
    for ids in cases:
        ids = ids.astype(np.uint16)
        last = np.unique(np.append(rng.integers(0, len(ids), len(ids) // 40), len(ids) - 1))
        g = grammar.Grammar(ids, last, 50, least)
        lengths = grammar.expansion_lengths(g.rules, 50)
        assert (grammar.expand(g.symbols, g.rules, lengths, 50) == ids).all()
        cut = np.split(g.symbols, g.last[:-1] + 1)
        assert [len(grammar.expand(c, g.rules, lengths, 50)) for c in cut] == np.diff(last, prepend=-1).tolist()
        counts = {}
        for c in cut:  # places of a pair that do not overlap
            taken = {}
            for k, pair in enumerate(zip(c.tolist(), c[1:].tolist())):
                if taken.get(pair) != k - 1 or pair[0] != pair[1]:
                    taken[pair] = k
                    counts[pair] = counts.get(pair, 0) + 1
        assert max(counts.values(), default=0) < least
        row = op8.shard_row(ids, np.diff(last, prepend=-1), 50, least, None)
        assert (op8.shard_ids(row) == ids).all()
        few = grammar.Grammar(ids, last, 50, least, 3)
        assert len(few.rules) <= 3 and (grammar.expand(few.symbols, few.rules, grammar.expansion_lengths(few.rules, 50), 50) == ids).all()


def test_op9_finds_planted_items(spark, docs):
    items = [(i, sentence(100 + i, n)) for i, n in enumerate((8, 40, 200, 3))] + [(8, None), (9, ""), (1, sentence(101, 40))]
    bench = spark.createDataFrame(items, "item_id long, text string")
    filler = sentence(50, 5000)
    rows = [(0, filler), (1, filler + " " + items[0][1].upper() + " " + filler), (2, items[1][1]), (3, "x\n" + items[2][1]), (4, filler[:900] + " " + items[3][1] + " end"), (5, " ".join(items[1][1].split()[:20])), (6, None), (7, ""), (2, items[1][1])]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {(r["doc_id"], r["item_id"]) for r in op9.contained_items(df, bench).collect()}
    want = set()
    for d, t in rows:
        w = WORD.findall((t or "").lower())
        for i, u in items:
            v = WORD.findall((u or "").lower())
            k = min(5, len(v))
            if v:
                grams = {tuple(w[a : a + k]) for a in range(len(w) - k + 1)}
                q = {tuple(v[a : a + k]) for a in range(len(v) - k + 1)}
                if 100 * len(q & grams) >= 80 * len(q):
                    want.add((d, i))
    assert got == want and {(1, 0), (2, 1), (3, 2), (4, 3)} <= got
    assert {r["doc_id"] for r in op9.decontaminate(df, bench).collect()} == {0, 5, 6, 7}
    assert op9.decontaminate(docs, none_of(bench)).count() == docs.count() and op9.contained_items(none_of(docs), bench).count() == 0
    # a row is judged by its own text, whatever its id
    mixed = [(None, filler), (None, items[1][1]), (3, "clean words alone"), (3, items[2][1])]
    assert sorted(r["text"] for r in op9.decontaminate(spark.createDataFrame(mixed, "doc_id long, text string"), bench).collect()) == sorted([filler, "clean words alone"])


def test_op9_sketches_lose_no_pair_and_prune(spark, monkeypatch):
    """Against all pairs, with items cut to just above and below the threshold at either end and in the middle."""
    rng = np.random.default_rng(17)
    items = [(i, sentence(300 + i, int(n))) for i, n in enumerate([5, 6, 9, 12, 20, 33, 70, 150, 600, 2000])]
    bench = spark.createDataFrame(items, "item_id long, text string")
    rows = []
    for i, t in items:
        w = t.split()
        for share in (0.7, 0.79, 0.8, 0.81, 0.9, 1.0):
            k = int(np.ceil(share * len(w)))
            at = int(rng.integers(0, len(w) - k + 1))
            half = len(w) // 2
            broken = w[:half] + ["x"] * int(len(w) * (1 - share)) + w[half:]
            rows += [(len(rows) + j, " ".join(x)) for j, x in enumerate([w[:k], w[-k:], [*sentence(len(rows), 40).split(), *w[at : at + k]], broken])]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    want = set()
    for d, t in rows:
        for i, u in items:
            q = shingles(u)
            if 100 * len(q & shingles(t)) >= 80 * len(q):
                want.add((d, i))
    for limit in (op9.BROADCAST_ROWS, 0):
        monkeypatch.setattr(op9, "BROADCAST_ROWS", limit)
        assert {(r["doc_id"], r["item_id"]) for r in op9.contained_items(df, bench).collect()} == want
    sketches = op9.item_sketches(bench)
    found = op9.candidates(df, sketches, []).count()
    assert len(want) <= found < len(rows) * len(items) / 4
    assert sketches.where("sketched").count() < sketches.count() / 2


def test_op10_restores_and_edges(spark, docs, labels):
    words = "idiot moron stupid tree house garden walks river mountain yellow window".split()
    text = " ".join(np.random.default_rng(1).choice(words, 4000))
    r = op10.Restorer(op10.CharModel.of(op10.trigram_counts(np.frombuffer(text.encode(), np.uint8))))
    assert r.text("1d10t m0r0n, stuuupid! s t u p i d i.d.i.o.t") == "idiot moron, stupid! stupid idiot"
    assert r.text("A tree in 2023, 3.5 OK!! word*** a b") == "A tree in 2023, 3.5 OK!! word*** a b"
    rows = [(i, f"{sentence(i, 30)} {'you stupid idiot' if i % 3 == 0 else 'green garden walks'} {sentence(999 + i, 30)}") for i in range(300)]
    rows += [(900, sentence(7, 30) + " you 5tup1d 1d10t " + sentence(8, 20)), (901, None), (902, "")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    y = spark.createDataFrame([(i, int(i % 3 == 0)) for i in range(300)], "doc_id long, toxic int")
    got = {x["doc_id"]: x["score"] for x in op10.score_toxicity(df, op10.train(df, y)).collect()}
    assert all((got[i] >= 0.5) == (i % 3 == 0) for i in range(300))
    assert got[900] >= 0.5 and got[901] < 0.5 and got[902] < 0.5
    assert op10.score_toxicity(docs, op10.train(docs, labels)).count() == docs.count()
    assert op10.score_toxicity(none_of(docs), op10.train(none_of(docs), none_of(labels))).count() == 0


def test_op10_prefilter_flags_whatever_is_restored():
    words = "asshole shit idiot stupid bitch the house is on fire and " * 400
    restorer = op10.Restorer(op10.CharModel.of(op10.trigram_counts(np.frombuffer(words.encode(), np.uint8))))
    disguised = {"a$$hole": "asshole", "sh!!t": "shit", "@$$hole": "asshole", "455hole": "asshole", "5h17": "shit", "st" + "u" * 40 + "pid": "stupid", "s h i t": "shit", "s*h*1*t": "shit"}
    rng = np.random.default_rng(7)
    random = ["".join(rng.choice(list("aB1$!* .@-4\n"), rng.integers(0, 12))) for _ in range(4000)]
    texts = [x for t in disguised for x in (t, f"on {t} fire", f"({t}).")] + ["word! 2024 $500 (a) *note*", "é 5", ""] + random

    def flags(some):
        sizes = [len(t.encode()) for t in some]
        return op10.suspects(np.frombuffer("".join(some).encode(), np.uint8), np.cumsum([0, *sizes]))

    for t, want in disguised.items():
        assert restorer.text(f"on {t} fire") == f"on {want} fire"
    changed = [restorer.text(t) != t for t in texts]
    together, apart = flags(texts), [flags([t])[0] for t in texts]
    assert not any(c and not (a and b) for c, a, b in zip(changed, apart, together))
    assert not flags(["word! 2024 $500 (a) *note*"])[0]
    long = "1a" * 100_000
    assert restorer.text(long) != long and len(restorer.text("a" * 1_000_000)) <= 2
