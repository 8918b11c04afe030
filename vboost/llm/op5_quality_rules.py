"""Quality rules by distribution divergence: character-class and common-word histograms against language references.

One pass computes each text's base figures and its two histograms. The references are the summed histograms of all
documents of a language. A text fails the method where it is long enough to judge and its Jensen-Shannon distance
to its language's reference exceeds the threshold of either histogram. Few words scatter: the threshold of the
common words grows for short texts by the distance that a sample of so many words has by chance. Built-in functions only.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import let, materialise, table

GAP = r"[\x20\x09-\x0D]+"
GAPS = " \t\n\x0b\f\r"
#: Common words of each language.
COMMON = {
    "en": ["the", "of", "and", "to", "in", "a", "is", "that", "for", "it", "was", "on", "with", "as", "be", "by"],
    "de": ["der", "die", "und", "in", "den", "von", "zu", "das", "mit", "sich", "des", "auf", "ist", "im", "dem", "nicht"],
    "fr": ["de", "la", "le", "et", "les", "des", "en", "un", "du", "une", "que", "est", "pour", "qui", "dans", "par"],
    "es": ["de", "la", "que", "el", "en", "y", "a", "los", "del", "se", "las", "por", "un", "para", "con", "no"],
}
WINDOW, MIN_WORDS, MAX_CHAR_JSD, MAX_WORD_JSD = 8, 50, 0.28, 0.16
#: How many times its expected square the chance distance of common words may reach.
WORD_NOISE = 1.3


def word_list(text: Column) -> Column:
    """Maximal runs of other than space and 0x09-0x0D."""
    trimmed = F.btrim(text, F.lit(GAPS))
    return F.when(trimmed == "", F.array().cast("array<string>")).otherwise(F.split(trimmed, GAP))


def repeated_words(words: Column, window: int = WINDOW) -> Column:
    """Words that stand in a window found twice or more in the text; first occurrences count."""
    hashes = F.transform(F.sequence(F.lit(1), F.size(words) - (window - 1)), lambda i: F.xxhash64(F.slice(words, i, F.lit(window))))

    def covered(h: Column) -> Column:
        placed = F.array_sort(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("i"))))
        same = lambda a, k: F.get(a, k)["h"]
        hits = let(placed, lambda a: F.filter(F.transform(a, lambda x, k: F.when((same(a, k - 1) == x["h"]) | (same(a, k + 1) == x["h"]), x["i"])), lambda i: i.isNotNull()))
        ends = F.aggregate(
            F.array_sort(hits),
            F.struct(F.lit(0).alias("n"), F.lit(0).alias("end")),
            lambda s, i: F.struct((s["n"] + i + window - F.greatest(i, s["end"])).alias("n"), (i + window).alias("end")),
        )
        return ends["n"]

    some = let(hashes, lambda h: F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0)).otherwise(covered(h)))
    return F.when(F.size(words) <= window, F.lit(0)).otherwise(some)


def _normal(h: Column) -> Column:
    return let(F.aggregate(h, F.lit(0.0), lambda a, x: a + x), lambda t: F.transform(h, lambda x: F.when(t > 0, x / t).otherwise(F.lit(0.0))))


def jensen_shannon(p: Column, q: Column) -> Column:
    """Jensen-Shannon distance (base 2, 0 to 1) of two histograms of equal length; 0 where either is empty."""
    term = lambda x, m: F.when(x > 0, x * F.log2(x / m)).otherwise(F.lit(0.0))
    part = lambda x, y: let((x + y) / 2, lambda m: (term(x, m) + term(y, m)) / 2)
    total = lambda a: F.aggregate(a, F.lit(0.0), lambda s, x: s + x)
    both = F.sqrt(F.greatest(total(F.zip_with(_normal(p), _normal(q), part)), F.lit(0.0)))
    return F.when((total(p) > 0) & (total(q) > 0), both).otherwise(F.lit(0.0))


def text_profile(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """doc_id, lang (a listed language or 'other'), base figures, and the histograms `chars` and `common`."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    known = F.when(F.col("lang").isin(*COMMON), F.col("lang")).otherwise(F.lit("other"))
    base = docs.select(F.col("doc_id"), known.alias("lang"), text.alias("text"))
    every = sorted({x for words in COMMON.values() for x in words})
    spelt = every + [x.capitalize() for x in every]
    lists = F.lit(None).cast("array<string>")
    for lang, words in COMMON.items():
        lists = F.when(F.col("lang") == lang, F.array(*map(F.lit, words))).otherwise(lists)
    lists = F.coalesce(lists, F.array().cast("array<string>"))

    def figures(w: Column) -> Column:
        common = F.transform(F.filter(w, lambda x: x.isin(*spelt)), lambda x: F.lower(x))
        counts = let(common, lambda m: F.transform("words_of_lang", lambda x: (F.size(m) - F.size(F.array_remove(m, x))).cast("double")))
        return F.struct(F.size(w).cast("long").alias("n_words"), repeated_words(w, window).cast("long").alias("n_repeat_words"), counts.alias("common"))

    lines = F.filter(F.split("text", "\n", -1), lambda x: F.btrim(x, F.lit(GAPS)) != "")
    chars = F.char_length("text")
    upper, digit, mark = (F.regexp_count("text", F.lit(x)) for x in ("[A-Z]", "[0-9]", r"[.,;:!?'\"()-]"))
    sized = base.withColumn("words_of_lang", lists).select(
        "doc_id",
        "lang",
        let(word_list(F.col("text")), figures).alias("f"),
        F.char_length(F.regexp_replace("text", GAP, "")).cast("long").alias("word_chars"),
        F.regexp_count("text", F.lit("[#*$%&|<>]")).cast("long").alias("n_symbols"),
        let(lines, lambda x: F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("n_dup_lines"),
        chars.alias("n_chars"),
        upper.alias("upper"),
        digit.alias("digit"),
        mark.alias("mark"),
        (F.octet_length("text") - chars).alias("wide"),
    )
    plain = F.col("word_chars") - F.col("upper") - F.col("digit") - F.col("mark") - F.col("n_symbols")
    classes = [F.col("upper"), F.col("digit"), F.col("mark"), F.col("n_symbols"), F.col("n_chars") - F.col("word_chars"), F.col("wide"), F.greatest(plain - F.col("wide"), F.lit(0))]
    n_common = F.aggregate("f.common", F.lit(0.0), lambda a, x: a + x)
    return sized.select(
        "doc_id",
        "lang",
        "f.n_words",
        "word_chars",
        "n_symbols",
        "n_dup_lines",
        "f.n_repeat_words",
        F.array(*[x.cast("double") for x in classes]).alias("chars"),
        F.concat("f.common", F.array(F.col("f.n_words") - n_common)).alias("common"),
    )


def language_references(profile: DataFrame) -> DataFrame:
    """Summed histograms of each listed language and 'other': five rows at most."""
    size = 1 + max(map(len, COMMON.values()))
    sums = [F.sum(F.get("chars", F.lit(i))).alias(f"c{i}") for i in range(7)] + [F.sum(F.get("common", F.lit(i))).alias(f"w{i}") for i in range(size)]
    found = profile.groupBy("lang").agg(*sums)
    # a language's list may be shorter than the longest: the cells beyond it are null
    return found.select("lang", F.array(*[f"c{i}" for i in range(7)]).alias("ref_chars"), F.filter(F.array(*[f"w{i}" for i in range(size)]), lambda x: x.isNotNull()).alias("ref_common"))


def word_limit(cells: Column, n_words: Column, max_word: float) -> Column:
    """Largest word distance allowed: the square of a sample's distance is (cells - 1) / (8 ln 2 n) by chance."""
    return F.sqrt(F.lit(max_word * max_word) + (cells - 1) * F.lit(WORD_NOISE / (8 * math.log(2))) / n_words)


def quality_rules(
    docs: DataFrame, min_words: int = MIN_WORDS, max_char: float = MAX_CHAR_JSD, max_word: float = MAX_WORD_JSD, window: int = WINDOW
) -> DataFrame:
    """One row per row of docs (doc_id, text, lang): base figures, distances, base_failed and kept.

    A null or empty text has no words and fails the base rule. A null or unlisted lang is judged against 'other', on
    its characters alone. Repeated rows stay. An empty table gives no rows; other columns are ignored.
    """
    profile = materialise(text_profile(docs, window))
    joined = profile.join(F.broadcast(language_references(profile)), "lang")  # five rows at most
    failed = (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))
    far = (F.col("char_jsd") > max_char) | (F.col("word_jsd") > word_limit(F.size("common"), F.greatest(F.col("n_words"), F.lit(1)), max_word))
    return (
        joined.withColumn("char_jsd", jensen_shannon(F.col("chars"), F.col("ref_chars")))
        .withColumn("word_jsd", F.when(F.size("common") > 1, jensen_shannon(F.col("common"), F.col("ref_common"))).otherwise(F.lit(0.0)))
        .withColumn("base_failed", failed)
        .withColumn("kept", ~F.col("base_failed") & ~((F.col("n_words") >= min_words) & far))
    )


def op5_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Base figures and the verdict for every document."""
    out = quality_rules(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "char_jsd", "word_jsd")
