"""Benchmark decontamination: size-partitioned MinHash containment search with exact verification.

Items are partitioned by the power of two of their shingle number; each partition has its least number of hits, and an
item's sketch is its smallest shingle hashes, so many that an item contained to the threshold cannot miss all but the
least hits (`sketch_size`): the search loses nothing. A sketch of the small side alone is looked up among the long
side's shingles, so a document's length does not dilute the estimate. Only documents and items with hits enough are
verified, on all the item's shingles. Built-in functions only.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialise, table
from .op5_quality_rules import word_list

WIDTH, PERCENT = 5, 80
#: Hits that make a candidate, for items of up to so many shingles; beyond, the last.
HITS = ((8, 1), (64, 2), (512, 4), (None, 8))
#: More rows than this are joined by a shuffle, not broadcast.
BROADCAST_ROWS = 1_000_000


def sketch_size(n: Column, least: Column, percent: int) -> Column:
    """Smallest hashes that an item of n shingles is searched by.

    A document that holds it lacks at most floor((100 - percent) n / 100) of its shingles, so at least `least` of the
    sketch are in the document.
    """
    return F.least(n, F.floor(n * (100 - percent) / 100).cast("int") + least)


def _grams(words: Column, width: int) -> Column:
    return F.when(F.size(words) < width, F.array().cast("array<bigint>")).otherwise(
        F.transform(F.sequence(F.lit(1), F.size(words) - (width - 1)), lambda i: F.xxhash64(F.slice(words, i, F.lit(width))))
    )


def _lower(text: Column) -> Column:
    return F.lower(F.coalesce(text.cast("string"), F.lit("")))


def item_sketches(items: DataFrame, width: int = WIDTH, percent: int = PERCENT) -> DataFrame:
    """One row for each distinct shingle of each item: h, item_id, item key, words, n, part, least hits, k, whether h is in the sketch."""
    words = items.select("item_id", F.xxhash64(F.coalesce(F.col("text").cast("string"), F.lit(""))).alias("item"), word_list(_lower(F.col("text"))).alias("w")).distinct()
    short = F.when(F.size("w") > 0, F.array(F.xxhash64("w"))).otherwise(F.array().cast("array<bigint>"))
    sets = words.withColumn("s", F.when(F.size("w") >= width, F.array_sort(F.array_distinct(_grams(F.col("w"), width)))).otherwise(short))
    sized = sets.where(F.size("s") > 0).select("item_id", "item", F.size("w").alias("words"), F.size("s").alias("n"), "s")
    least = F.lit(HITS[-1][1])
    for most, hits in reversed(HITS[:-1]):
        least = F.when(F.col("n") <= most, hits).otherwise(least)
    sized = sized.withColumn("part", F.ceil(F.log2(F.col("n"))).cast("int")).withColumn("least", least).withColumn("k", sketch_size(F.col("n"), F.col("least"), percent))
    return sized.select("item_id", "item", "words", "n", "part", "least", "k", F.posexplode("s").alias("place", "h")).withColumn("sketched", F.col("place") < F.col("k"))


def _row() -> Column:
    """A row of docs: copies of a row with the same id and text are one."""
    return F.xxhash64("doc_id", F.col("text").cast("string"))


def _shingles(docs: DataFrame, short: list[int], width: int) -> DataFrame:
    words = docs.select("doc_id", _row().alias("row"), word_list(_lower(F.col("text"))).alias("w"))
    grams = F.concat(_grams(F.col("w"), width), *[_grams(F.col("w"), n) for n in short]) if short else _grams(F.col("w"), width)
    return words.select("doc_id", "row", F.explode(grams).alias("h"))


def candidates(docs: DataFrame, sketches: DataFrame, short: list[int], width: int = WIDTH) -> DataFrame:
    """doc_id, row, item_id, item, sketch_hits of every pair with the hits that its item's partition asks for."""
    probes = sketches.where("sketched").select("h", "item_id", "item", "least")
    few = probes.count() <= BROADCAST_ROWS
    # a shingle that stands often in one text is one row after this
    found = _shingles(docs, short, width).join(F.broadcast(probes) if few else probes, "h").distinct()
    return found.groupBy("doc_id", "row", "item_id", "item", "least").agg(F.count("*").alias("sketch_hits")).where("sketch_hits >= least").drop("least")


def held_pairs(docs: DataFrame, items: DataFrame, width: int = WIDTH, percent: int = PERCENT) -> DataFrame:
    """doc_id, row, item_id, part, sketch_hits, shared, n: every row of docs and every item that it holds."""
    sketches = materialise(item_sketches(items, width, percent))
    # at most `width` - 1 numbers: the lengths of items shorter than a shingle
    short = sorted(r[0] for r in sketches.where(F.col("words") < width).select("words").distinct().collect())
    pairs = materialise(candidates(docs, sketches, short, width))
    rows = materialise(pairs.select("row").distinct())
    few = lambda df: F.broadcast(df) if df.count() <= BROADCAST_ROWS else df
    # only documents of candidates are read again, and only candidates' shingles are compared
    again = docs.where(F.col("text").isNotNull()).withColumn("row_of_text", _row()).join(few(rows.withColumnRenamed("row", "row_of_text")), "row_of_text", "left_semi")
    hit = _shingles(again.select("doc_id", "text"), short, width).select("row", "h").join(few(sketches.select("h", "item_id", "item", "n", "part")), "h").distinct()
    shared = hit.groupBy("row", "item_id", "item", "n", "part").agg(F.count("*").alias("shared"))
    verified = shared.where(100 * F.col("shared") >= percent * F.col("n"))
    same = pairs["row"].eqNullSafe(verified["row"]) & pairs["item_id"].eqNullSafe(verified["item_id"]) & (pairs["item"] == verified["item"])
    return pairs.join(verified, same).select("doc_id", pairs["row"], pairs["item_id"], "part", "sketch_hits", "shared", "n")


def contained_items(docs: DataFrame, items: DataFrame, width: int = WIDTH, percent: int = PERCENT) -> DataFrame:
    """doc_id, item_id, part, sketch_hits, shared, n_shingles, containment of every item that a document holds.

    An item is held where 100 * (its distinct shingles in the document) >= percent * (its distinct shingles); an item
    of fewer than `width` words has its whole sequence as the one shingle. Items and documents without words are in
    no pair. Rows with the same doc_id and text count once; the same doc_id with other texts gives its best pair.
    Null ids form pairs with a null id. Empty tables give no rows; other columns are ignored.
    """
    held = held_pairs(docs.select("doc_id", "text"), items.select("item_id", "text"), width, percent)
    best = F.max(F.struct((F.col("shared") / F.col("n")).alias("containment"), "shared", "n", "sketch_hits", "part")).alias("x")
    return held.groupBy("doc_id", "item_id").agg(best).select("doc_id", "item_id", "x.part", "x.sketch_hits", "x.shared", F.col("x.n").alias("n_shingles"), "x.containment")


def decontaminate(docs: DataFrame, items: DataFrame, width: int = WIDTH, percent: int = PERCENT) -> DataFrame:
    """The rows of docs, all their columns, that hold no item. Each row is judged by its own text, also where ids repeat or are null."""
    held = held_pairs(docs.select("doc_id", "text"), items.select("item_id", "text"), width, percent)
    marked = materialise(held.select(F.col("row").alias(f"held_{uuid.uuid4().hex}")).distinct())
    few = F.broadcast(marked) if marked.count() <= BROADCAST_ROWS else marked
    return docs.join(few, _row() == F.col(marked.columns[0]), "left_anti")


def op9_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every pair of a document and a benchmark item that it holds."""
    out = contained_items(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return out.select("doc_id", "item_id", F.col("shared").cast("long").alias("shared"), F.col("n_shingles").cast("long").alias("n_shingles"), "containment")
