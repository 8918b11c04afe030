"""N-gram Jaccard join by signature trees.

1. One Arrow pass hashes every text's distinct word shingles; equal sets share a digest, so a group of exact copies
   is one node from here on.
2. A third of the shingle space, chosen by hash, is counted over all sets. A shingle of one set alone is shared with
   none, so a set with more lone shingles than the threshold allows has no partner and leaves. Exact for any share.
   All shingles of the sets that stay are then counted in the same way.
3. For the sets that stay, all shingles are counted, and each set is listed under the rarest shingles that any
   partner must share one of (prefix filter). Sets listed together, directly or through others, form a candidate
   group; groups are found by distributed components, and each set goes to its group's task once.
4. Within a group, signature trees are joined by dual traversal. Large groups are cut into blocks of so many shingles
   and joined block by block, neighbours first; two blocks that already are of one component are not joined again.
   Two sets can be linked only if their sizes are of the same or of neighbouring classes, a class being a factor of
   1 / threshold: blocks hold one class each, and blocks of other classes never meet.

A digest has 64 bits: two different sets are taken for one with probability of about (number of sets)^2 / 2^65.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import textkernel as K
from .common import materialise, release, shuffle_partitions, small_batches, table
from .components import connected_components
from .signature_tree import dual_join

#: Shingles of a block or of a task: bounds a task's memory whatever the lengths of the texts.
BLOCK = 1 << 18
SAMPLE = 3


def _sets(width: int, whole: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = K.text_bytes(batch.column(1))
            for lo, hi in K.chunks(offsets):
                sets = K.shingle_sets(data[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo], width)
                sizes = np.array([len(s) for s in sets], dtype=np.int64)
                node = np.array([np.bitwise_xor.reduce(K.mix(s * np.uint64(0xA24BAED4963EE407) + np.uint64(len(s)))) if len(s) else 0 for s in sets], dtype=np.uint64)
                if not whole:
                    sets = [s[s % np.uint64(SAMPLE) == 0] for s in sets]
                bounds = np.concatenate([[0], np.cumsum([len(s) for s in sets])]).astype(np.int32)
                values = np.concatenate(sets).view(np.int64) if sets else np.zeros(0, np.int64)
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(lo, hi - lo), pa.array(sizes), pa.array(node.view(np.int64)), pa.ListArray.from_arrays(pa.array(bounds), pa.array(values))],
                    names=["doc_id", "n", "node", "h"],
                )

    return run


SCHEMA = "doc_id long, n long, node long, h array<long>"


def shingle_table(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 5, whole: bool = True) -> DataFrame:
    """doc_id, number of distinct shingles, digest of the set, and the sorted shingle hashes (or the counted share)."""
    small_batches(docs.sparkSession)
    return docs.select(F.col(id_col).cast("long"), F.col(text_col).cast("string")).mapInArrow(_sets(width, whole), SCHEMA)


def _floor_share(n, percent: int):
    """Most lone shingles that a set of n may have and still be linked."""
    return F.col(n) - F.floor((F.col(n) * percent + 99) / 100)


def _without_partners(shingles: DataFrame, percent: int) -> DataFrame:
    """Nodes that too many lone shingles of `shingles` (node, n, h) keep from any partner: one shuffle of the rows."""
    return (
        shingles.groupBy("h")
        .agg(F.min("node").alias("node"), F.max("node").alias("top"), F.min("n").alias("n"))
        .where("node = top")
        .groupBy("node", "n")
        .agg(F.count("*").alias("u"))
        .where(F.col("u") > _floor_share("n", percent))
        .select("node")
    )


def _tree_task(percent: int):
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pairs: list[tuple[int, int]] = []
        for _, g in pdf.groupby("comp", sort=False):
            ids = g["node"].to_numpy()
            sets = [np.sort(np.asarray(x).view(np.uint64)) for x in g["h"]]
            side = g["side"].to_numpy()
            pairs += dual_join(ids, g["n"].to_numpy(), sets, g["label"].to_numpy(), side == 1 if side.any() else None, percent)
        return pd.DataFrame(pairs, columns=["a", "b"], dtype="int64")

    return run


def _joined(rows: DataFrame, percent: int) -> DataFrame:
    return materialise(rows.groupBy("task").applyInPandas(_tree_task(percent), "a long, b long"))


def jaccard_links(sets: DataFrame, percent: int = 80, block: int = BLOCK) -> DataFrame:
    """Links (a, b) between distinct sets (node, n, h) that connect every pair with 100 * common >= percent * union.

    Links inside a component already connected are left out: the rows span each component and are all true links.
    """
    spark = sets.sparkSession
    flat = sets.select("node", "n", F.explode("h").alias("h"))
    many = flat.groupBy("h").agg(F.count("*").alias("c")).where("c > 1")
    need = F.floor((F.col("n") * percent + 99) / 100)
    listed = (
        flat.join(many, "h")
        .groupBy("node", "n")
        .agg(F.sort_array(F.collect_list(F.struct("c", "h"))).alias("x"))  # bounded by one text's length
        .where(F.size("x") >= need)
        .select("node", F.explode(F.slice("x", F.lit(1), (F.size("x") - need + 1).cast("int"))).alias("x"))
        .select("node", F.col("x.h").alias("h"))
    )
    listed = materialise(listed)
    hub = listed.groupBy("h").agg(F.min("node").alias("hub"), F.max("node").alias("top")).where("hub < top")
    near = listed.join(hub.select("h", "hub"), "h").select(F.col("node").alias("a"), F.col("hub").alias("b")).distinct()
    groups = materialise(connected_components(near).select("node", F.col("root").alias("comp")))
    weighed = materialise(groups.join(sets.select("node", "n"), "node"))
    total = weighed.agg(F.sum("n"), F.count("*")).first()
    if not total[1]:
        return spark.createDataFrame([], "a long, b long")
    # small groups share tasks of about a block; a large group is cut into blocks by size class and hash
    tasks = max(1, -(-total[0] // block), min(shuffle_partitions(spark), total[1] // 64))
    step = math.log(100 / percent)
    kind = F.floor(F.log(F.col("n")) / step + 1e-9).cast("long")
    sizes = weighed.groupBy("comp").agg(F.sum("n").alias("m"))
    classes = weighed.groupBy("comp", kind.alias("kind")).agg(F.sum("n").alias("w")).withColumn("cuts", F.ceil(F.col("w") / block).cast("long"))
    classes = classes.join(sizes.where(F.col("m") > block), "comp")
    upto = Window.partitionBy("comp").orderBy("kind").rowsBetween(Window.unboundedPreceding, -1)
    # one row for each size class of a large group: a few dozen at most for a group
    classes = materialise(classes.withColumn("first", F.coalesce(F.sum("cuts").over(upto), F.lit(0))).select("comp", "kind", "first", "cuts"))
    placed = weighed.withColumn("kind", kind).join(classes, ["comp", "kind"], "left").select("node", "comp", "kind", (F.col("first") + F.pmod(F.xxhash64("node"), "cuts")).alias("k"))
    rows = materialise(placed.join(sets, "node"))
    small = rows.where("k IS NULL").select("comp", "node", "n", "h", F.lit(0).alias("side"), F.col("node").alias("label"), F.concat(F.lit("s"), F.pmod(F.xxhash64("comp"), F.lit(tasks))).alias("task"))
    large = rows.where("k IS NOT NULL")
    task = F.concat_ws("/", F.col("comp"), F.col("i"), F.col("j"))
    columns = ("comp", "node", "n", "h", "side", "label", "task")

    def sides(pairs: DataFrame, held: DataFrame) -> DataFrame:
        """The sets of block pairs (comp, i, j): a block with itself once, of two blocks each on its side."""
        left = held.join(pairs.withColumn("k", F.col("i")), ["comp", "k"]).withColumn("side", F.lit(0))
        right = held.join(pairs.where("i <> j").withColumn("k", F.col("j")), ["comp", "k"]).withColumn("side", F.lit(1))
        return left.unionByName(right).withColumn("task", task).select(*columns)

    spans = classes.select("comp", "kind", "first", "cuts")
    if spans.limit(1).count() == 0:
        return _joined(small, percent)
    blocks = spans.select("comp", "kind", "first", "cuts", F.explode(F.sequence(F.col("first"), F.col("first") + F.col("cuts") - 1)).alias("i"))
    after = F.col("first") + F.pmod(F.col("i") - F.col("first") + 1, "cuts")
    up = spans.select("comp", (F.col("kind") - 1).alias("kind"), F.col("first").alias("next_first"), F.col("cuts").alias("next_cuts"))
    # each block with itself, with the next of its class, and with one of the class above
    ring = blocks.select("comp", "i", F.col("i").alias("j")).union(blocks.select("comp", F.least("i", after), F.greatest("i", after)))
    ring = ring.union(blocks.join(up, ["comp", "kind"]).select("comp", "i", F.col("next_first") + F.pmod("i", "next_cuts"))).distinct()
    own = large.withColumn("label", F.col("node"))
    first = _joined(small.select(*columns).union(sides(ring, own)), percent)
    roots = connected_components(first)
    labelled = materialise(large.join(roots, "node", "left").withColumn("label", F.coalesce("root", "node")).drop("root"))
    whole = labelled.groupBy("comp", "kind", "k").agg(F.min("label").alias("lo"), F.max("label").alias("hi"))
    whole = materialise(whole)
    open_pairs = []
    for gap in (0, 1):  # pairs of blocks of one class, and of neighbouring classes
        a = whole.select("comp", "kind", F.col("k").alias("i"), F.col("lo").alias("lo_i"), F.col("hi").alias("hi_i"))
        b = whole.select("comp", (F.col("kind") - gap).alias("kind"), F.col("k").alias("j"), F.col("lo").alias("lo_j"), F.col("hi").alias("hi_j"))
        open_pairs.append(a.join(b, ["comp", "kind"]).where("i < j AND NOT (lo_i = hi_i AND lo_j = hi_j AND lo_i = lo_j)").select("comp", "i", "j"))
    rest = open_pairs[0].union(open_pairs[1]).join(ring, ["comp", "i", "j"], "left_anti")
    return first.union(_joined(sides(rest, labelled), percent))


def set_classes(docs: DataFrame, id_col: str, text_col: str, width: int, percent: int, block: int) -> tuple[DataFrame, DataFrame]:
    """Every row's doc_id, n and node (its set), and the component_id of every node that a row with an id has."""
    sampled = materialise(shingle_table(docs, id_col, text_col, width, whole=False))
    sig = materialise(sampled.drop("h"))
    named = sig.where("n > 0 AND doc_id IS NOT NULL")
    counted = sampled.where("n > 0 AND doc_id IS NOT NULL").select("node", "n", F.explode("h").alias("h"))
    lone = materialise(_without_partners(counted, percent))
    release(sampled)
    # one row for each set from here on: copies are folded into their smallest id before any join
    reps = materialise(named.groupBy("node").agg(F.min("doc_id").alias("least")))
    # one text of each set that may have partners; joined alike at every size, so no broadcast
    stay = materialise(reps.join(lone, "node", "left_anti").select(F.col("least").alias(id_col)))
    kept = docs.select(id_col, text_col).where(F.col(id_col).isNotNull()).join(stay.select(id_col).hint("merge"), id_col, "left_semi")
    whole = materialise(shingle_table(kept, id_col, text_col, width).where("n > 0").dropDuplicates(["node"]).select("node", "n", "h"))
    lone = materialise(_without_partners(whole.select("node", "n", F.explode("h").alias("h")), percent))
    sets = materialise(whole.join(lone.hint("merge"), "node", "left_anti"))
    release(whole)
    roots = connected_components(jaccard_links(sets, percent, block))
    grouped = materialise(reps.join(roots, "node", "left").select("node", "least", F.coalesce("root", "node").alias("root")))
    first = grouped.groupBy("root").agg(F.min("least").alias("component_id"))
    classes = materialise(grouped.select("node", "root").join(first, "root").select("node", "component_id"))
    return sig, classes


def ngram_jaccard_components(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 5, percent: int = 80, block: int = BLOCK) -> DataFrame:
    """Components of texts linked by 100 * common >= percent * union of distinct word shingles.

    Returns doc_id, n_shingles, component_id (smallest id reachable). Texts without words and rows without an id are
    linked with nothing: the first are their own component, the second have none. Repeated rows stay, each with the
    same result. Other columns are ignored. An empty table gives no rows.
    """
    sig, classes = set_classes(docs, id_col, text_col, width, percent, block)
    own = F.when(F.col("n") == 0, F.col("doc_id")).otherwise(F.col("component_id"))
    # a node that only rows without an id have is in no class
    return sig.select("doc_id", F.col("n").alias("n_shingles"), "n", "node").join(classes, "node", "left").select("doc_id", "n_shingles", own.alias("component_id"))


def keep_representatives(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """The rows of docs, with all their columns, whose doc_id is their component's smallest; repeated rows once.

    Rows without an id are in no component and stay.
    """
    sig, classes = set_classes(docs, "doc_id", "text", width, percent, BLOCK)
    empty = sig.where("n = 0 AND doc_id IS NOT NULL").select("doc_id")
    kept = classes.select(F.col("component_id").alias("doc_id")).union(empty).distinct()
    return docs.join(kept.hint("merge"), "doc_id", "left_semi").dropDuplicates(["doc_id", "text"]).unionByName(docs.where("doc_id IS NULL"))


def op1_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_shingles, component_id for every document: five-word shingles, similarity of 0.8 or more."""
    return ngram_jaccard_components(table(spark, sf_dir, "documents"))
