"""Quality classifier: a generalised additive model with pairwise interactions.

Each feature has a lookup table over its quantile bins, learned by cyclic boosting of trees of three leaves; the
strongest pairs of features have tables over coarse bins. A score is the sum of the tables' cells, by vectorised
additions over Arrow batches. The model is a few thousand numbers, fitted on the driver from a bounded sample of
labelled rows; text features are computed on the executors.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import textkernel as K
from .common import small_batches, table

FEATURES = (
    "log_words", "word_length", "distinct", "upper", "digit", "symbol", "mark", "wide", "shout", "adjacent", "lines", "bar", "single", "longest",
)
#: Labelled rows that a model is fitted on at most, those with the smallest hashes of their ids.
SAMPLE_ROWS = 20_000
BINS, COARSE, PAIRS, ROUNDS, RATE = 32, 8, 6, 60, 0.15


def _class_table(chars: str) -> np.ndarray:
    out = np.zeros(256, dtype=np.uint8)
    out[list(chars.encode())] = 1
    return out


_CLASSES = [
    _class_table("ABCDEFGHIJKLMNOPQRSTUVWXYZ"),
    _class_table("0123456789"),
    _class_table("#*$%&<>^~=+_@"),
    _class_table(".,;:?'\"()-"),
    np.r_[np.zeros(128, np.uint8), np.ones(128, np.uint8)],
    _class_table("!"),
    _class_table("\n"),
    _class_table("|"),
]


def _per_text(flags: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    running = np.zeros(len(flags) + 1, dtype=np.int64)
    np.cumsum(flags, out=running[1:])
    return running[offsets[1:]] - running[offsets[:-1]]


def features_of(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """One row of FEATURES for each text; a text without words has zeros."""
    texts = len(offsets) - 1
    size = np.maximum(np.diff(offsets), 1)
    counts = [_per_text(c[data], offsets) / size for c in _CLASSES]
    start, end, owner, word = K.hash_words(data, offsets)
    n = np.bincount(owner, minlength=texts)
    some = np.maximum(n, 1)
    length = end - start
    order = np.lexsort((word, owner))
    o, w = owner[order], word[order]
    new = np.ones(len(o), dtype=bool)
    new[1:] = (o[1:] != o[:-1]) | (w[1:] != w[:-1])
    distinct = np.bincount(o[new], minlength=texts)
    same = (owner[1:] == owner[:-1]) & (word[1:] == word[:-1])
    adjacent = np.bincount(owner[1:][same], minlength=texts)
    longest = np.zeros(texts)
    np.maximum.at(longest, owner, length)
    upper, digit, symbol, mark, wide, shout, lines, bar = counts
    columns = [np.log1p(n), np.bincount(owner, weights=length, minlength=texts) / some, distinct / some, upper, digit, symbol, mark, wide, shout, adjacent / some, lines, bar, np.bincount(owner, weights=length == 1, minlength=texts) / some, np.log1p(longest)]
    return np.column_stack(columns)


def batch_features(column: pa.Array) -> np.ndarray:
    data, offsets = K.text_bytes(column)
    parts = [features_of(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]) for a, b in K.chunks(offsets)]
    return np.concatenate(parts) if parts else np.zeros((0, len(FEATURES)))


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


@dataclass
class AdditiveModel:
    base: float = 0.0
    edges: list[np.ndarray] = field(default_factory=list)
    tables: list[np.ndarray] = field(default_factory=list)
    pairs: list[tuple[int, int]] = field(default_factory=list)
    coarse: list[np.ndarray] = field(default_factory=list)
    pair_tables: list[np.ndarray] = field(default_factory=list)

    def logits(self, x: np.ndarray) -> np.ndarray:
        z = np.full(len(x), self.base)
        for j, (edges, cells) in enumerate(zip(self.edges, self.tables)):
            z += cells[np.searchsorted(edges, x[:, j], side="right")]
        if self.pairs:
            rough = [np.searchsorted(e, x[:, j], side="right") for j, e in enumerate(self.coarse)]
            for (a, b), cells in zip(self.pairs, self.pair_tables):
                z += cells[rough[a], rough[b]]
        return z

    def scores(self, x: np.ndarray) -> np.ndarray:
        return _sigmoid(self.logits(x))


def _leaf(g, h, ridge):
    return g / (h + ridge)


def _best_cut(g: np.ndarray, h: np.ndarray, ridge: float) -> tuple[float, int]:
    """Gain and last left cell of the best cut of a run of cells; no gain for one cell."""
    if len(g) < 2:
        return 0.0, 0
    left_g, left_h = np.cumsum(g)[:-1], np.cumsum(h)[:-1]
    all_g, all_h = g.sum(), h.sum()
    gain = left_g**2 / (left_h + ridge) + (all_g - left_g) ** 2 / (all_h - left_h + ridge) - all_g**2 / (all_h + ridge)
    at = int(np.argmax(gain))
    return float(gain[at]), at


def _small_tree(g: np.ndarray, h: np.ndarray, ridge: float) -> np.ndarray:
    """Values of a tree of at most three leaves over ordered cells."""
    runs = [(0, len(g))]
    for _ in range(2):
        cuts = [(*_best_cut(g[a:b], h[a:b], ridge), a, b) for a, b in runs]
        gain, at, a, b = max(cuts)
        if gain <= 1e-9:
            break
        runs.remove((a, b))
        runs += [(a, a + at + 1), (a + at + 1, b)]
    out = np.zeros(len(g))
    for a, b in runs:
        out[a:b] = _leaf(g[a:b].sum(), h[a:b].sum(), ridge)
    return out


def _corner_tree(g: np.ndarray, h: np.ndarray, ridge: float) -> tuple[float, np.ndarray]:
    """Gain and values of the best four-corner tree (one cut on each axis) over a grid."""
    cg, ch = g.cumsum(0).cumsum(1), h.cumsum(0).cumsum(1)
    best = (0.0, np.zeros_like(g))
    base = cg[-1, -1] ** 2 / (ch[-1, -1] + ridge)
    for i in range(g.shape[0] - 1):
        for j in range(g.shape[1] - 1):
            quarter = [(cg[i, j], ch[i, j]), (cg[i, -1] - cg[i, j], ch[i, -1] - ch[i, j]), (cg[-1, j] - cg[i, j], ch[-1, j] - ch[i, j])]
            quarter.append((cg[-1, -1] - sum(q[0] for q in quarter), ch[-1, -1] - sum(q[1] for q in quarter)))
            gain = sum(a * a / (b + ridge) for a, b in quarter) - base
            if gain > best[0] + 1e-12:
                out = np.empty_like(g)
                v = [_leaf(a, b, ridge) for a, b in quarter]
                out[: i + 1, : j + 1], out[: i + 1, j + 1 :], out[i + 1 :, : j + 1], out[i + 1 :, j + 1 :] = v
                best = (gain, out)
    return best


def fit_additive(x: np.ndarray, y: np.ndarray, rounds: int = ROUNDS, rate: float = RATE, bins: int = BINS, pairs: int = PAIRS, ridge: float = 2.0) -> AdditiveModel:
    """Cyclic boosting of logistic loss. Rows without a label must be left out; one class gives a constant model."""
    n = len(y)
    share = (y.sum() + 1) / (n + 2)
    model = AdditiveModel(base=float(np.log(share / (1 - share))))
    if n == 0 or y.min() == y.max():
        return model
    cuts = lambda k: [np.unique(np.quantile(x[:, j], np.linspace(0, 1, k + 1)[1:-1])) for j in range(x.shape[1])]
    model.edges = cuts(bins)
    model.tables = [np.zeros(len(e) + 1) for e in model.edges]
    at = [np.searchsorted(e, x[:, j], side="right") for j, e in enumerate(model.edges)]
    z = np.full(n, model.base)
    for _ in range(rounds):
        for j, cells in enumerate(model.tables):
            p = _sigmoid(z)
            g = np.bincount(at[j], weights=y - p, minlength=len(cells))
            h = np.bincount(at[j], weights=p * (1 - p), minlength=len(cells))
            step = rate * _small_tree(g, h, ridge)
            cells += step
            z += step[at[j]]
    model.coarse = cuts(COARSE)
    rough = [np.searchsorted(e, x[:, j], side="right") for j, e in enumerate(model.coarse)]
    shape = [len(e) + 1 for e in model.coarse]

    def grid(a: int, b: int) -> tuple[np.ndarray, np.ndarray]:
        p, cell, size = _sigmoid(z), rough[a] * shape[b] + rough[b], shape[a] * shape[b]
        return tuple(np.bincount(cell, weights=w, minlength=size).reshape(shape[a], shape[b]) for w in (y - p, p * (1 - p)))

    ranked = sorted(((_corner_tree(*grid(a, b), ridge)[0], a, b) for a in range(x.shape[1]) for b in range(a)), reverse=True)
    model.pairs = [(a, b) for gain, a, b in ranked[:pairs] if gain > 0]
    model.pair_tables = [np.zeros((shape[a], shape[b])) for a, b in model.pairs]
    for _ in range(rounds // 4):
        for (a, b), cells in zip(model.pairs, model.pair_tables):
            step = rate * _corner_tree(*grid(a, b), ridge)[1]
            cells += step
            z += step[rough[a], rough[b]]
    return model


def held_out(doc_id: Column | str) -> Column:
    """The fifth of documents that no label is learned from."""
    return F.coalesce(F.pmod(F.crc32(F.col(doc_id).cast("string") if isinstance(doc_id, str) else doc_id.cast("string")), F.lit(5)) == 0, F.lit(False))


def labelled_texts(docs: DataFrame, labels: DataFrame, label: str, rows: int = SAMPLE_ROWS) -> DataFrame:
    """doc_id, text, y of at most `rows` labelled documents that may be learned from, one text each.

    Of several texts of one doc_id the one with the smallest digest counts, and of several labels the largest: the
    sample is bounded by `rows` whatever repeats.
    """
    known = labels.select("doc_id", F.col(label).cast("double").alias("y")).where("y IS NOT NULL AND doc_id IS NOT NULL").where(~held_out("doc_id"))
    chosen = known.groupBy("doc_id").agg(F.max("y").alias("y")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)
    found = docs.select("doc_id", F.col("text").cast("string").alias("text")).join(F.broadcast(chosen), "doc_id")  # `rows` rows at most
    digest = F.struct(F.xxhash64("text"), F.length("text"), "text")
    return found.groupBy("doc_id", "y").agg(F.min_by("text", digest).alias("text")).select("doc_id", "text", "y")


def _feature_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        x = batch_features(batch.column("text"))
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("y"), *[pa.array(x[:, j]) for j in range(x.shape[1])]], names=["doc_id", "y", *FEATURES])


def train(docs: DataFrame, labels: DataFrame, label: str = "quality", rows: int = SAMPLE_ROWS) -> AdditiveModel:
    schema = "doc_id long, y double, " + ", ".join(f"{c} double" for c in FEATURES)
    small_batches(docs.sparkSession)
    sample = labelled_texts(docs, labels, label, rows).select(F.col("doc_id").cast("long"), "text", "y").mapInArrow(_feature_batches, schema)
    found = sample.toPandas().sort_values("doc_id")  # `rows` rows at most
    return fit_additive(found[list(FEATURES)].to_numpy(), found["y"].to_numpy())


def _scorer(model: AdditiveModel):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = batch_features(batch.column("text"))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(model.scores(x))], names=["doc_id", "score"])

    return run


def score_quality(docs: DataFrame, model: AdditiveModel) -> DataFrame:
    """doc_id, score for every row; a null or empty text is scored by its zero features. Repeated rows stay."""
    small_batches(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(_scorer(model), "doc_id long, score double")


def _selector(model: AdditiveModel, least: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = batch_features(batch.column(batch.schema.get_field_index("text")).cast(pa.string()))
            yield batch.filter(pa.array(model.scores(x) >= least))

    return run


def keep_quality(docs: DataFrame, model: AdditiveModel, least: float = 0.3) -> DataFrame:
    """The rows of docs, with all their columns, that score `least` or more: a filter without a shuffle."""
    small_batches(docs.sparkSession)
    return docs.mapInArrow(_selector(model, least), docs.schema)


def op7_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quality score of every document, learned from four fifths of the labels."""
    docs = table(spark, sf_dir, "documents")
    model = train(docs, table(spark, sf_dir, "labels"))
    return score_quality(docs, model).select("doc_id", held_out("doc_id").alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))
