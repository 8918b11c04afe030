"""Toxicity with noisy-channel deobfuscation.

A character trigram model is counted over all documents. Tokens that look disguised (digits or signs among letters,
letters three times or more, single letters set apart) span a lattice of the letters that each sign may stand for,
and a Viterbi search under the model picks the reading. The restored text is scored: words and word beginnings that
labelled documents show to be more frequent in toxic texts have weights, and a document's strongest weight, their sum
and their density give the score. Labels are learned from a bounded sample without near copies of one another.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import lru_cache
from os.path import commonprefix

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import textkernel as K
from .common import materialise, small_batches, table
from .op7_quality_classifier import held_out, labelled_texts

SAMPLE_ROWS = 20_000
PREFIXES = (5, 6, 7, 8)
LEAST_DOCS, LEAST_WEIGHT = 5, 0.5
#: A feature counts up to so many times a document; its weight is a lower bound, so many deviations below the estimate.
COUNT_CAP, DEVIATIONS = 4, 2.5
EVIDENCE = ("top", "total", "density")
#: Letters that a sign may stand for.
SIGNS = {"0": "o", "1": "il", "2": "z", "3": "e", "4": "a", "5": "s", "6": "bg", "7": "t", "8": "b", "9": "g", "@": "a", "$": "s", "!": "i", "|": "il", "+": "t", "*": "aeiou"}
#: Signs that are punctuation at a token's beginning or end.
LEAD, TAIL = "!*+|", "!*+|$"
#: Longer tokens are read without the cache; readings are cut to what is still open every so many steps.
CACHED_TOKEN, FLUSH = 64, 64

_SYMBOL = np.zeros(256, dtype=np.int64)
_SYMBOL[97:123] = _SYMBOL[65:91] = np.arange(1, 27)
_SYMBOL[128:] = 27
SYMBOLS = 28
_LETTER = np.zeros(256, dtype=bool)
_LETTER[[*range(97, 123), *range(65, 91)]] = True
_SIGN = np.zeros(256, dtype=bool)
_SIGN[[ord(c) for c in SIGNS]] = True
_LEAD = np.zeros(256, dtype=bool)
_LEAD[[ord(c) for c in LEAD]] = True
_TAIL = np.zeros(256, dtype=bool)
_TAIL[[ord(c) for c in TAIL]] = True
_MARK = np.zeros(256, dtype=bool)
_MARK[[ord(c) for c in " ._*-"]] = True
#: Four or more single letters or signs, all set apart by the same mark.
_APART = re.compile(r"(?<![^\s])[A-Za-z0-9@$!|+*]([ ._*\-])(?:[A-Za-z0-9@$!|+*]\1){2,}[A-Za-z0-9@$!|+*](?=[.,;:!?]*(?:\s|\Z))")
#: Tokens with a sign in them, or a letter three times over.
_TOKEN = re.compile(r"(?<![A-Za-z0-9@$!|+*])(?=[A-Za-z]*[0-9@$!|+*]|[A-Za-z]*?([A-Za-z])\1\1)[A-Za-z0-9@$!|+*]+")


@dataclass
class CharModel:
    """Log probabilities of a letter (1-26, 0 the word's edge) after two symbols."""

    logs: np.ndarray

    @staticmethod
    def of(counts: np.ndarray) -> "CharModel":
        c = counts.reshape(SYMBOLS, SYMBOLS, SYMBOLS).astype(np.float64)
        two = c.sum(0)
        one = two.sum(0) + 1
        p1 = one / one.sum()
        p2 = (two + 20 * p1) / (two.sum(1, keepdims=True) + 20)
        p3 = (c + 5 * p2) / (c.sum(2, keepdims=True) + 5)
        return CharModel(np.log(p3))


def trigram_counts(data: np.ndarray) -> np.ndarray:
    s = _SYMBOL[data]
    if len(s) < 3:
        return np.zeros(SYMBOLS**3, np.int64)
    return np.bincount((s[:-2] * SYMBOLS + s[1:-1]) * SYMBOLS + s[2:], minlength=SYMBOLS**3)


def _count_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    total = np.zeros(SYMBOLS**3, np.int64)
    for batch in batches:
        data, offsets = K.text_bytes(batch.column(0))
        for a, b in K.chunks(offsets):
            total += trigram_counts(data[offsets[a] : offsets[b]])
    cells = np.flatnonzero(total)
    yield pa.RecordBatch.from_arrays([pa.array(cells), pa.array(total[cells])], names=["cell", "n"])


def corpus_counts(docs: DataFrame) -> np.ndarray:
    """Character trigram counts of all texts; at most 28^3 numbers come to the driver."""
    small_batches(docs.sparkSession)
    rows = docs.select(F.col("text").cast("string")).mapInArrow(_count_batches, "cell long, n long").groupBy("cell").agg(F.sum("n").alias("n"))
    out = np.zeros(SYMBOLS**3, np.int64)
    for r in rows.toLocalIterator():
        out[r["cell"]] = r["n"]
    return out


class Restorer:
    """Viterbi reading of disguised tokens; readings are kept in a bounded cache."""

    def __init__(self, model: CharModel):
        self.logs = model.logs.tolist()
        self.read = lru_cache(maxsize=50_000)(self._read)

    @staticmethod
    def lattice(token: str) -> Iterator[list[tuple[str, float]]]:
        """For each run of one sign, the strings it may stand for and the channel's log probabilities."""
        for run in re.finditer(r"(.)\1*", token.lower(), re.S):
            sign, times = run[1], len(run[0])
            letters = SIGNS.get(sign, sign if "a" <= sign <= "z" else "")
            cost = math.log(1 / max(1, len(letters)))
            if times == 1:
                yield [(x, cost) for x in letters]
            else:  # a run is one or two of the letter; a pair is most likely meant as it stands
                single = 0.02 if times == 2 else 0.5
                yield [(x * k, cost + math.log(single if k == 1 else 1 - single)) for x in letters for k in (1, 2)]

    def _read(self, token: str) -> str:
        states = {(0, 0): (0.0, "")}
        done: list[str] = []
        for step, choices in enumerate(self.lattice(token), 1):
            after: dict[tuple[int, int], tuple[float, str]] = {}
            for (a, b), (score, text) in states.items():
                for letters, cost in choices:
                    p, q, s = a, b, score + cost
                    for x in letters:
                        c = ord(x) - 96
                        s += self.logs[p][q][c]
                        p, q = q, c
                    if (p, q) not in after or s > after[p, q][0]:
                        after[p, q] = (s, text + letters)
            if not after:
                return token
            states = after
            if step % FLUSH == 0:  # what all readings share is decided
                done.append(commonprefix([t for _, t in states.values()]))
                states = {k: (s, t[len(done[-1]) :]) for k, (s, t) in states.items()}
        done.append(max((s + self.logs[a][b][0], t) for (a, b), (s, t) in states.items())[1])
        return "".join(done)

    def token(self, m: re.Match) -> str:
        t = m[0]
        core = t.rstrip(TAIL)  # signs at the end are punctuation
        tail = t[len(core) :]
        core = core.lstrip(LEAD)
        letters = sum("a" <= c <= "z" for c in core.lower())
        disguised = letters < len(core) or any(a == b == c for a, b, c in zip(core, core[1:], core[2:]))
        if not disguised or len(core) < 3 or not letters:
            return t
        return (self.read if len(core) <= CACHED_TOKEN else self._read)(core) + tail

    def text(self, text: str) -> str:
        joined = _APART.sub(lambda m: re.sub(r"[ ._*\-]", "", m[0]), text)
        return _TOKEN.sub(self.token, joined)


def _inner(data: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Which of the signs at `at` are not only punctuation before or after a token that holds a letter."""
    letter = _LETTER[data]
    token = letter | _SIGN[data]

    def beyond(loose: np.ndarray, last: bool) -> np.ndarray:
        """The nearest place from each sign on, itself included, whose character is not loose."""
        place, out = np.flatnonzero(loose[data]), at.copy()
        if len(place):
            starts = np.flatnonzero(np.diff(place, prepend=-2) != 1)
            edge = place[np.append(starts[1:], len(place)) - 1] + 1 if last else place[starts] - 1
            k = np.flatnonzero(loose[data[at]])
            out[k] = edge[np.searchsorted(place[starts], at[k], side="right") - 1]
        return out

    after, before = beyond(_TAIL, True), beyond(_LEAD, False)
    held = (after < len(data)) & (before >= 0)
    held &= token[np.minimum(after, len(data) - 1)] & token[np.maximum(before, 0)]
    gaps = np.concatenate([[-1], np.flatnonzero(~token), [len(data)]])
    run = np.searchsorted(gaps, at)
    letters = np.concatenate([[0], np.cumsum(letter, dtype=np.int64)])
    return held & (letters[gaps[run]] > letters[gaps[run - 1] + 1])


def suspects(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Flags of the texts that hold anything to restore: every text with a match of _APART or a token to read."""
    texts = len(offsets) - 1
    if len(data) < 3:
        return np.zeros(texts, dtype=bool)
    letter, sign = _LETTER[data], _SIGN[data]
    signs = np.flatnonzero(sign)
    found = [signs[_inner(data, signs)], np.flatnonzero(letter[:-2] & (data[:-2] == data[1:-1]) & (data[1:-1] == data[2:]))]
    if len(data) >= 7:
        alone = letter | sign
        same = (data[:-2] == data[2:]) & _MARK[data[:-2]]
        found.append(np.flatnonzero(alone[:-6] & alone[2:-4] & alone[4:-2] & alone[6:] & same[1:-3] & same[3:-1]))
    at = np.concatenate(found)
    flags = np.zeros(texts, dtype=bool)
    # a flag may name a neighbour for a run across two texts; restoring more is harmless
    flags[np.clip(np.searchsorted(offsets, at, side="right") - 1, 0, texts - 1)] = True
    return flags


def restored(column: pa.Array, restorer: Restorer | None) -> tuple[np.ndarray, np.ndarray]:
    data, offsets = K.text_bytes(column)
    if restorer is None or not len(column):
        return data, offsets
    flags = np.zeros(len(column), dtype=bool)
    for a, b in K.chunks(offsets):
        flags[a:b] = suspects(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
    if not flags.any():
        return data, offsets
    raw, parts, size = data.tobytes(), [], np.diff(offsets)
    at = 0
    for i in np.flatnonzero(flags).tolist():
        parts.append(raw[at : offsets[i]])
        at = int(offsets[i + 1])
        parts.append(restorer.text(raw[offsets[i] : at].decode("utf-8", "replace")).encode())
        size[i] = len(parts[-1])
    parts.append(raw[at:])
    return np.frombuffer(b"".join(parts), dtype=np.uint8), np.concatenate([[0], np.cumsum(size)])


def word_features(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Text number of each word, and a row of hashes: the word and its beginnings (0: none)."""
    _, _, owner, word, *heads = K.hash_words(data, offsets, K.BREAKS, PREFIXES)
    return owner, np.column_stack([word, *heads])


@dataclass
class ToxicModel:
    keys: np.ndarray = field(default_factory=lambda: np.zeros(0, np.uint64))
    weights: np.ndarray = field(default_factory=lambda: np.zeros(0))
    coefficients: np.ndarray = field(default_factory=lambda: np.zeros(1 + len(EVIDENCE)))
    chars: CharModel | None = None

    def evidence(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """For each text its strongest weight, the log of 1 + the sum of weights, and the sum over the root of its words."""
        texts = len(offsets) - 1
        out = np.zeros((texts, len(EVIDENCE)))
        if not len(self.keys):
            return out
        owner, hashes = word_features(data, offsets)
        best = np.zeros(len(owner))
        low = np.uint64(0xFFFF)
        likely = np.zeros(1 << 16, dtype=bool)
        likely[(self.keys & low).astype(np.int64)] = True
        for k in range(hashes.shape[1]):
            h = hashes[:, k]
            at = np.flatnonzero(likely[(h & low).astype(np.int64)])
            place = np.minimum(np.searchsorted(self.keys, h[at]), len(self.keys) - 1)
            hit = self.keys[place] == h[at]
            best[at[hit]] = np.maximum(best[at[hit]], self.weights[place[hit]])
        np.maximum.at(out[:, 0], owner, best)
        total = np.bincount(owner, weights=best, minlength=texts)
        out[:, 1] = np.log1p(total)
        out[:, 2] = total / np.sqrt(np.bincount(owner, minlength=texts) + 1.0)
        return out

    def scores(self, evidence: np.ndarray) -> np.ndarray:
        z = self.coefficients[0] + evidence @ self.coefficients[1:]
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def _evidence(column: pa.Array, model: ToxicModel, restorer: Restorer | None) -> np.ndarray:
    data, offsets = restored(column, restorer)
    parts = [model.evidence(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]) for a, b in K.chunks(offsets)]
    return np.concatenate(parts) if parts else np.zeros((0, len(EVIDENCE)))


def _marks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Four MinHash values of each text's shingles."""
    odd = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x27D4EB2F165667C5)]
    for batch in batches:
        data, offsets = K.text_bytes(batch.column("text"))
        rows: list[list[int]] = []
        for a, b in K.chunks(offsets):
            for s in K.shingle_sets(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]):
                rows.append([int(K.mix(s * k).min().view(np.int64)) if len(s) else 0 for k in odd])
        m = np.array(rows, dtype=np.int64).reshape(-1, 4)
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *[pa.array(m[:, k]) for k in range(4)]], names=["doc_id", "m0", "m1", "m2", "m3"])


def _feature_counts(chars: CharModel):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        restorer = Restorer(chars)
        for batch in batches:
            y = batch.column("y").to_numpy(zero_copy_only=False) > 0
            data, offsets = restored(batch.column("text"), restorer)
            for a, b in K.chunks(offsets):
                owner, hashes = word_features(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
                pairs = np.concatenate([np.column_stack([hashes[:, k], owner.astype(np.uint64)])[hashes[:, k] != 0] for k in range(hashes.shape[1])])
                order = np.lexsort((pairs[:, 1], pairs[:, 0]))
                pairs = pairs[order]
                new = np.ones(len(pairs), dtype=bool)
                new[1:] = (pairs[1:] != pairs[:-1]).any(1)
                at = np.flatnonzero(new)
                times = np.minimum(np.diff(np.append(at, len(pairs))), COUNT_CAP)
                keys, place = np.unique(pairs[at, 0], return_inverse=True)
                toxic = y[a:b][pairs[at, 1].astype(np.int64)]
                counts = [np.bincount(place, weights=w, minlength=len(keys)).astype(np.int64) for w in (toxic, times * toxic, times * ~toxic)]
                yield pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64)), *map(pa.array, counts)], names=["f", "docs", "n1", "n0"])

    return run


def _evidence_batches(model: ToxicModel, keep: tuple[str, ...], names: tuple[str, ...], score: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        restorer = Restorer(model.chars) if model.chars else None
        for batch in batches:
            e = _evidence(batch.column("text"), model, restorer)
            values = [model.scores(e)] if score else list(e.T)
            yield pa.RecordBatch.from_arrays([*[batch.column(c) for c in keep], *map(pa.array, values)], names=list(names))

    return run


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2, steps: int = 30) -> np.ndarray:
    """Newton steps of ridge logistic regression; the first coefficient is the constant."""
    a = np.column_stack([np.ones(len(x)), x])
    w = np.zeros(a.shape[1])
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(a @ w, -30, 30)))
        h = a.T * (p * (1 - p)) @ a + ridge * np.eye(len(w))
        w = w + np.linalg.solve(h, a.T @ (y - p) - ridge * w)
    return w


def train(docs: DataFrame, labels: DataFrame, label: str = "toxic", rows: int = SAMPLE_ROWS) -> ToxicModel:
    """Character counts over all documents; weights from seven tenths of a sample of labelled rows without near
    copies, the score's coefficients from the rest. Without both classes every score is the smoothed share."""
    counts = corpus_counts(docs)
    chars = CharModel.of(counts)
    sample = materialise(labelled_texts(docs, labels, label, rows).select(F.col("doc_id").cast("long"), "text", "y"))
    marks = sample.mapInArrow(_marks, "doc_id long, m0 long, m1 long, m2 long, m3 long").toPandas().sort_values("doc_id")  # `rows` rows at most
    seen: set[tuple[int, int]] = set()
    first = []
    for doc_id, *m in marks.drop_duplicates("doc_id").itertuples(index=False):
        values = set(enumerate(m))
        if not values & seen:
            first.append(int(doc_id))
        seen |= values
    model = ToxicModel(chars=chars)
    if not first:
        return model
    spark = docs.sparkSession
    chosen = spark.createDataFrame([(i,) for i in first], "doc_id long")
    sample = sample.join(F.broadcast(chosen), "doc_id").withColumn("fit", F.pmod(F.crc32(F.concat(F.lit("fit"), F.col("doc_id").cast("string"))), F.lit(10)) < 7)
    sizes = {r["y"] > 0: r["n"] for r in sample.where("fit").groupBy("y").agg(F.count("*").alias("n")).collect()}
    pos, neg = sizes.get(True, 0), sizes.get(False, 0)
    share = (pos + 1) / (pos + neg + 2)
    model.coefficients[0] = math.log(share / (1 - share))
    if not pos or not neg:
        return model
    sums = [F.sum(c).alias(c) for c in ("docs", "n1", "n0")]
    counted = sample.where("fit").select("text", "y").mapInArrow(_feature_counts(chars), "f long, docs long, n1 long, n0 long").groupBy("f").agg(*sums)
    n1, n0 = F.col("n1") + 0.5, F.col("n0") + 0.5
    weight = F.log(n1 / n0 * (neg / pos)) - DEVIATIONS * F.sqrt(1 / n1 + 1 / n0)
    found = counted.where(F.col("docs") >= LEAST_DOCS).withColumn("w", weight).where(F.col("w") >= LEAST_WEIGHT).select("f", "w").toPandas()
    order = np.argsort(found["f"].to_numpy().view(np.uint64), kind="stable")
    model.keys, model.weights = found["f"].to_numpy().view(np.uint64)[order], found["w"].to_numpy()[order]
    rest = sample.where("NOT fit").select("y", "text").mapInArrow(_evidence_batches(model, ("y",), ("y", *EVIDENCE), False), "y double, " + ", ".join(f"{c} double" for c in EVIDENCE)).toPandas()
    if rest["y"].nunique() == 2:
        model.coefficients = logistic(rest[list(EVIDENCE)].to_numpy(), (rest["y"] > 0).to_numpy().astype(float))
    return model


def score_toxicity(docs: DataFrame, model: ToxicModel) -> DataFrame:
    """doc_id, score for every row; a null or empty text has no evidence. Repeated rows stay."""
    small_batches(docs.sparkSession)
    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    return rows.mapInArrow(_evidence_batches(model, ("doc_id",), ("doc_id", "score"), True), "doc_id long, score double")


def op10_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Toxicity score of every document, learned from four fifths of the labels."""
    docs = table(spark, sf_dir, "documents")
    model = train(docs, table(spark, sf_dir, "labels"))
    return score_toxicity(docs, model).select("doc_id", held_out("doc_id").alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
