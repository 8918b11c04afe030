"""Token-ID output with Re-Pair grammar compression.

Documents are range-partitioned and sorted by doc_id; each task cuts its documents into shards of about SHARD_TOKENS
ids and compresses each by Re-Pair: the most frequent pairs of neighbouring symbols become nonterminals, again and
again, until no pair stands `least` times. A file row is one shard: its rules (pairs), the length that each rule
expands to, the symbol sequence, and for each document its first symbol and its number of ids, so one document is
decoded without the others. Symbols, rules and lengths are packed to the bits that the shard needs. No pair spans two
documents.

Encoding is by the tokenizers library. A text of ASCII and Latin-1 letters is cut into the tokenizer's pre-tokens by
array operations on its bytes; their ids laid end to end are the text's ids. The library encodes each distinct
pre-token once for each worker while it stays in a bounded cache; what came again stays longest. Any other text, and
one that holds an added token of the tokenizer, is encoded whole.
"""

from __future__ import annotations

import os
import uuid
import zlib
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import textkernel as K
from .grammar import Grammar, expand, expansion_lengths, gather, pack_bits, unpack_bits
from .common import shared_dir, shuffle_partitions, small_batches, table

END_ID = 0
SHARD_TOKENS = 1 << 19
#: A pair becomes a rule where it stands so often: below, the rule costs more bits than it saves.
LEAST = 4
#: Distinct pre-tokens that a worker remembers while it runs a task (half as many between tasks), their bytes, and
#: pre-tokens in one call of the library.
CACHE_PIECES, CACHE_BYTES, JOINED = 400_000, 1 << 24, 4096
#: Ranges that are looked up one by one; more are left to a range exchange.
MOST_RANGES = 4096
#: More shards than this are joined with their places by a shuffle, not by a broadcast.
BROADCAST_ROWS = 1_000_000
#: Text that is cut at once.
CHUNK_BYTES = 1 << 22
_SPACE, _LETTER, _DIGIT, _MARK = 0, 1, 2, 3
_CLASS = np.full(256, _MARK, dtype=np.uint8)
_CLASS[[10, 32]] = _SPACE
_CLASS[48:58] = _DIGIT
_CLASS[[*range(65, 91), *range(97, 123), *range(128, 256)]] = _LETTER
#: Bytes of texts that are cut here: ASCII but for controls, and the first byte of Latin-1 letters.
_KNOWN = np.zeros(256, dtype=bool)
_KNOWN[[10, *range(32, 127), 0xC3]] = True
_HELD_BY: dict[str, "PieceEncoder"] = {}


def cut_pieces(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Starts of the pre-tokens of texts laid end to end; the bytes are those of `_KNOWN` and of Latin-1 letters.

    A pre-token is a run of letters, digits or marks with the one space before it, a clitic after an apostrophe that
    stands alone, or white space; of white space before a word the last character is apart.
    """
    n = len(data)
    kind = _CLASS[data]
    first = np.zeros(n + 3, dtype=bool)
    first[offsets] = True
    opens = np.empty(n + 3, dtype=bool)
    opens[n:] = True
    opens[:n] = first[:n]
    opens[1:n] |= kind[1:] != kind[:-1]
    space = kind == _SPACE
    # the last of some white space before a word stands apart, and a space belongs to the word
    before = np.flatnonzero(space[:-1] & ~space[1:] & ~first[1:n])
    opens[before] = True
    blank = before[data[before] == 32]
    opens[blank + 1] = False
    at = np.flatnonzero(data == 39)
    at = at[opens[at] & opens[at + 1] & ~first[at + 1]]
    if len(at):
        near = np.concatenate([data, np.zeros(3, np.uint8)])
        one, two = near[at + 1], near[at + 2]
        single = (one == 115) | (one == 116) | (one == 109) | (one == 100)
        double = ((one == 114) | (one == 118)) & (two == 101) | (one == 108) & (two == 108)
        double &= ~first[at + 2]
        for some, size in ((at[single], 2), (at[double], 3)):
            opens[some + 1] = False
            opens[some + size] = True
    return np.flatnonzero(opens[:n])


class PieceEncoder:
    """Ids of texts; the ids of each distinct pre-token are asked of the library once while the cache holds them."""

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.added = [t.content.encode() for t in self.tokenizer.get_added_tokens_decoder().values()]
        words = self.tokenizer.get_vocab(with_added_tokens=False)
        # a byte-level token has one character for each byte
        self.width = np.zeros(self.tokenizer.get_vocab_size(), np.int64)
        self.width[list(words.values())] = np.fromiter(map(len, words), np.int64, len(words))
        self.clear()

    def clear(self) -> None:
        self._hold(pa.array([b""], pa.large_binary()), np.array([END_ID], np.uint16), np.ones(1, np.int32), np.zeros(1, np.int32))

    def _hold(self, known: pa.Array, pool: np.ndarray, size: np.ndarray, seen: np.ndarray) -> None:
        """known: the pieces, the first of which is the end of a text; seen: in how many pieces of text each came."""
        self.known, self.pool, self.size, self.seen = known, pool, size, seen
        self.start = (np.cumsum(size) - size).astype(np.int32)

    def trim(self) -> None:
        """Forget the pre-tokens that came once; of the others the half of the cache that came most often stays."""
        self.seen[0] = np.iinfo(np.int32).max
        kept = np.flatnonzero(self.seen > 1)
        kept = np.sort(kept[np.argsort(-self.seen[kept], kind="stable")[: CACHE_PIECES // 2]])
        known = self.known.take(pa.array(kept))
        if known.nbytes > CACHE_BYTES:
            self.clear()
        else:
            self._hold(known, gather(self.pool, self.start[kept], self.size[kept]), self.size[kept], self.seen[kept] // 2)

    def whole(self, texts: list[str]) -> list[list[int]]:
        return [e.ids for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def learn(self, fresh: pa.Array) -> None:
        """Ask for the ids of new pieces and number them behind the known ones.

        Words that begin with a space are asked for many at a time: side by side they are the same pre-tokens.
        """
        data, offsets = K.text_bytes(fresh)
        begin, width = offsets[:-1], np.diff(offsets)
        word = (width > 1) & (data[begin] == 32)
        word[word] = _CLASS[data[begin[word] + 1]] == _LETTER
        order = np.concatenate([np.flatnonzero(word), np.flatnonzero(~word)])
        words = int(word.sum())
        joined = gather(data, begin[word], width[word]).tobytes()
        ends = np.cumsum(width[word])
        cuts = [0, *ends[JOINED - 1 :: JOINED].tolist(), len(joined)]
        found = self.whole([joined[x:y].decode() for x, y in zip(cuts, cuts[1:])])
        rest = self.whole([x.decode() for x in fresh.take(pa.array(order[words:])).to_pylist()])
        flat = np.fromiter(chain.from_iterable(found), np.uint16, sum(map(len, found)))
        upto = np.cumsum(self.width[flat])
        last = np.searchsorted(upto, ends)
        if words and not np.array_equal(upto[last], ends):
            raise ValueError("a token spans two pre-tokens")
        counts = np.concatenate([np.diff(last, prepend=-1), np.fromiter(map(len, rest), np.int64, len(rest))])
        flat = np.concatenate([flat, np.fromiter(chain.from_iterable(rest), np.uint16, sum(map(len, rest)))])
        start, size = np.empty(len(order), np.int32), np.empty(len(order), np.int32)
        start[order], size[order] = len(self.pool) + np.cumsum(counts) - counts, counts
        self.known = pa.concat_arrays([self.known, fresh])
        self.start, self.size, self.pool = np.concatenate([self.start, start]), np.concatenate([self.size, size]), np.concatenate([self.pool, flat])
        self.seen = np.concatenate([self.seen, np.zeros(len(fresh), np.int32)])

    def _numbers(self, column: pa.Array) -> np.ndarray:
        """The cache's number of each piece of a column: new pieces come behind the known ones in one dictionary."""
        if len(self.known) > CACHE_PIECES or self.known.nbytes > CACHE_BYTES:
            self.trim()
        coded = pa.chunked_array([self.known, column]).dictionary_encode().chunk(1)
        had = len(self.known)
        if len(coded.dictionary) > had:
            self.learn(coded.dictionary.slice(had))
        numbers = coded.indices.to_numpy()
        came = np.zeros(len(self.known), dtype=bool)
        came[numbers] = True
        self.seen += came
        return numbers

    def _cut_and_encode(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        texts = len(offsets) - 1
        numbers = np.zeros(texts, np.int32)  # 0 ends a text
        upto = np.zeros(texts + 1, np.int64)
        if len(data):
            starts = cut_pieces(data, offsets)
            upto = np.searchsorted(starts, offsets)
            column = pa.Array.from_buffers(pa.large_binary(), len(starts), [None, pa.py_buffer(np.append(starts, len(data))), pa.py_buffer(data)])
            numbers = np.zeros(len(starts) + texts, np.int32)
            numbers[np.arange(len(starts)) + np.repeat(np.arange(texts), np.diff(upto))] = self._numbers(column)
        size = self.size[numbers]
        ids = gather(self.pool, self.start[numbers], size)
        ends = np.cumsum(size, dtype=np.int64)[upto[1:] + np.arange(texts)]
        return ids, np.diff(ends, prepend=0)

    def encode(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts end to end, each with its end id, and their number for each text. A null is empty."""
        data, offsets = K.text_bytes(column)
        texts = len(offsets) - 1
        strange = np.flatnonzero(~_KNOWN[data])
        latin = (data[strange] >= 0x80) & (data[strange] < 0xC0) & (data[strange] != 0x97) & (data[strange] != 0xB7) & (data[strange - 1] == 0xC3)
        odd = np.zeros(texts, dtype=bool)
        odd[np.searchsorted(offsets, strange[~latin], side="right") - 1] = True
        for token in self.added:
            odd |= pc.match_substring(column.cast(pa.large_string()).fill_null(""), token.decode()).to_numpy(zero_copy_only=False)
        if not odd.any():
            return self._cut_and_encode(data, offsets)
        size = np.zeros(texts, np.int64)
        plain = np.flatnonzero(~odd)
        one, two = offsets[plain], np.diff(offsets)[plain]
        ids, size[plain] = self._cut_and_encode(gather(data, one, two), np.concatenate([[0], np.cumsum(two)]))
        ends = np.cumsum(size)
        raw = data.tobytes()
        parts, at = [], 0
        for i in np.flatnonzero(odd).tolist():
            parts.append(ids[at : ends[i]])
            found = self.whole([raw[offsets[i] : offsets[i + 1]].decode()])[0]
            parts.append(np.array([*found, END_ID], dtype=np.uint16))
            at, size[i] = ends[i], len(found) + 1
        return np.concatenate([*parts, ids[at:]]), size


def encoder(path: str) -> PieceEncoder:
    """This worker's encoder: the vocabulary stays loaded."""
    if path not in _HELD_BY:
        _HELD_BY[path] = PieceEncoder(path)
    return _HELD_BY[path]


FILE = """part int, seq int, terminals int, n_rules int, n_symbols int, length_bits int, doc_ids array<long>, doc_tokens array<int>, doc_symbols array<int>,
n_tokens long, rules binary, rule_lengths binary, symbols binary"""
_KINDS = [pa.int32()] * 6 + [pa.list_(pa.int64()), pa.list_(pa.int32()), pa.list_(pa.int32()), pa.int64(), pa.binary(), pa.binary(), pa.binary()]


def _bits(terminals: int, rules: int) -> int:
    return int(terminals + rules - 1).bit_length()


def shard_row(ids: np.ndarray, size: np.ndarray, terminals: int, least: int, most: int | None) -> dict:
    """What a file holds of documents laid end to end, but for their names."""
    g = Grammar(ids, np.cumsum(size) - 1, terminals, least, most)
    bits, lengths = _bits(terminals, len(g.rules)), expansion_lengths(g.rules, terminals)
    deep = int(lengths.max()).bit_length() if len(lengths) else 1
    return {
        "terminals": terminals,
        "n_rules": len(g.rules),
        "n_symbols": len(g.symbols),
        "length_bits": deep,
        "doc_tokens": size,
        "doc_symbols": np.diff(g.last, prepend=-1),
        "n_tokens": len(ids),
        "rules": pack_bits(g.rules.ravel(), bits),
        "rule_lengths": pack_bits(lengths, deep),
        "symbols": pack_bits(g.symbols, bits),
    }


def shard_ids(row: dict, start: int = 0, stop: int | None = None) -> np.ndarray:
    """The ids that symbols start to stop of a shard stand for."""
    bits, n = _bits(row["terminals"], row["n_rules"]), row["n_rules"]
    rules = unpack_bits(row["rules"], bits, 0, 2 * n).reshape(-1, 2)
    lengths = unpack_bits(row["rule_lengths"], row["length_bits"], 0, n)
    return expand(unpack_bits(row["symbols"], bits, start, row["n_symbols"] if stop is None else stop), rules, lengths, row["terminals"])


def _writer(path: str, terminals: int, shard_tokens: int, least: int, most: int | None):
    names = [x.split()[0] for x in FILE.replace("\n", " ").split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, part, seq = encoder(path), TaskContext.get().partitionId(), 0
        held: list[tuple[pa.Array, np.ndarray, np.ndarray]] = []
        waiting = 0

        def shard() -> pa.RecordBatch:
            doc_ids, ids, size = pa.concat_arrays([x[0] for x in held]), np.concatenate([x[1] for x in held]), np.concatenate([x[2] for x in held])
            row = shard_row(ids, size, terminals, least, most) | {"part": part, "seq": seq, "doc_ids": doc_ids}
            return pa.RecordBatch.from_arrays([pa.array([row[n]], type=k) for n, k in zip(names, _KINDS)], names=names)

        try:
            for batch in batches:
                _, offsets = K.text_bytes(batch.column(1))
                for lo, hi in K.chunks(offsets, CHUNK_BYTES):
                    ids, size = enc.encode(batch.column(1).slice(lo, hi - lo))
                    at, upto = 0, np.cumsum(size)
                    while at < len(size):
                        # up to the document that fills the shard
                        before = int(upto[at - 1]) if at else 0
                        to = min(int(np.searchsorted(upto, before + shard_tokens - waiting)) + 1, len(size))
                        held.append((batch.column(0).slice(lo + at, to - at), ids[before : upto[to - 1]].copy(), size[at:to]))
                        waiting += int(upto[to - 1]) - before
                        at = to
                        if waiting >= shard_tokens:
                            yield shard()
                            held, waiting, seq = [], 0, seq + 1
            if held:
                yield shard()
        finally:
            enc.trim()

    return run


def by_ranges(rows: DataFrame, key: str, n: int) -> DataFrame:
    """The rows in n ranges of a key, in order. The ranges come from a sketch of the key's column alone: a range exchange
    would read the texts a second time to sample it."""
    if n > MOST_RANGES:
        return rows.repartitionByRange(n, key)
    cuts = rows.agg(F.percentile_approx(key, [k / n for k in range(1, n)] or [0.5], max(10_000, 20 * n))).first()[0] or []
    edges = F.array(*map(F.lit, sorted(set(cuts)))) if cuts else F.array().cast("array<bigint>")
    return rows.repartitionById(n, F.size(F.filter(edges, lambda c: c < F.col(key))))


def write_tokens(docs: DataFrame, folder: str, tokenizer: str, shard_tokens: int = SHARD_TOKENS, partitions: int | None = None, least: int = LEAST, most_rules: int | None = None) -> None:
    """Encode doc_id, text in ascending doc_id order (nulls first, ties by the text) and write the shards to `folder`.

    Null or empty texts are the end id alone. Repeated rows stay; rows of one doc_id meet in one task. An empty table
    writes no shard. An id must fit 16 bits; a longer document is a shard of its own. least: how often a pair
    must stand to become a rule; most_rules: rules of a shard at most (None: as many as there are).
    """
    from tokenizers import Tokenizer

    small_batches(docs.sparkSession)
    terminals = Tokenizer.from_file(tokenizer).get_vocab_size()
    n = partitions or shuffle_partitions(docs.sparkSession)
    rows = by_ranges(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")), "doc_id", n).sortWithinPartitions("doc_id", "text")
    rows.mapInArrow(_writer(tokenizer, terminals, shard_tokens, least, most_rules), FILE).write.parquet(folder)


def _decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for k in range(batch.num_rows):
            columns = {n: batch.column(n)[k] for n in batch.schema.names}
            ids = shard_ids({n: columns[n].as_py() for n in ("terminals", "n_rules", "n_symbols", "length_bits", "rules", "rule_lengths", "symbols")})
            size = columns["doc_tokens"].values.to_numpy().astype(np.int64)
            ends = np.cumsum(size)
            raw = memoryview(ids.astype("<u4", copy=False)).cast("B")
            crc = [zlib.crc32(raw[4 * (e - s) : 4 * e]) for s, e in zip(size.tolist(), ends.tolist())]
            out = [columns["doc_ids"].values, pa.array(ends - size + columns["base"].as_py()), pa.array(size), pa.array(crc, pa.int64())]
            yield pa.RecordBatch.from_arrays(out, names=["doc_id", "start", "n_tokens", "ids_crc32"])


def read_digests(spark: SparkSession, folder: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of each document in the files."""
    shards = spark.read.schema(FILE).parquet(folder)
    sizes = shards.select("part", "seq", "n_tokens")
    # a row for each task that wrote: their number is the writer's partitions
    totals = sizes.groupBy("part").agg(F.sum("n_tokens").alias("n")).orderBy("part").collect()
    before, base = [], 0
    for r in totals:
        before.append((r["part"], base))
        base += r["n"]
    offsets = spark.createDataFrame(before, "part int, before long")
    running = F.sum("n_tokens").over(Window.partitionBy("part").orderBy("seq").rowsBetween(Window.unboundedPreceding, -1))
    bases = sizes.select("part", "seq", F.coalesce(running, F.lit(0)).alias("within")).join(F.broadcast(offsets), "part")
    bases = bases.select("part", "seq", (F.col("within") + F.col("before")).alias("base"))
    few = sizes.count() <= BROADCAST_ROWS
    return shards.join(F.broadcast(bases) if few else bases, ["part", "seq"]).mapInArrow(_decode, "doc_id long, start long, n_tokens long, ids_crc32 long")


def read_document(spark: SparkSession, folder: str, doc_id: int) -> list[list[int]]:
    """The ids of each document with this doc_id, decoded from its own symbols alone."""
    out = []
    for row in spark.read.schema(FILE).parquet(folder).where(F.array_contains("doc_ids", F.lit(doc_id).cast("long"))).toLocalIterator():
        ends = np.cumsum(row["doc_symbols"]).tolist()
        out += [shard_ids(row.asDict(), e - s, e).tolist() for d, s, e in zip(row["doc_ids"], row["doc_symbols"], ends) if d == doc_id]
    return out


def token_digests(docs: DataFrame, tokenizer: str | None = None) -> DataFrame:
    """Write the documents' ids to the shared folder and return what is read back."""
    if tokenizer is None:
        import public_tokenizers

        tokenizer = public_tokenizers.path("byte_bpe_50k.json")
    spark = docs.sparkSession
    folder = f"{shared_dir(spark)}/tokens-{uuid.uuid4().hex}"
    write_tokens(docs, folder, tokenizer)
    return read_digests(spark, folder)


def op8_token_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Digests of every document's ids as read back from the files."""
    return token_digests(table(spark, sf_dir, "documents"))
