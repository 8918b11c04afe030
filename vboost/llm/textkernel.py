"""Vectorised word and shingle hashing on the bytes of Arrow string columns.

Words are maximal runs of bytes other than space and 0x09-0x0D; A-Z are folded to a-z. A word's hash is a
polynomial over a table of random 64-bit byte values, taken from one running sum, so no Python loop runs over
words. Long texts are hashed in pieces cut at separators: memory follows the number of words, not 32 bytes a byte.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

PIECE = 1 << 19
CHUNK = 1 << 21
_U = np.uint64


def _odd_powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, dtype=np.uint64)
    out[0] = 1
    return np.cumprod(out, dtype=np.uint64)


_BASE = 0x9E3779B97F4A7C15
_BYTE = np.random.Generator(np.random.PCG64(20240607)).integers(1, 2**64 - 1, size=256, dtype=np.uint64)
_BYTE[65:91] = _BYTE[97:123]
_GAP = np.zeros(256, dtype=bool)
_GAP[[0x20, *range(0x09, 0x0E)]] = True
#: All ASCII but letters and digits, for words without their punctuation.
BREAKS = np.r_[np.ones(128, dtype=bool), np.zeros(128, dtype=bool)]
BREAKS[[*range(48, 58), *range(65, 91), *range(97, 123)]] = False
_POWER = _odd_powers(_BASE, PIECE + 1)
_INVERSE = _odd_powers(pow(_BASE, -1, 2**64), PIECE + 1)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser on 64-bit values."""
    x = x ^ (x >> _U(30))
    x = x * _U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> _U(27))
    x = x * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and 64-bit offsets of a string column; a null is an empty text."""
    if not pa.types.is_large_binary(column.type):
        column = column.fill_null("").cast(pa.large_string()) if column.null_count else column.cast(pa.large_string())
    buffers = column.buffers()
    offsets = np.frombuffer(buffers[1], dtype=np.int64, count=column.offset + len(column) + 1)[column.offset :]
    data = np.frombuffer(buffers[2], dtype=np.uint8) if buffers[2] is not None else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def chunks(offsets: np.ndarray, limit: int = CHUNK) -> Iterator[tuple[int, int]]:
    """Runs of whole texts of about `limit` bytes; a longer text stands alone."""
    at, n = 0, len(offsets) - 1
    while at < n:
        to = int(np.searchsorted(offsets, offsets[at] + limit, side="right")) - 1
        to = min(max(to, at + 1), n)
        yield at, to
        at = to


def _cuts(data: np.ndarray, gap: np.ndarray, first: np.ndarray) -> Iterator[tuple[int, int]]:
    at, size = 0, len(data)
    while at < size:
        to = min(at + PIECE, size)
        if to < size:
            free = np.flatnonzero(gap[at + 1 : to + 1] | first[at + 1 : to + 1])
            if len(free):
                to = at + 1 + int(free[-1])
            else:  # one word longer than a piece
                beyond = np.flatnonzero(gap[to:] | first[to:])
                to = to + int(beyond[0]) if len(beyond) else size
        yield at, to
        at = to


def hash_words(data: np.ndarray, offsets: np.ndarray, gaps: np.ndarray = _GAP, prefixes: tuple[int, ...] = ()) -> tuple[np.ndarray, ...]:
    """Start, end, text number and hash of every word of the texts laid end to end.

    gaps: flags of the bytes between words. For each of `prefixes` follows the hash of a word's first so many bytes,
    0 for shorter words.
    """
    gap = gaps[data]
    first = np.zeros(len(data) + 1, dtype=bool)
    first[offsets] = True
    first = first[: len(data)]
    starts, ends, hashes = [], [], []
    heads: list[list[np.ndarray]] = [[] for _ in prefixes]
    for lo, hi in _cuts(data, gap, first):
        word = ~gap[lo:hi]
        opens = word.copy()
        opens[1:] &= ~word[:-1] | first[lo + 1 : hi]
        closes = word.copy()
        closes[:-1] &= ~word[1:] | first[lo + 1 : hi]
        a, b = np.flatnonzero(opens), np.flatnonzero(closes) + 1
        if not len(a):
            continue
        size = hi - lo
        if size <= PIECE:
            power, inverse = _POWER[:size], _INVERSE
        else:
            power, inverse = _odd_powers(_BASE, size), _odd_powers(pow(_BASE, -1, 2**64), size)
        total = np.zeros(size + 1, dtype=np.uint64)
        np.cumsum(_BYTE[data[lo:hi]] * power, out=total[1:])
        hashes.append(mix((total[b] - total[a]) * inverse[a] ^ (b - a).astype(np.uint64)))
        for out, length in zip(heads, prefixes):
            to = np.minimum(a + length, b)
            out.append(np.where(b - a >= length, mix((total[to] - total[a]) * inverse[a] ^ _U(1000 + length)), _U(0)))
        starts.append(a + lo)
        ends.append(b + lo)
    if not starts:
        none = np.zeros(0, np.int64)
        return none, none, none, *[np.zeros(0, np.uint64)] * (1 + len(prefixes))
    start = np.concatenate(starts)
    return start, np.concatenate(ends), np.searchsorted(offsets, start, side="right") - 1, np.concatenate(hashes), *map(np.concatenate, heads)


def shingle_sets(data: np.ndarray, offsets: np.ndarray, width: int = 5) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of each text; with fewer words than `width`, the whole sequence as one."""
    _, _, owner, words = hash_words(data, offsets)
    texts = len(offsets) - 1
    counts = np.bincount(owner, minlength=texts)
    base = _U(0xD6E8FEB86659FD93)
    last = np.concatenate([[0], np.cumsum(counts)])
    grams = np.zeros(max(len(words) - width + 1, 0), dtype=np.uint64)
    for k in range(width):
        grams = grams * base + words[k : k + len(grams)]
    grams = mix(grams)
    out = []
    for i in range(texts):
        n, at = int(counts[i]), int(last[i])
        if n >= width:
            out.append(np.unique(grams[at : at + n - width + 1]))
        elif n:
            h = np.zeros(1, dtype=np.uint64)
            for w in words[at : at + n]:
                h = h * base + w
            out.append(mix(h ^ _U(n << 32)))
        else:
            out.append(grams[:0])
    return out
