"""Re-Pair grammar compression of one shard by array operations, and its random-access decoding."""

from __future__ import annotations

import numpy as np


def gather(pool: np.ndarray, start: np.ndarray, size: np.ndarray) -> np.ndarray:
    """The runs pool[start : start + size] laid end to end."""
    ends = np.cumsum(size, dtype=np.int64)
    if not len(ends) or not ends[-1]:
        return pool[:0]
    at = np.repeat(start - (ends - size), size)
    at += np.arange(ends[-1])
    return pool.take(at)


class Grammar:
    """The rules and the symbols left of `ids`, several documents end to end; no pair spans two documents.

    last: the position of each document's last id. A rule is a pair that stands `least` times or more; overlapping
    places of one pair count once. Pairs are taken from the most frequent down until none stands so often, or until
    `most` rules are made. In one turn all pairs whose counts reach the highest power of four are replaced; where two
    of them overlap, the more frequent one is. Rule k is symbol terminals + k and refers to lower symbols alone.

    Places of a pair arise with its newer symbol, all in one turn, and only become fewer. So each pair is listed once,
    and its places are checked when its turn comes: the work follows the ids and the replacements, not the turns.
    """

    def __init__(self, ids: np.ndarray, last: np.ndarray, terminals: int, least: int = 2, most: int | None = None):
        n = self.end = len(ids)
        self.seq = np.append(ids.astype(np.int32), np.int32(-1))  # -1: no symbol, behind the last and where one was taken
        self.after = np.arange(1, n + 2, dtype=np.int32)
        self.after[last] = n
        self.before = np.arange(-1, n, dtype=np.int32)
        self.before[0] = n
        self.before[last + 1] = n
        self.claim = np.zeros(n + 1, dtype=np.int32)
        self.terminals, self.least, self.most = terminals, max(2, least), n if most is None else most
        self.wide, self.deep = int(terminals + min(self.most, n)).bit_length(), int(n).bit_length()
        self.parts, self.made = [np.zeros((0, 2), np.uint32)], 0
        #: By the power of four that their counts reach: keys of pairs, counts, and places, pair after pair.
        self.listed: list[list[tuple[np.ndarray, np.ndarray, np.ndarray]]] = [[] for _ in range(self.deep // 2 + 2)]
        had = -1
        place = np.flatnonzero(self.after[:n] != n)
        self._list(place, self.seq[place], self.seq[np.minimum(place + 1, n)])
        while len(place) and had < self.made < self.most:
            if had >= 0:
                self._list_at(place)
            had = self.made
            while self.made < self.most and any(self.listed):
                self._turn()
            # of runs such as x x x some places were passed over; places of other pairs were all kept
            place = np.flatnonzero(self.seq >= 0)
            place = place[self.seq[place] == self.seq[self.after[place]]]
        self.rules = np.concatenate(self.parts)
        place = np.flatnonzero(self.seq >= 0)
        self.symbols = self.seq[place].astype(np.uint32)
        self.last = np.flatnonzero(self.after[place] == n)

    def _list_at(self, place: np.ndarray) -> None:
        """List the pairs that begin at these places (ascending)."""
        right = self.seq.take(self.after.take(place))
        inner = right >= 0
        place = place[inner]
        self._list(place, self.seq.take(place), right[inner])

    def _list(self, place: np.ndarray, left: np.ndarray, right: np.ndarray) -> None:
        if not len(place):
            return
        key = (left.astype(np.int64) << self.wide) | right
        if 2 * self.wide + self.deep < 64:
            both = key << self.deep | place
            both.sort()
            key, place = both >> self.deep, both & ((1 << self.deep) - 1)
        else:
            order = np.argsort(key, kind="stable")
            key, place = key[order], place[order]
        at = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
        counts = np.diff(at, append=len(key))
        good = np.flatnonzero(counts >= self.least)
        self._hold(key[at[good]], counts[good], place, at[good])

    def _hold(self, keys: np.ndarray, counts: np.ndarray, place: np.ndarray, begin: np.ndarray) -> None:
        """Put pairs, whose places are place[begin : begin + counts], to the lists of their counts."""
        if not len(keys):
            return
        power = (np.frexp(counts)[1] + 1) // 2
        order = np.argsort(power, kind="stable")
        keys, counts = keys[order], counts[order]
        place = gather(place, begin[order], counts)
        upto = np.cumsum(counts)
        cuts = np.flatnonzero(np.diff(power[order])) + 1
        for a, b in zip([0, *cuts], [*cuts, len(keys)]):
            self.listed[int(power[order[a]]) - 1].append((keys[a:b], counts[a:b], place[upto[a] - counts[a] : upto[b - 1]]))

    def _stand(self, place: np.ndarray, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Which places still hold their pair, and of a run such as x x x every other one."""
        after = self.after.take(place)
        ok = self.seq.take(place) == left
        ok &= self.seq.take(after) == right
        twin = np.flatnonzero(ok & (left == right))
        if len(twin):
            follows = np.zeros(len(twin), dtype=bool)
            follows[1:] = after[twin[:-1]] == place[twin[1:]]
            count = np.arange(len(twin))
            run = np.maximum.accumulate(np.where(follows, 0, count))
            ok[twin[(count - run) % 2 == 1]] = False
        return ok

    def _turn(self) -> None:
        """Make rules of the pairs that stand most often."""
        power = max(k for k, x in enumerate(self.listed) if x)
        level = max(self.least, 1 << 2 * power)
        keys, counts, place = (np.concatenate(x) for x in zip(*self.listed[power]))
        self.listed[power] = []
        left, right = (keys >> self.wide).astype(np.int32), (keys & ((1 << self.wide) - 1)).astype(np.int32)
        ok = self._stand(place, np.repeat(left, counts), np.repeat(right, counts))
        place = place[ok]
        counts = np.add.reduceat(ok, np.cumsum(counts) - counts, dtype=np.int64)
        begin = np.cumsum(counts) - counts
        # what has become rarer than the level waits
        waits = np.flatnonzero((counts < level) & (counts >= self.least))
        self._hold(keys[waits], counts[waits], place, begin[waits])
        chosen = np.flatnonzero(counts >= level)
        chosen = chosen[np.argsort(counts[chosen], kind="stable")][-(self.most - self.made) :]
        if not len(chosen):
            return
        place = gather(place, begin[chosen], counts[chosen])
        owner = np.repeat(np.arange(len(chosen), dtype=np.int32), counts[chosen])
        keys, left, right = keys[chosen], left[chosen], right[chosen]
        won = self._claim(place)
        good = np.bincount(owner[won], minlength=len(keys)) >= self.least
        symbol = np.full(len(keys), -1, dtype=np.int32)
        symbol[good] = self.terminals + self.made + np.arange(good.sum())
        self.parts.append(np.stack([left[good], right[good]], axis=1).astype(np.uint32))
        self.made += int(good.sum())
        fails = ~good[owner]
        if fails.any():
            lost, whose = place[fails], owner[fails]
            place, owner, won = place[~fails], owner[~fails], won[~fails]
        else:
            lost = whose = place[:0]
        changed = []
        while len(place):
            self._replace(place[won], symbol[owner[won]])
            changed.append(place[won])
            place, owner = place[~won], owner[~won]
            ok = self._stand(place, left[owner], right[owner])
            place, owner = place[ok], owner[ok]
            won = self._claim(place)
        if len(lost):  # pairs whose places went to others
            ok = self._stand(lost, left[whose], right[whose])
            counts = np.bincount(whose[ok], minlength=len(keys))
            waits = np.flatnonzero(counts >= self.least)
            self._hold(keys[waits], counts[waits], lost[ok], (np.cumsum(counts) - counts)[waits])
        if changed:
            new = np.concatenate(changed)
            new = np.concatenate([new, self.before.take(new).astype(np.int64)])
            if 16 * len(new) < self.end:
                new.sort()
                new = new[np.diff(new, append=self.end) > 0]
                self._list_at(new[self.seq[new] >= 0])
            else:
                fresh = np.zeros(self.end + 1, dtype=bool)
                fresh[new] = True
                fresh &= self.seq >= 0
                self._list_at(np.flatnonzero(fresh))

    def _claim(self, place: np.ndarray) -> np.ndarray:
        """Which places overlap with no later place of the list."""
        number = np.arange(len(place), dtype=np.int32)
        after = self.after.take(place)
        both = np.empty(2 * len(place), np.int64)
        both[::2], both[1::2] = place, after
        self.claim[both] = np.repeat(number, 2)  # the last of a place's claims stays
        return (self.claim.take(place) == number) & (self.claim.take(after) == number)

    def _replace(self, place: np.ndarray, symbol: np.ndarray) -> None:
        gone = self.after.take(place)
        self.seq[place] = symbol
        self.seq[gone] = -1
        beyond = self.after.take(gone)
        self.after[place] = beyond
        self.before[beyond] = place
        self.before[self.end] = self.end


def expansion_lengths(rules: np.ndarray, terminals: int) -> np.ndarray:
    """How many ids each rule stands for. Rules refer to lower symbols, so a few passes over all rules settle them."""
    size = np.ones(terminals + len(rules), dtype=np.int64)
    own = size[terminals:]
    while len(rules):
        new = size[rules[:, 0]] + size[rules[:, 1]]
        if np.array_equal(new, own):
            break
        own[:] = new
    return own


def expand(symbols: np.ndarray, rules: np.ndarray, lengths: np.ndarray, terminals: int) -> np.ndarray:
    """The ids that the symbols stand for; all symbols of one depth at a time."""
    width = np.concatenate([np.ones(terminals, np.int32), lengths.astype(np.int32)])
    children, place = symbols.astype(np.int64), np.cumsum(width[symbols], dtype=np.int64)
    out = np.empty(int(place[-1]) if len(place) else 0, dtype=np.uint32)
    place -= width[symbols]
    left, right = rules[:, 0].astype(np.int64), rules[:, 1].astype(np.int64)
    while len(children):
        out[place] = children  # a rule's place is written again by its first id
        inner = np.flatnonzero(children >= terminals)
        rule, at = children[inner] - terminals, place[inner]
        first = left[rule]
        children, place = np.concatenate([first, right[rule]]), np.concatenate([at, at + width[first]])
    return out


def pack_bits(values: np.ndarray, bits: int) -> bytes:
    """The values' lowest `bits` bits, end to end."""
    wide = np.unpackbits(np.ascontiguousarray(values, dtype=">u4").view(np.uint8).reshape(-1, 4), axis=1)
    return np.packbits(wide[:, 32 - bits :]).tobytes()


def unpack_bits(raw: bytes, bits: int, start: int, stop: int) -> np.ndarray:
    """Values start to stop of what pack_bits wrote."""
    first, n = start * bits, (stop - start) * bits
    some = np.unpackbits(np.frombuffer(raw, dtype=np.uint8)[first // 8 : -(-(first + n) // 8)])[first % 8 : first % 8 + n]
    wide = np.zeros((stop - start, 32), dtype=np.uint8)
    wide[:, 32 - bits :] = some.reshape(-1, bits)
    return np.packbits(wide, axis=1).view(">u4").ravel().astype(np.uint32)
