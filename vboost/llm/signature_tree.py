"""Signature tree over shingle sets: OR-combined token bitmaps and size ranges, joined by dual traversal."""

from __future__ import annotations

import numpy as np

BITS = 2048
FAN = 8
FRONT = 2048


class SignatureTree:
    """Leaves are sets; an inner node holds the OR of its leaves' bitmaps, their size range and their bit excess.

    Two sets share at most popcount(bits of both) + excess elements, the excess being the elements of one set
    that fall on a bit already taken. The same holds for nodes with the OR of bits and the largest excess.
    """

    def __init__(self, sets: list[np.ndarray], sizes: np.ndarray, vocabulary: np.ndarray):
        order = np.lexsort((sizes, [s[0] if len(s) else 0 for s in sets]))
        self.order, self.sets = order, [sets[i] for i in order]
        sizes = np.asarray(sizes, dtype=np.int64)[order]
        flags = np.zeros((len(sets), BITS), dtype=bool)
        for row, values in enumerate(self.sets):
            flags[row, np.searchsorted(vocabulary, values) % BITS] = True
        bits = np.packbits(flags, axis=1).view(np.uint64)
        # elements that can be shared at all are those of the vocabulary; the rest count in the size alone
        shared = np.array([len(s) for s in self.sets], dtype=np.int64)
        excess = shared - np.bitwise_count(bits).sum(axis=1, dtype=np.int64)
        self.levels = [{"bits": bits, "low": sizes, "high": sizes, "excess": excess, "most": shared}]
        while len(self.levels[-1]["low"]) > 1:
            x = self.levels[-1]
            cut = np.arange(0, len(x["low"]), FAN)
            self.levels.append(
                {
                    "bits": np.bitwise_or.reduceat(x["bits"], cut, axis=0),
                    "low": np.minimum.reduceat(x["low"], cut),
                    "high": np.maximum.reduceat(x["high"], cut),
                    "excess": np.maximum.reduceat(x["excess"], cut),
                    "most": np.maximum.reduceat(x["most"], cut),
                }
            )

    def children(self, level: int, nodes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Child numbers one level down, and for each the position of its parent in `nodes`."""
        below = len(self.levels[level - 1]["low"])
        child = (nodes[:, None] * FAN + np.arange(FAN)).ravel()
        parent = np.repeat(np.arange(len(nodes)), FAN)
        keep = child < below
        return child[keep], parent[keep]


def _may_link(a: dict, b: dict, i: np.ndarray, j: np.ndarray, percent: int) -> np.ndarray:
    low_a, low_b = a["low"][i], b["low"][j]
    ok = (100 * a["high"][i] >= percent * low_b) & (100 * b["high"][j] >= percent * low_a)
    need = percent * (low_a + low_b)
    ok &= (100 + percent) * np.minimum(a["most"][i], b["most"][j]) >= need
    at = np.flatnonzero(ok)
    common = np.bitwise_count(a["bits"][i[at]] & b["bits"][j[at]]).sum(axis=1, dtype=np.int64)
    most = common + np.minimum(a["excess"][i[at]], b["excess"][j[at]])
    ok[at] = (100 + percent) * most >= need[at]
    return ok


class _Groups:
    """Union-find over the leaves of one or two trees."""

    def __init__(self, labels: np.ndarray):
        _, self.up = np.unique(labels, return_index=True)
        self.up = self.up[np.unique(labels, return_inverse=True)[1]].astype(np.int64)

    def roots(self) -> np.ndarray:
        while True:
            above = self.up[self.up]
            if np.array_equal(above, self.up):
                return self.up
            self.up = above

    def find(self, i: int) -> int:
        while self.up[i] != i:
            self.up[i] = self.up[self.up[i]]
            i = int(self.up[i])
        return i


def dual_join(
    ids: np.ndarray, sizes: np.ndarray, sets: list[np.ndarray], labels: np.ndarray, right: np.ndarray | None, percent: int
) -> list[tuple[int, int]]:
    """Links that join all sets of Jaccard similarity of percent/100 or more into their groups.

    right: marks the sets of the second tree; None joins one tree with itself. Sets with equal labels are known to
    be of one group. A pair whose sets already are of one group adds nothing and is not compared.
    """
    n = len(ids)
    if n < 2:
        return []
    flat = np.concatenate(sets) if n else np.zeros(0, np.int64)
    values, counts = np.unique(flat, return_counts=True)
    vocabulary = values[counts > 1]  # within this task an element of one set alone is shared with none
    sets = [s[np.isin(s, vocabulary, assume_unique=True)] for s in sets]
    sides = [np.arange(n)] * 2 if right is None else [np.flatnonzero(~right), np.flatnonzero(right)]
    if not len(sides[0]) or not len(sides[1]) or not len(vocabulary):
        return []
    trees = [SignatureTree([sets[i] for i in at], sizes[at], vocabulary) for at in (sides if right is not None else sides[:1])]
    left, other = trees[0], trees[-1]
    leaf_a, leaf_b = sides[0][left.order], sides[1][other.order]
    groups, found = _Groups(labels), []
    stack = [(len(left.levels) - 1, len(other.levels) - 1, np.zeros(1, np.int64), np.zeros(1, np.int64))]
    while stack:
        la, lb, i, j = stack.pop()
        if len(i) > FRONT:
            stack.append((la, lb, i[FRONT:], j[FRONT:]))
            i, j = i[:FRONT], j[:FRONT]
        keep = _may_link(left.levels[la], other.levels[lb], i, j, percent)
        i, j = i[keep], j[keep]
        if not len(i):
            continue
        if la == lb == 0:
            roots = groups.roots()
            apart = roots[leaf_a[i]] != roots[leaf_b[j]]
            for a, b in zip(i[apart].tolist(), j[apart].tolist()):
                x, y = int(leaf_a[a]), int(leaf_b[b])
                gx, gy = groups.find(x), groups.find(y)
                if gx == gy:
                    continue
                both = len(np.intersect1d(left.sets[a], other.sets[b], assume_unique=True))
                if 100 * both >= percent * (int(sizes[x]) + int(sizes[y]) - both):
                    groups.up[max(gx, gy)] = min(gx, gy)
                    found.append((int(ids[x]), int(ids[y])))
            continue
        if la >= lb:
            child, parent = left.children(la, i)
            i, j, la = child, j[parent], la - 1
        if lb > la:
            child, parent = other.children(lb, j)
            i, j, lb = i[parent], child, lb - 1
        if right is None and la == lb:
            keep = i <= j if la else i < j
            i, j = i[keep], j[keep]
        if len(i):
            stack.append((la, lb, i, j))
    return found
