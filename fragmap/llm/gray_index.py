"""In-memory Hamming index over fingerprints in Gray order.

Fingerprints are sorted by the rank their bits have as a Gray code, which brings
words of few differing bits together. Every ``FANOUT`` neighbours form a node that
keeps the bits they all share; nodes are grouped again up to the top. A search goes
down from the top: a node adds the differences on bits that its parent did not fix,
and a whole group is left as soon as the sum exceeds the limit.
"""

from __future__ import annotations

import numpy as np

FANOUT = 8
CHUNK = 256


def gray_rank(codes: np.ndarray) -> np.ndarray:
    """Position of each code in the reflected Gray sequence (prefix parity of its bits)."""
    rank = codes.astype(np.uint64).copy()
    for shift in (1, 2, 4, 8, 16, 32):
        rank ^= rank >> np.uint64(shift)
    return rank


class GrayIndex:
    def __init__(self, codes: np.ndarray):
        codes = np.unique(np.asarray(codes, np.uint64))
        self.codes = codes[np.argsort(gray_rank(codes), kind="stable")]
        ones, some = [self.codes], [self.codes]
        while len(ones[-1]) > FANOUT:
            starts = np.arange(0, len(ones[-1]), FANOUT)
            ones.append(np.bitwise_and.reduceat(ones[-1], starts))
            some.append(np.bitwise_or.reduceat(some[-1], starts))
        self.patterns = ones
        self.masks = [~(a ^ o) for a, o in zip(ones, some)]  # bits that all below a node share
        self.added = []  # those of them that its parent leaves open
        for level, mask in enumerate(self.masks):
            over = self.masks[level + 1][np.arange(len(mask)) // FANOUT] if level + 1 < len(self.masks) else np.uint64(0)
            self.added.append(mask & ~over)

    def search(self, queries: np.ndarray, limit: int, after: np.ndarray | None = None):
        """Yields (query number, position in ``codes``) arrays of all codes within ``limit`` bits.

        ``after``: for each query, only positions above it count.
        """
        queries = np.asarray(queries, np.uint64)
        for first in range(0, len(queries), CHUNK):
            part = queries[first : first + CHUNK]
            top = len(self.patterns) - 1
            width = len(self.patterns[top])
            who, node = np.repeat(np.arange(len(part)), width), np.tile(np.arange(width), len(part))
            sofar = np.zeros(len(who), np.uint8)
            for level in range(top, -1, -1):
                pattern, mask = self.patterns[level], self.added[level]
                sofar = sofar + np.bitwise_count((part[who] ^ pattern[node]) & mask[node])
                keep = sofar <= limit
                if after is not None:
                    span = FANOUT**level
                    keep &= (node + 1) * span - 1 > after[first + who]
                who, node, sofar = who[keep], node[keep], sofar[keep]
                if level:
                    below = len(self.patterns[level - 1])
                    who, sofar = np.repeat(who, FANOUT), np.repeat(sofar, FANOUT)
                    node = (node[:, None] * FANOUT + np.arange(FANOUT)).ravel()
                    real = node < below
                    who, node, sofar = who[real], node[real], sofar[real]
            yield first + who, node

    def components(self, limit: int) -> np.ndarray:
        """For each of ``codes``, the position of the first code it is linked with, directly or through others."""
        label = np.arange(len(self.codes))
        for a, b in self.search(self.codes, limit, np.arange(len(self.codes))):
            merge(label, a, b)
        return label


    def forest(self, limit: int) -> tuple[np.ndarray, np.ndarray]:
        """Positions (a, b) of links that join all components, the nearest first, ties by position."""
        found = [np.stack(p) for p in self.search(self.codes, limit, np.arange(len(self.codes)))]
        a, b = np.concatenate(found, axis=1) if found else np.empty((2, 0), np.int64)
        if not len(a):
            return a, b
        order = np.lexsort((b, a, np.bitwise_count(self.codes[a] ^ self.codes[b])))
        a, b = a[order], b[order]
        own = spanning(len(self.codes), a, b)
        return a[own], b[own]


def spanning(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Numbers of links (a, b) among ``n`` nodes that join all components, earlier links first."""
    label, kept, place = np.arange(n), [], np.arange(len(a))
    while True:
        place = place[label[a[place]] != label[b[place]]]
        if not len(place):
            break
        best = np.full(n, len(a))
        np.minimum.at(best, label[a[place]], place)  # each component takes its first way out
        np.minimum.at(best, label[b[place]], place)
        own = np.unique(best[best < len(a)])
        kept.append(own)
        merge(label, a[own], b[own])
    return np.concatenate(kept) if kept else np.empty(0, np.int64)


def merge(label: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
    """Joins the labels of linked positions in place; every label becomes the least of its set."""
    while len(a):
        x, y = label[a], label[b]
        apart = x != y
        a, b, x, y = a[apart], b[apart], x[apart], y[apart]
        if not len(a):
            return
        np.minimum.at(label, np.maximum(x, y), np.minimum(x, y))
        while True:
            up = label[label]
            if (up == label).all():
                break
            label[:] = up
