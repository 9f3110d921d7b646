"""Context-tree weighting over bytes, each byte decomposed into eight binary choices.

Bit j of a byte is coded under the j bits before it by a tree over the preceding
bytes: a node at depth d stands for d bytes of context. Every node has a
Krichevsky-Trofimov estimate of its bits; a node's weighted probability is the mean of
its own estimate and the product of its children's. The weighted probability of a
block depends on counts alone, so trees are built from counts of (context, byte)
windows, deepest level first, without a pass over the text in order. A prediction
mixes the estimates along a path with the weights that the counts leave them.

A window packs the byte in its lowest eight bits and the bytes before it above, the
nearest lowest. A text ends with a zero byte and is preceded by zero bytes. Windows
whose nearest ``d`` context bytes are equal share a subtree below depth d and nothing
else does, so subtrees are built apart: ``lower_levels`` makes one set of subtrees and
the sums that its parents need, ``upper_levels`` the nodes above from those sums.
"""

from __future__ import annotations

from math import lgamma

import numpy as np

BITS = 8
_LGAMMA = np.array([lgamma(k + 0.5) for k in range(4096)])
_LFACT = np.array([lgamma(k + 1.0) for k in range(4096)])
#: (depth, bit): node numbers in order, weight of each node's own estimate, its chance of a one.
Levels = dict[tuple[int, int], tuple[np.ndarray, np.ndarray, np.ndarray]]
#: bit: node numbers in order, their bits, their ones, the sum of their children's weighted logs.
Sums = dict[int, tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]


def _log_gamma(x: np.ndarray, table: np.ndarray, shift: float) -> np.ndarray:
    """log Gamma(x + shift) for whole x; a series beyond the table."""
    out = table[np.minimum(x, len(table) - 1)]
    big = x >= len(table)
    if big.any():
        z = x[big] + shift
        out[big] = (z - 0.5) * np.log(z) - z + 0.9189385332046727 + 1 / (12 * z) - 1 / (360 * z**3)
    return out


def log_kt(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Natural log of the block estimate of a zeros and b ones."""
    return _log_gamma(a, _LGAMMA, 0.5) + _log_gamma(b, _LGAMMA, 0.5) - 2 * _LGAMMA[0] - _log_gamma(a + b, _LFACT, 1.0)


def windows(texts: list[bytes], depth: int) -> tuple[np.ndarray, np.ndarray]:
    """All windows of the texts in order, and where each text's begin (one more entry at the end)."""
    gap = b"\0" * depth
    data = np.frombuffer(gap + gap.join(texts) + gap, np.uint8)
    sizes = np.array([len(t) for t in texts], np.int64)
    starts = depth + np.concatenate([[0], np.cumsum(sizes + depth)[:-1]])
    packed = np.zeros(len(data) - depth, np.uint64)
    for d in range(depth + 1):
        packed |= data[depth - d : len(data) - d].astype(np.uint64) << np.uint64(BITS * d)
    keep = np.ones(len(packed), bool)
    ends = starts - depth + sizes
    for k in range(1, depth):
        at = ends + k
        keep[at[at < len(keep)]] = False
    return packed[keep], np.concatenate([[0], np.cumsum(sizes + 1)])


def counted(keys: np.ndarray, counts: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys in order and their counts."""
    if counts is None:
        keys = np.sort(keys)
    else:
        order = np.argsort(keys, kind="stable")
        keys, counts = keys[order], counts[order]
    if not len(keys):
        return keys, np.empty(0, np.int64)
    first = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))
    if counts is None:
        return keys[first], np.diff(np.append(first, len(keys)))
    return keys[first], np.add.reduceat(counts, first)


def _low(bits: int) -> np.uint64:
    return np.uint64((1 << bits) - 1)


def _summed(number: np.ndarray, *columns: np.ndarray) -> tuple[np.ndarray, ...]:
    """Distinct numbers in order and the sums of the columns over each."""
    if not len(number):
        return (number, *columns)
    order = np.argsort(number, kind="stable")
    number = number[order]
    first = np.flatnonzero(np.concatenate([[True], number[1:] != number[:-1]]))
    return (number[first], *(np.add.reduceat(c[order], first) for c in columns))


def _node(total: np.ndarray, ones: np.ndarray, rest: np.ndarray | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Weighted log, weight of the own estimate and chance of a one; ``rest`` is None at the deepest level."""
    own = log_kt(total - ones, ones)
    one = (ones + 0.5) / (total + 1)
    if rest is None:
        return own, np.ones(len(own)), one
    return np.logaddexp(own, rest) - np.log(2), np.exp(-np.logaddexp(0, rest - own)), one


def _climb(levels: Levels, depth: int, j: int, sums: tuple, leaf: bool) -> tuple[np.ndarray, ...]:
    """Adds the nodes of ``depth`` from their sums; returns the sums of their parents."""
    number, total, ones, rest = sums
    log, share, one = _node(total, ones, None if leaf else rest)
    levels[depth, j] = (number, share, one)
    if not depth:
        return number, total, ones, log
    parent = (((number >> np.uint64(j)) & _low(BITS * (depth - 1))) << np.uint64(j)) | (number & _low(j))
    return _summed(parent, total, ones, log)


def lower_levels(keys: np.ndarray, counts: np.ndarray, depth: int, top: int = 0) -> tuple[Levels, Sums]:
    """Nodes of depths ``top`` to ``depth``, and the sums of their parents (at ``top`` 0: of the roots themselves)."""
    levels: Levels = {}
    sums: Sums = {}
    keys, counts = np.asarray(keys, np.uint64), np.asarray(counts, np.int64)
    keys, counts = keys[counts > 0], counts[counts > 0]
    for j in range(BITS):
        one = ((keys >> np.uint64(BITS - 1 - j)) & np.uint64(1)).astype(np.int64)
        at = (*_summed(keys >> np.uint64(BITS - j), counts, counts * one), None)
        for d in range(depth, top - 1, -1):
            at = _climb(levels, d, j, at, d == depth)
        sums[j] = at
    return levels, sums


def upper_levels(sums: Sums, top: int) -> Levels:
    """Nodes of all depths below ``top`` from the sums of depth ``top`` - 1, each number once a bit."""
    levels: Levels = {}
    for j in range(BITS):
        at = sums.get(j, (np.empty(0, np.uint64), np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0)))
        for d in range(top - 1, -1, -1):
            at = _climb(levels, d, j, at, False)
    return levels


def log10_chances(levels: Levels, depth: int, keys: np.ndarray) -> np.ndarray:
    """log10 of the chance of each window's byte after its context; a node never met says 1/2."""
    out = np.zeros(len(keys))
    for j in range(BITS):
        chance = np.full(len(keys), 0.5)
        bit = ((keys >> np.uint64(BITS - 1 - j)) & np.uint64(1)).astype(bool)
        for d in range(depth, -1, -1):
            number, share, one = levels[d, j]
            if not len(number):
                continue
            of = (keys & _low(BITS * (d + 1))) >> np.uint64(BITS - j)
            at = np.minimum(np.searchsorted(number, of), len(number) - 1)
            here = number[at] == of
            p = np.where(bit, one[at], 1 - one[at])
            chance = np.where(here, share[at] * p + (1 - share[at]) * chance, chance)
        out += np.log10(chance)
    return out
