"""Context-tree weighting against a plain recursive version, and the unigram base by hand."""

import math
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from fragmap.llm import context_tree, lm_score

TEXTS = ["the cat sat on the mat", "The  cat\nsat on the hat", "a cat and a hat", "", None, "zebra 漢字 é", "the cat sat on the mat"]


def _bits(texts, depth):
    """(contexts from the nearest byte on, bit prefix, bit) of every binary choice."""
    for t in texts:
        data = b"\0" * depth + t + b"\0"
        for i in range(depth, len(data)):
            ctx = bytes(reversed(data[i - depth : i]))
            for j in range(8):
                yield ctx, (j, data[i] >> (8 - j)), (data[i] >> (7 - j)) & 1


class PlainTree:
    """One recursion per node, from the definition; logs of products of single KT steps."""

    def __init__(self, texts, depth):
        self.depth, self.counts, self.children = depth, defaultdict(lambda: [0, 0]), defaultdict(set)
        for ctx, prefix, bit in _bits(texts, depth):
            for d in range(depth + 1):
                self.counts[ctx[:d], prefix][bit] += 1
                if d:
                    self.children[ctx[: d - 1], prefix].add(ctx[:d])
        self.memo = {}

    def kt(self, node):
        a, b = self.counts[node] if node in self.counts else (0, 0)
        steps = [(i + 0.5) / (i + 1) for i in range(a)] + [(i + 0.5) / (a + i + 1) for i in range(b)]
        return math.fsum(map(math.log, steps))

    def logs(self, node):
        """(own, product of the children, weighted)."""
        if node not in self.memo:
            ctx, prefix = node
            own = self.kt(node)
            if len(ctx) == self.depth:
                self.memo[node] = own, None, own
            else:
                rest = math.fsum(self.logs((c, prefix))[2] for c in sorted(self.children[node]))
                self.memo[node] = own, rest, math.log(math.exp(own) / 2 + math.exp(rest) / 2)
        return self.memo[node]

    def chance(self, ctx, prefix, bit, d=0):
        node = (ctx[:d], prefix)
        if node not in self.counts:
            return 0.5
        a, b = self.counts[node]
        p = ((b if bit else a) + 0.5) / (a + b + 1)
        if d == self.depth:
            return p
        own, rest, weighted = self.logs(node)
        share = math.exp(own - math.log(2) - weighted)
        return share * p + (1 - share) * self.chance(ctx, prefix, bit, d + 1)

    def log10(self, text):
        return math.fsum(math.log10(self.chance(*x)) for x in _bits([text], self.depth))


def _norm(t):
    return b" ".join((t or "").encode().lower().split())


def test_windows_pad_and_end_texts():
    keys, starts = context_tree.windows([b"abc", b"", b"z"], 2)
    assert starts.tolist() == [0, 4, 5, 7]
    assert [k.to_bytes(3, "big") for k in keys.tolist()] == [b"\0\0a", b"\0ab", b"abc", b"bc\0", b"\0\0\0", b"\0\0z", b"\0z\0"]


def test_subtrees_make_the_same_tree_as_a_plain_recursion():
    texts = [_norm(t) for t in TEXTS] * 2
    depth, split = 4, 2
    plain = PlainTree(texts, depth)
    keys, n = context_tree.counted(context_tree.windows(texts, depth)[0])
    whole = context_tree.lower_levels(keys, n, depth)[0]
    low, sums = {}, defaultdict(list)
    for part in range(3):  # subtrees apart, parents from their sums
        own = (keys >> np.uint64(8) & np.uint64((1 << 8 * split) - 1)) % np.uint64(3) == part
        levels, up = context_tree.lower_levels(keys[own], n[own], depth, split)
        for k, v in levels.items():
            low[k] = v if k not in low else tuple(np.concatenate(x) for x in zip(low[k], v))
        for j, s in up.items():
            sums[j].append(s)
    order = lambda xs: tuple(x[np.argsort(xs[0], kind="stable")] for x in xs)
    added = {j: context_tree._summed(*(np.concatenate(x) for x in zip(*s))) for j, s in sums.items()}
    split_up = {k: order(v) for k, v in low.items()} | context_tree.upper_levels(added, split)
    for t in (b"the cat sat on the mat", b"", b"the dog", b"\xff\xfe unseen"):
        own = context_tree.windows([t], depth)[0]
        want = plain.log10(t)
        assert context_tree.log10_chances(whole, depth, own).sum() == pytest.approx(want, abs=1e-9)
        assert context_tree.log10_chances(split_up, depth, own).sum() == pytest.approx(want, abs=1e-9)


def test_chances_of_all_bytes_add_up_to_one():
    keys, n = context_tree.counted(context_tree.windows([b"abracadabra" * 20, b""], 3)[0])
    levels = context_tree.lower_levels(keys, n, 3)[0]
    for ctx in (keys[0] & ~np.uint64(255), np.uint64(0x7A7A7A00)):
        every = np.array([ctx | np.uint64(v) for v in range(256)], np.uint64)
        assert (10 ** context_tree.log10_chances(levels, 3, every)).sum() == pytest.approx(1)
    assert context_tree.log_kt(np.array([1]), np.array([1]))[0] == pytest.approx(math.log(1 / 8))
    big = np.array([5000]), np.array([3])
    assert context_tree.log_kt(*big)[0] == pytest.approx(math.lgamma(5000.5) + math.lgamma(3.5) - 2 * math.lgamma(0.5) - math.lgamma(5004))


def test_packing_is_exact():
    rng = np.random.default_rng(0)
    keys = np.unique(rng.integers(0, 1 << 63, 1000).astype(np.uint64))
    assert (lm_score.unpack_sorted(lm_score.pack_sorted(keys)) == keys).all()
    assert lm_score.unpack(lm_score.pack(np.arange(5)), np.int64).tolist() == list(range(5))
    assert len(lm_score.unpack_sorted(lm_score.pack_sorted(np.empty(0, np.uint64)))) == 0


@pytest.mark.parametrize("block", [1 << 25, 20])
def test_scores_of_all_rows_against_plain_versions(spark, monkeypatch, block):
    monkeypatch.setattr(lm_score, "BLOCK_BYTES", block)
    monkeypatch.setattr(lm_score, "PIECE_BYTES", 30)
    rows = [(i, t, "x") for i, t in enumerate(TEXTS * 2)] + [(None, "no id here", "x"), (3, "", "x")]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, score string").repartition(3)
    got = lm_score.score_texts(docs, depth=4).collect()
    out = lambda d: d is not None and zlib.crc32(str(d).encode()) % 5 == 1
    learn = [_norm(t) for d, t, _ in rows if not out(d)]
    tree = PlainTree(learn, 4)
    count = Counter(w for t in learn for w in [*t.split(), None])
    total, kinds = sum(count.values()), len(count)
    want = []
    for d, t, _ in rows:
        words = [*_norm(t).split(), None]
        base = sum(math.log10((count[w] + 0.5) / (total + 0.5 * (kinds + 1))) for w in words)
        want.append((d if d is not None else -1, out(d), len(words), sum(count[w] > 0 for w in words), total, round(base, 6), round(tree.log10(_norm(t)), 3)))
    mine = [(r["doc_id"] if r["doc_id"] is not None else -1, r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"], round(r["base_score"], 6), round(r["score"], 3)) for r in got]
    key = lambda x: x[:-1]
    assert [x[:-1] for x in sorted(mine, key=key)] == [x[:-1] for x in sorted(want, key=key)]
    assert [x[-1] for x in sorted(mine)] == pytest.approx([x[-1] for x in sorted(want)], abs=2e-3)
    for r in got:
        assert r["bits_per_byte"] == pytest.approx(-r["score"] * math.log2(10) / r["n_bytes"])


def test_no_training_rows_and_no_rows(spark):
    docs = spark.createDataFrame([(1, "ab")], "doc_id bigint, text string")
    only = lm_score.score_texts(docs, out=F.lit(True)).first()
    assert only["bits_per_byte"] == pytest.approx(8) and only["train_tokens"] == 0 and only["n_known"] == 0
    assert lm_score.score_texts(docs.limit(0)).count() == 0


def test_long_unbroken_text(spark):
    docs = spark.createDataFrame([(2, "ab" * 400_000), (4, "c")], "doc_id bigint, text string")
    got = {r["doc_id"]: r for r in lm_score.score_texts(docs).collect()}
    assert got[2]["n_bytes"] == 800_001 and got[2]["bits_per_byte"] < 0.01 and got[2]["n_tokens"] == 2
