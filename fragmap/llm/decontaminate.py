"""Benchmark decontamination: BM25 over test items, searched with block-max WAND.

Test items form an inverted index; every passage of every training document is a
query. Scores are BM25 sums divided by the item's score against itself, so one
threshold serves items of all lengths: 1 means that all of an item's words occur.
A passage whose words' largest possible scores sum to less than the threshold can
have no pivot and is left. Block maxima of all blocks are then summed at once; only
blocks that can reach the threshold are entered, where cursors move from pivot to pivot
and score exactly what remains. What is retrieved must then
share word shingles with the item's question and with its answer.

Passages are runs of twice the longest item, starting every such length, so each item
lies whole in one. An index holds about ``INDEX_CHARS`` characters of items; a larger
benchmark is searched in several such parts, one after the other. Document frequencies,
mean length and passage length are those of the whole benchmark in every part, so the
parts give the scores that one index would give.

Defined cases: null or empty texts and items match nothing; items of no word are not
indexed; an item's answer is what follows its last question mark, else its last
sentence, else its last quarter; repeated rows each get their rows; repeated items are
items of their own; empty tables give an empty result; other columns pass through.
"""

from __future__ import annotations

import math
import re
from collections import Counter, defaultdict
from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fragmap.llm import common

THRESHOLD = 0.5
SHINGLE = 5
QUESTION_OVERLAP = 0.5
ANSWER_OVERLAP = 0.5
K1, B = 1.2, 0.75
BLOCK = 4
INDEX_CHARS = 16_000_000
_WORD = re.compile(r"[^\W_]+")


def words_of(text: str | None) -> list[str]:
    return _WORD.findall((text or "").lower())


def question_and_answer(text: str) -> tuple[list[str], list[str]]:
    cut = text.rfind("?") + 1
    if not 0 < cut < len(text.rstrip()):
        body = text.rstrip().rstrip(".!?")
        cut = max(body.rfind(c) for c in ".!?\n") + 1
    question, answer = words_of(text[:cut]), words_of(text[cut:])
    if not question or not answer:
        every = question or answer
        tail = max(1, len(every) // 4)
        question, answer = every, every[-tail:]
    return question, answer


def shingles(words: list[str], n: int = SHINGLE) -> set[tuple[str, ...]]:
    n = min(n, len(words))
    return {tuple(words[i : i + n]) for i in range(len(words) - n + 1)} if n else set()


@dataclass
class Statistics:
    """What scores take from all items that hold a word: their number, words and longest, and the items of each word."""

    items: int
    words: int
    longest: int
    df: dict[str, int]


class ItemIndex:
    """Inverted index with term maxima and block maxima; postings are in order of item number.

    ``stats`` are those of the whole benchmark where ``items`` is a part of it.
    """

    def __init__(self, items: list[tuple[object, str]], block: int = BLOCK, stats: Statistics | None = None):
        rows = [(i, words_of(t), t) for i, t in items]
        rows = [r for r in rows if r[1]]
        self.ids = [r[0] for r in rows]
        self.parts = [tuple((shingles(p), min(SHINGLE, len(p))) for p in question_and_answer(r[2])) for r in rows]
        counts = [Counter(r[1]) for r in rows]
        own = Counter(w for c in counts for w in c)
        if stats is None:
            sizes = [len(r[1]) for r in rows]
            stats = Statistics(len(rows), sum(sizes), max(sizes, default=1), own)
        self.longest = stats.longest
        mean = stats.words / max(stats.items, 1)
        idf = {w: math.log(1 + (stats.items - stats.df[w] + 0.5) / (stats.df[w] + 0.5)) for w in own}
        self.terms = {w: i for i, w in enumerate(own)}
        postings = defaultdict(list)
        for item, (c, r) in enumerate(zip(counts, rows)):
            norm = K1 * (1 - B + B * len(r[1]) / mean)
            score = {w: idf[w] * n * (K1 + 1) / (n + norm) for w, n in c.items()}
            total = sum(score.values())
            for w, s in score.items():
                postings[self.terms[w]].append((item, s / total))
        self.block = block
        #: by term: block -> postings of that block
        self.postings = [defaultdict(list) for _ in self.terms]
        for t in range(len(self.terms)):
            for item, s in postings[t]:
                self.postings[t][item // block].append((item, s))
        self.most = np.array([max(s for _, s in postings[t]) for t in range(len(self.terms))] + [0.0])  # the last is for unknown words
        sizes = [len(blocks) for blocks in self.postings]
        self.block_from = np.concatenate([[0], np.cumsum(sizes, dtype=np.int64)]).astype(np.int64)
        self.block_at = np.array([k for blocks in self.postings for k in blocks], np.int64)
        self.block_value = np.array([max(s for _, s in p) for blocks in self.postings for p in blocks.values()])

    def reachable(self, terms: np.ndarray, threshold: float) -> np.ndarray:
        """Blocks in which the block maxima of ``terms`` reach the threshold."""
        first, size = self.block_from[terms], self.block_from[terms + 1] - self.block_from[terms]
        before = np.cumsum(size) - size
        at = np.arange(int(size.sum())) + np.repeat(first - before, size)
        return np.flatnonzero(np.bincount(self.block_at[at], self.block_value[at]) >= threshold - 1e-9)

    def retrieve(self, terms: np.ndarray, threshold: float) -> list[tuple[int, float]]:
        """All (item, score) at or above ``threshold`` for a set of terms."""
        if self.most[terms].sum() < threshold - 1e-9:
            return []
        found = []
        for block in self.reachable(terms, threshold).tolist():
            lists = [self.postings[t][block] for t in terms.tolist() if block in self.postings[t]]
            found += _wand(lists, threshold - 1e-9)
        return found

    def leaks(self, text: str | None, threshold: float = THRESHOLD) -> list[tuple[object, float, float, float]]:
        """(item id, score, question overlap, answer overlap) of verified items, best passage of each."""
        words = words_of(text)
        if not words or not self.ids:
            return []
        unknown = len(self.terms)
        get = self.terms.get
        ids = np.array([get(w, unknown) for w in words], np.int64)
        step, width = self.longest, 2 * self.longest
        reach = np.concatenate([[0.0], np.cumsum(self.most[ids])])
        starts = np.arange(0, max(len(ids) - step, 1), step)
        ends = np.minimum(starts + width, len(ids))
        best: dict[int, tuple[float, float, float]] = {}
        for a, b in zip(starts, ends):
            if reach[b] - reach[a] < threshold - 1e-9:
                continue
            terms = np.unique(ids[a:b])
            terms = terms[terms < unknown]
            for item, score in self.retrieve(terms, threshold):
                here = words[max(0, a - step) : b + step]
                q, r = (len(s & shingles(here, n)) / len(s) for s, n in self.parts[item])
                if q >= QUESTION_OVERLAP and r >= ANSWER_OVERLAP:
                    best[item] = max(best.get(item, (0.0, 0.0, 0.0)), (score, q, r))
        return [(self.ids[i], *v) for i, v in sorted(best.items())]


def _wand(lists: list[list[tuple[int, float]]], threshold: float) -> list[tuple[int, float]]:
    """Items of one block whose scores reach the threshold; cursors move from pivot to pivot."""
    cursors = [[p[0][0], 0, max(s for _, s in p), p] for p in lists]
    found = []
    while cursors:
        cursors.sort(key=lambda c: c[0])
        bound, pivot = 0.0, None
        for item, _, most, _ in cursors:
            bound += most
            if bound >= threshold:
                pivot = item
                break
        if pivot is None:
            break
        if cursors[0][0] == pivot:
            score = sum(p[at][1] for item, at, _, p in cursors if item == pivot)
            if score >= threshold:
                found.append((pivot, score))
            pivot += 1
        moved = []
        for item, at, most, p in cursors:
            while at < len(p) and p[at][0] < pivot:
                at += 1
            if at < len(p):
                moved.append([p[at][0], at, most, p])
        cursors = moved
    return found


def _worded(items: DataFrame, part: Column) -> DataFrame:
    """(part, size, words) of every item that holds a word; ``words`` are its distinct ones."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            words = [words_of(t.as_py()) for t in batch.column("t")]
            yield pa.RecordBatch.from_arrays(
                [batch.column("part"), pa.array([len(w) for w in words], pa.int64()), pa.array([sorted(set(w)) for w in words], pa.list_(pa.string()))],
                ["part", "size", "words"],
            )

    return items.select(part.cast("int").alias("part"), "t").mapInArrow(run, "part int, size bigint, words array<string>").where("size > 0")


def each_index(benchmark: DataFrame, id_col: str = "item_id", text_col: str = "text", index_chars: int = INDEX_CHARS) -> Iterator[ItemIndex]:
    """Indexes over parts of the items, each of about ``index_chars`` characters; one is on the driver at a time.

    Of the word counts of all items only those of a part's words reach the driver.
    """
    items = benchmark.select(F.col(id_col).alias("i"), F.coalesce(F.col(text_col), F.lit("")).alias("t"))
    chars = items.agg(F.sum(F.length("t"))).first()[0] or 0
    parts = math.ceil(chars / index_chars) or 1
    part = F.pmod(F.xxhash64("i", "t"), F.lit(parts))
    if parts == 1:  # its own statistics are those of the whole
        yield ItemIndex([(r["i"], r["t"]) for r in items.orderBy("i", "t").collect()])
        return
    worded = common.checkpoint(_worded(items, part))
    n, words, longest = worded.agg(F.count("*"), F.sum("size"), F.max("size")).first()
    if not n:
        return
    each = worded.select("part", F.explode("words").alias("word"))
    df = common.checkpoint(each.groupBy("word").agg(F.count("*").alias("n")))
    for k in range(parts):
        mine = df.join(each.where(F.col("part") == k).select("word").distinct(), "word", "left_semi")
        stats = Statistics(n, words, longest, {r["word"]: r["n"] for r in mine.collect()})
        yield ItemIndex([(r["i"], r["t"]) for r in items.where(part == k).orderBy("i", "t").collect()], stats=stats)


def item_indexes(benchmark: DataFrame, id_col: str = "item_id", text_col: str = "text", index_chars: int = INDEX_CHARS) -> list[ItemIndex]:
    """``each_index`` as a list."""
    return list(each_index(benchmark, id_col, text_col, index_chars))


def find_leaks(docs: DataFrame, index: ItemIndex, keep: list[str], text_col: str = "text", item_type: str = "bigint") -> DataFrame:
    """``keep`` columns, item_id, score, question_overlap, answer_overlap: a row per document and leaked item."""
    shared = docs.sparkSession.sparkContext.broadcast(index)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        for batch in batches:
            rows = [(i, *leak) for i, t in enumerate(batch.column("_dc_text")) for leak in own.leaks(t.as_py())]
            cols = list(zip(*rows)) or [(), (), (), (), ()]
            at = pa.array(cols[0], pa.int64())
            kinds = [pa.string() if item_type == "string" else pa.int64(), *[pa.float64()] * 3]
            yield pa.RecordBatch.from_arrays(
                [*[batch.column(c).take(at) for c in keep], *[pa.array(c, k) for c, k in zip(cols[1:], kinds)]],
                [*keep, "item_id", "score", "question_overlap", "answer_overlap"],
            )

    kinds = [f"`{n}` {k}" for n, k in docs.select(*keep).dtypes]
    schema = ", ".join([*kinds, f"item_id {item_type}, score double, question_overlap double, answer_overlap double"])
    return docs.select(*keep, F.col(text_col).alias("_dc_text")).mapInArrow(run, schema)


def drop_leaking(docs: DataFrame, benchmark: DataFrame, text_col: str = "text", index_chars: int = INDEX_CHARS) -> DataFrame:
    """The rows of ``docs`` that hold no test item, same columns.

    Between the parts of a large benchmark rows are stored, so a worker holds one index.
    """
    spark, names = docs.sparkSession, docs.columns
    at, last = names.index(text_col), None
    for k, index in enumerate(each_index(benchmark, index_chars=index_chars)):
        if k:
            docs = common.stored(docs, "leak-free")
            if last is not None:
                common.discard(last)
            last = docs
        shared = spark.sparkContext.broadcast(index)

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            own = shared.value
            for batch in common.sliced("decontamination", batches):
                yield batch.filter(pa.array([not own.leaks(t.as_py()) for t in batch.column(at)], pa.bool_()))

        docs = docs.mapInArrow(run, docs.schema)
    return docs


def op7_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents").select("doc_id", "text")
    found = [find_leaks(docs, index, ["doc_id"]) for index in each_index(common.table(spark, sf_dir, "benchmark"))]
    return reduce(DataFrame.unionByName, found) if found else find_leaks(docs, ItemIndex([]), ["doc_id"])
