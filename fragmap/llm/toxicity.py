"""Toxicity by multiple-instance learning with noisy-or.

Only documents carry labels. A document's probability is one minus the product of
its sentences' complements, each sentence a logistic score over hashed words and word
beginnings; training moves the sentence scores through that product, so sentences are
found without sentence labels. The model is fitted on at most ``SAMPLE`` labelled rows
(those of least id hash, as far as ``SAMPLE_CHARS`` characters in all), a fixed number of weights; all rows are scored whole. Word weights are at least 0, with a
linear penalty that empties most of them; the bias alone speaks against.

Defined cases: a null or empty text has one empty sentence, which scores the model's
bias; a null id is outside the held-out part; ids labelled more than once count once,
toxic if any row says so; null labels teach nothing; without labels of both kinds the
model is its prior; repeated rows get equal scores; an empty table gives an empty result.
"""

from __future__ import annotations

import re
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from fragmap.llm import common

SAMPLE = 6000
SAMPLE_CHARS = 32_000_000
N_WEIGHTS = 1 << 18
ROUNDS = 140
RATE = 0.15
DECAY = 2e-4
MIN_SEEN = 4
PREFIXES = (4, 6)
CACHE = 1 << 18
THRESHOLD = 0.5
FOLDS = 5
HELD_OUT = 0
_TOKEN = re.compile(r"[^\W\d_]+|[.!?\n]+")
_END = re.compile(r"[.!?\n]")


def held_out(id_col: str, remainder: int = HELD_OUT) -> Column:
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % FOLDS == remainder, F.lit(False))


def word_features(word: str) -> list[int]:
    names = ["=" + word, *["^" + word[:n] for n in PREFIXES if len(word) >= n]]
    return [zlib.crc32(n.encode("utf-8", "surrogatepass")) & (N_WEIGHTS - 1) for n in names]


def _tokens(text: str | None) -> list[str]:
    return _TOKEN.findall((text or "").lower())


def _softplus(z: np.ndarray) -> np.ndarray:
    return np.logaddexp(0, z)


def fit(texts: list[str | None], labels: list[int]) -> tuple[np.ndarray, float]:
    """Weights and bias; full-batch Adam on the noisy-or likelihood, words first pooled to distinct words."""
    weights, bias = np.zeros(N_WEIGHTS, np.float64), -3.0
    y = np.asarray(labels, np.float64)
    if not len(y) or y.min() == y.max():
        return weights.astype(np.float32), bias if not len(y) or y.max() == 0 else -bias
    number: dict[str, int] = {}
    word_at, sent_at, doc_of = array("i"), array("i"), array("i")  # 4 bytes an entry, where lists of numbers take 40
    for d, text in enumerate(texts):
        doc_of.append(d)
        for token in _tokens(text):
            if _END.match(token):
                doc_of.append(d)
            else:
                word_at.append(number.setdefault(token, len(number)))
                sent_at.append(len(doc_of) - 1)
    word_at, sent_at, doc_of = (np.frombuffer(x, np.int32) if len(x) else np.empty(0, np.int32) for x in (word_at, sent_at, doc_of))
    docs_with = np.unique(word_at.astype(np.int64) * len(y) + doc_of[sent_at]) // len(y)
    seen = np.bincount(docs_with, minlength=len(number))
    pairs = [(w, f) for word, w in number.items() for f in word_features(word)]
    pair_word, pair_feature = (np.asarray(x, np.int64) for x in (zip(*pairs) if pairs else ((), ())))
    support = np.bincount(pair_feature, weights=seen[pair_word], minlength=N_WEIGHTS)
    used = support[pair_feature] >= MIN_SEEN
    pair_word, pair_feature = pair_word[used], pair_feature[used]
    active = np.unique(pair_feature)
    slot = np.searchsorted(active, pair_feature)
    theta = np.zeros(len(active) + 1)
    theta[-1] = bias
    first, second = np.zeros_like(theta), np.zeros_like(theta)
    for step in range(1, ROUNDS + 1):
        value = np.bincount(pair_word, theta[:-1][slot], len(number))
        z = np.bincount(sent_at, value[word_at], len(doc_of)) + theta[-1]
        none = np.bincount(doc_of, _softplus(z), len(y))  # -log of the chance that no sentence is toxic
        pull = np.where(y == 1, -1.0 / np.expm1(np.clip(none, 1e-6, 50)), 1.0)
        dz = pull[doc_of] * np.exp(-_softplus(-z))
        dword = np.bincount(word_at, dz[sent_at], len(number))
        grad = np.append(np.bincount(slot, dword[pair_word], len(active)), dz.sum()) / len(y)
        grad[:-1] += DECAY
        first, second = 0.9 * first + 0.1 * grad, 0.999 * second + 0.001 * grad**2
        theta -= RATE * (first / (1 - 0.9**step)) / (np.sqrt(second / (1 - 0.999**step)) + 1e-8)
        np.maximum(theta[:-1], 0, out=theta[:-1])  # words only speak for toxicity, so long sentences can't outweigh one
    weights[active] = theta[:-1]
    return weights.astype(np.float32), float(theta[-1])


class _WordValues(dict):
    def __init__(self, weights: np.ndarray):
        super().__init__()
        self.weights = weights

    def __missing__(self, word: str) -> float:
        if len(self) >= CACHE:
            self.clear()
        value = np.nan if _END.match(word) else float(self.weights[word_features(word)].sum())
        self[word] = value
        return value


def sentence_scores(text: str | None, values: _WordValues, bias: float) -> np.ndarray:
    """Log-odds of every sentence (runs of end marks separate them)."""
    v = np.array(list(map(values.__getitem__, _tokens(text))), np.float64)
    ends = np.isnan(v)
    at = np.cumsum(ends)
    return np.bincount(at[~ends], v[~ends], (int(at[-1]) if len(at) else 0) + 1) + bias


def noisy_or(z: np.ndarray) -> float:
    return float(-np.expm1(-_softplus(z).sum()))


def sentence_span(text: str | None, number: int) -> tuple[int, int]:
    """Code points of the sentence with that number."""
    start = 0
    for i, mark in enumerate(re.finditer(r"[.!?\n]+", text or "")):
        if i == number:
            return start, mark.end()
        start = mark.end()
    return start, len(text or "")


def training_rows(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, remainder: int = HELD_OUT, chars: int = SAMPLE_CHARS) -> tuple[list, list]:
    """At most ``sample`` (text, label) rows outside the held-out part, those of least id hash, until their texts pass ``chars`` in all."""
    known = labels.where(F.col("toxic").isNotNull() & ~held_out("doc_id", remainder)).groupBy("doc_id").agg(F.max("toxic").alias("y"))
    known = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)
    rows = docs.select("doc_id", "text").join(F.broadcast(known), "doc_id").groupBy("doc_id").agg((F.max("y") > 0).cast("int").alias("y"), F.max("text").alias("text"))
    upto = Window.orderBy(F.xxhash64("doc_id"), "doc_id").rowsBetween(Window.unboundedPreceding, -1)  # over at most ``sample`` rows
    rows = rows.withColumn("before", F.coalesce(F.sum(F.coalesce(F.length("text"), F.lit(0))).over(upto), F.lit(0)))
    table = rows.where(F.col("before") < chars).select("text", "y").toArrow()
    return table["text"].to_pylist(), table["y"].to_pylist()


def score_toxicity(docs: DataFrame, model: tuple[np.ndarray, float], text_col: str = "text") -> DataFrame:
    """All columns of ``docs`` and ``tox_score``, ``tox_sentence`` (number), ``tox_start``, ``tox_end`` of the worst sentence.

    Input columns of these names are returned as ``input_<name>``.
    """
    weights, bias = model
    added = ["tox_score", "tox_sentence", "tox_start", "tox_end"]
    docs = common.set_aside(docs, added)
    shared = docs.sparkSession.sparkContext.broadcast(weights)  # N_WEIGHTS floats
    names = docs.columns
    at = names.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        values = _WordValues(shared.value)
        for batch in common.sliced("toxicity", batches):
            out = []
            for text in batch.column(at):
                text = text.as_py()
                z = sentence_scores(text, values, bias)
                worst = int(z.argmax())
                out.append((noisy_or(z), worst, *sentence_span(text, worst)))
            cols = list(zip(*out)) or [(), (), (), ()]
            more = [pa.array(cols[0], pa.float64()), *[pa.array(c, pa.int32()) for c in cols[1:]]]
            yield pa.RecordBatch.from_arrays([*batch.columns, *more], [*names, *added])

    kinds = [f"`{n}` {k}" for n, k in docs.dtypes]
    return docs.mapInArrow(run, ", ".join([*kinds, "tox_score double, tox_sentence int, tox_start int, tox_end int"]))


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents").select("doc_id", "text")
    model = fit(*training_rows(docs, common.table(spark, sf_dir, "labels")))
    return score_toxicity(docs, model).select(
        "doc_id", held_out("doc_id").alias("held_out"), F.col("tox_score").alias("score"),
        (F.col("tox_score") >= THRESHOLD).cast("int").alias("predicted"), "tox_sentence", "tox_start", "tox_end",
    )
