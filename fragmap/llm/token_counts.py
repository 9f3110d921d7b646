"""Exact token-length histograms and what their suffix sums answer.

Documents are encoded whole; only (length, number of documents) survives the first
aggregation. With n(l) documents of length l, the sums of n and of l * n over longer
lengths give, for every context limit c, the documents cut at c and the tokens left
when each document is truncated to c; totals and quantiles come from the same row.

Defined cases: a null or empty text has no token; repeated rows count each time; an
empty table gives an empty histogram; special-token strings in a text are ordinary text.
"""

from __future__ import annotations

import base64
from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from fragmap.llm import common

VOCABULARY = "byte_bpe_50k.tiktoken"
QUANTILES = (0.5, 0.9, 0.99)
BLOCK = 256


@lru_cache(maxsize=4)
def encoder(vocabulary: str):
    """A byte-level BPE of a public vocabulary file, given by name or path."""
    import public_tokenizers
    import tiktoken

    path = vocabulary if "/" in vocabulary else public_tokenizers.path(vocabulary)
    with open(path, "rb") as lines:
        ranks = {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, lines)}
    return tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


def token_lengths(docs: DataFrame, text_col: str = "text", vocabulary: str = VOCABULARY, keep: tuple[str, ...] = ()) -> DataFrame:
    """``keep`` columns and ``n_tokens`` of every document."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(vocabulary).encode_ordinary
        for batch in batches:
            texts = pc.fill_null(batch.column("_tc_text"), "").to_pylist()
            lengths = pa.array([len(encode(t)) for t in texts], pa.int64())
            yield pa.record_batch([*[batch.column(c) for c in keep], lengths], [*keep, "n_tokens"])

    taken = docs.select(*keep, F.col(text_col).alias("_tc_text"))
    kinds = [f"`{name}` {kind}" for name, kind in docs.select(*keep).dtypes]
    return taken.mapInArrow(count, ", ".join([*kinds, "n_tokens bigint"]))


def length_histogram(lengths: DataFrame) -> DataFrame:
    """One row per length with counts, prefix and suffix sums; sums run inside blocks of lengths and are then shifted.

    Counts are read twice, so they are cut from the plan that encodes.
    """
    counts = common.checkpoint(lengths.groupBy("n_tokens").agg(F.count("*").alias("n_docs")))
    counts = counts.withColumn("block", F.floor(F.col("n_tokens") / BLOCK))
    tokens = F.col("n_tokens") * F.col("n_docs")
    inside = Window.partitionBy("block").orderBy(F.desc("n_tokens")).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    local = counts.select("*", F.sum("n_docs").over(inside).alias("docs_in"), F.sum(tokens).over(inside).alias("tokens_in"))
    blocks = counts.groupBy("block").agg(F.sum("n_docs").alias("d"), F.sum(tokens).alias("t"))
    above = Window.orderBy(F.desc("block")).rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    starts = blocks.select(
        "block",
        F.coalesce(F.sum("d").over(above), F.lit(0)).alias("docs_over"), F.coalesce(F.sum("t").over(above), F.lit(0)).alias("tokens_over"),
        F.sum("d").over(whole).alias("total_docs"), F.sum("t").over(whole).alias("total_tokens"),
    )
    docs_ge, tokens_ge = F.col("docs_in") + F.col("docs_over"), F.col("tokens_in") + F.col("tokens_over")
    return local.join(starts, "block").select(
        "n_tokens", "n_docs", docs_ge.alias("docs_at_least"), tokens_ge.alias("tokens_at_least"),
        (F.col("total_tokens") - tokens_ge + F.col("n_tokens") * docs_ge).alias("truncated_tokens"),
        "total_docs", "total_tokens",
    )


def limits_report(histogram: DataFrame, limits: DataFrame) -> DataFrame:
    """For every row of ``limits`` (context_limit): documents cut and tokens left, exact for limits that are no length too."""
    longer = F.col("n_tokens") > F.col("context_limit")
    return (
        limits.join(F.broadcast(histogram), F.lit(True), "left").groupBy("context_limit")
        .agg(
            F.coalesce(F.sum(F.when(longer, F.col("n_docs"))), F.lit(0)).alias("docs_cut"),
            F.coalesce(F.sum(F.least("n_tokens", "context_limit") * F.col("n_docs")), F.lit(0)).alias("tokens_left"),
        )
    )


def quantile_report(histogram: DataFrame, quantiles: tuple[float, ...] = QUANTILES) -> DataFrame:
    """Smallest length that at least the given share of documents does not exceed."""
    at_most = F.col("total_docs") - F.col("docs_at_least") + F.col("n_docs")
    asked = F.explode(F.array(*[F.lit(float(q)) for q in quantiles])).alias("quantile")
    return (
        histogram.select("n_tokens", at_most.alias("at_most"), "total_docs", asked)
        .where(F.col("at_most") >= F.col("quantile") * F.col("total_docs"))
        .groupBy("quantile").agg(F.min("n_tokens").alias("n_tokens"))
    )


def op3_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return length_histogram(token_lengths(common.table(spark, sf_dir, "documents")))
