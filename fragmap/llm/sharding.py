"""Sharding by jump consistent hashing.

A shard is a function of the key's 64-bit hash and the number of shards alone,
so there is no ring table, and a further shard takes rows only into itself, about
1 in (n + 1) of them. The numbering inside a shard is done per (shard, bucket of
the hash): bucket sizes are summed first and their running totals are joined back,
so no task ever holds a whole shard.

Defined cases: a null key hashes like any other value; repeated rows share a shard
and get slots of their own; a null text has size 8 and the CRC of no bytes; an empty
table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType

from fragmap.llm import common

N_SHARDS = 24
N_BUCKETS = 1024
#: Fixed value: multiplier of the published generator.
_STEP = np.uint64(2862933555777941757)


def jump_buckets(keys: np.ndarray, n: int) -> np.ndarray:
    """Shard of every unsigned 64-bit key; all keys advance together until each has left [0, n)."""
    state = keys.astype(np.uint64).copy()
    at, ahead = np.full(len(state), -1, np.int64), np.zeros(len(state), np.int64)
    live = np.arange(len(state))
    with np.errstate(over="ignore"):
        while len(live):
            at[live] = ahead[live]
            state[live] = state[live] * _STEP + np.uint64(1)
            draw = (state[live] >> np.uint64(33)).astype(np.float64) + 1.0
            ahead[live] = ((at[live] + 1) * (float(1 << 31) / draw)).astype(np.int64)
            live = live[ahead[live] < n]
    return at.astype(np.int32)


def shard_of(key_hash: Column, n: int) -> Column:
    if n < 1:
        raise ValueError("at least one shard is needed")

    @F.pandas_udf(IntegerType())
    def shard(h: pd.Series) -> pd.Series:
        return pd.Series(jump_buckets(h.to_numpy(np.int64).view(np.uint64), n))

    return shard(key_hash)


def with_slots(rows: DataFrame, shard_col: str, order: list[str], n_buckets: int = N_BUCKETS) -> DataFrame:
    """Adds ``slot``, 0 to n - 1 inside each shard, without a task per shard."""
    dealt = rows.withColumn("_sh_bucket", F.pmod(F.xxhash64(*order), F.lit(n_buckets)).cast("int"))
    before = Window.partitionBy(shard_col).orderBy("_sh_bucket").rowsBetween(Window.unboundedPreceding, -1)
    starts = (
        dealt.groupBy(shard_col, "_sh_bucket").agg(F.count("*").alias("_sh_n"))
        .select(shard_col, "_sh_bucket", F.coalesce(F.sum("_sh_n").over(before), F.lit(0)).alias("_sh_start"))
    )
    inside = Window.partitionBy(shard_col, "_sh_bucket").orderBy(*order)
    return (
        dealt.withColumn("_sh_row", F.row_number().over(inside)).join(starts, [shard_col, "_sh_bucket"])
        .withColumn("slot", F.col("_sh_start") + F.col("_sh_row") - 1)
        .drop("_sh_bucket", "_sh_row", "_sh_start")
    )


def shard_documents(docs: DataFrame, n_shards: int = N_SHARDS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, size, text_crc32, shard, grown_shard, slot) of every row; texts never move."""
    data = F.coalesce(F.col(text_col), F.lit(""))
    rows = docs.select(
        F.col(id_col).alias("doc_id"),
        (F.octet_length(data).cast("bigint") + 8).alias("size"),
        F.crc32(data.cast("binary")).alias("text_crc32"),
    )
    key = F.xxhash64("doc_id")
    rows = rows.withColumns({"shard": shard_of(key, n_shards), "grown_shard": shard_of(key, n_shards + 1)})
    return with_slots(rows, "shard", ["doc_id", "size", "text_crc32"])


def write_shards(docs: DataFrame, path: str, n_shards: int = N_SHARDS, id_col: str = "doc_id", files_per_shard: int = 1) -> None:
    """Writes whole rows as ``path/shard=k``; with ``files_per_shard`` over 1 a shard's rows are dealt to several tasks."""
    placed = docs.withColumn("shard", shard_of(F.xxhash64(id_col), n_shards))
    part = F.pmod(F.xxhash64(*[c for c in (id_col,)], F.lit(1)), F.lit(files_per_shard))
    placed.repartition(n_shards * files_per_shard, "shard", part).write.partitionBy("shard").parquet(path)


def op6_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents").select("doc_id", "text")
    return shard_documents(docs).select(
        "doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", "slot", "grown_shard"
    )
