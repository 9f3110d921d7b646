"""The corpus pipeline: five stages from ``documents`` to encoded, clean, distinct texts.

Each stage takes (spark, docs, sf_dir), reads every row its predecessor kept and is
written as Parquet before the next one reads it. All stages but the last return the
columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fragmap.llm import common, decontaminate, line_dedup, pieces, simhash, toxicity

#: Words of a shingle in the near-duplicate stage.
SHINGLE = 5


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    model = toxicity.fit(*toxicity.training_rows(docs, common.table(spark, sf_dir, "labels")))
    common.release()
    scored = toxicity.score_toxicity(docs, model)
    return scored.where(F.col("tox_score") < toxicity.THRESHOLD).select(*scored.columns[: len(docs.columns)]).toDF(*docs.columns)


def drop_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without their repeated lines; a document whose every line went goes too."""
    kept = line_dedup.dedup_lines(docs).where("n_dropped < n_lines")
    text = F.when(F.col("n_dropped") > 0, F.col("kept_text")).otherwise(F.col("text"))
    return kept.select(*[
        text.alias(c) if c == "text" else F.when(F.col("n_dropped") > 0, F.length("kept_text").cast("bigint")).otherwise(F.col(c)).alias(c) if c == "n_chars" else F.col(c)
        for c in kept.columns[: len(docs.columns)]
    ]).toDF(*docs.columns)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The least doc_id of each group stays: SimHash links of the Gray index, verified, then pairs beyond its radius; similarity of 0.8 or more over shingles of five words."""
    return simhash.drop_near_duplicates(docs, shingle=SHINGLE)


def drop_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.drop_leaking(docs, common.table(spark, sf_dir, "benchmark"))


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pieces.encode_documents(docs, ids=True)


STAGES = [
    ("toxicity", drop_toxic),
    ("line_dedup", drop_lines),
    ("simhash", drop_near_copies),
    ("decontamination", drop_benchmark),
    ("pieces", encode),
]

#: Trained scores, fingerprints and merges have no SQL form; tests hold run() against a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = common.stored(stage(spark, docs, sf_dir), f"stage-{name}")
    return common.stored(STAGES[-1][1](spark, docs, sf_dir), f"stage-{STAGES[-1][0]}")
