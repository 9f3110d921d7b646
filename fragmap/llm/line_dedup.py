"""Line dedup over levelled sorted runs of line hashes. DataFrame functions only.

A run is a Parquet table sorted by key with one row per line key: the number of
documents holding it and the largest such ``doc_id`` (the keeper). A batch is
anti-joined with the runs, which tells new keys from known ones, and is added as
a run of level 0. ``FANOUT`` runs of a level are merged into one of the next
level, so a key is rewritten once per level, never once per batch.

Defined cases: a null or empty text is one empty line, which is too short to be
dropped; a null ``doc_id`` sorts below every other id; repeated rows of one
``doc_id`` count as one document and get the same result; an empty table gives an
empty result; other columns pass through, those named as an added one as ``input_<name>``.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fragmap.llm import common

MIN_CHARS = 20
MIN_DOCS = 3
N_BATCHES = 4
FANOUT = 4
_LOWEST = -(2**63)


def lines_of(text: Column) -> Column:
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


def line_keys(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = MIN_CHARS) -> DataFrame:
    """(doc, text_id, pos, key) of every line long enough to count.

    The key is a 128-bit digest of the line without white space at its ends and
    with A-Z lower-cased.
    """
    line = F.btrim(F.col("line"), F.lit(common.SPACES))
    return (
        docs.select(
            F.coalesce(F.col(id_col).cast("bigint"), F.lit(_LOWEST)).alias("doc"),
            F.xxhash64(text_col).alias("text_id"),
            F.posexplode(lines_of(F.col(text_col))).alias("pos", "line"),
        )
        .select("doc", "text_id", "pos", line.alias("line"))
        .where(F.length("line") >= min_chars)
        .select("doc", "text_id", "pos", F.unhex(F.md5(common.ascii_lower(F.col("line")))).alias("key"))
    )


class LineRuns:
    """Levelled runs in the shared folder; ``levels[i]`` lists the paths of level i."""

    def __init__(self, spark: SparkSession, fanout: int = FANOUT):
        self.spark, self.fanout = spark, fanout
        self.root = common.work_path(spark, "line-runs")
        self.levels: list[list[str]] = []
        self._made = 0

    def _write(self, rows: DataFrame, level: int) -> None:
        path = f"{self.root}/{self._made}"
        self._made += 1
        rows.sortWithinPartitions("key").write.parquet(path)
        while len(self.levels) <= level:
            self.levels.append([])
        self.levels[level].append(path)

    def _read(self, paths: list[str]) -> DataFrame:
        return self.spark.read.schema("key binary, n_docs bigint, keeper bigint").parquet(*paths)

    def runs(self) -> DataFrame | None:
        paths = [p for level in self.levels for p in level]
        return self._read(paths) if paths else None

    def unseen(self, keys: DataFrame) -> DataFrame:
        """The merge anti-join: the lines of ``keys`` that no run holds."""
        runs = self.runs()
        return keys if runs is None else keys.join(runs.select("key"), "key", "left_anti")

    def add(self, keys: DataFrame) -> None:
        """Adds a batch: keys of documents that no earlier batch held."""
        counted = (
            keys.select("key", "doc").distinct()
            .groupBy("key").agg(F.count("*").alias("n_docs"), F.max("doc").alias("keeper"))
        )
        self._write(counted, 0)
        self.compact()

    def compact(self) -> None:
        level = 0
        while level < len(self.levels):
            if len(self.levels[level]) >= self.fanout:
                old, self.levels[level] = self.levels[level], []
                self._write(_merged(self._read(old)), level + 1)
                for path in old:
                    common.remove_path(self.spark, path)
            level += 1

    def totals(self) -> DataFrame:
        """One row per key over all runs."""
        runs = self.runs()
        single = sum(map(len, self.levels)) == 1
        return runs if single else _merged(runs)


def _merged(runs: DataFrame) -> DataFrame:
    return runs.groupBy("key").agg(F.sum("n_docs").alias("n_docs"), F.max("keeper").alias("keeper"))


def first_seen_lines(runs: LineRuns, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Incremental use: the lines of a new batch that no earlier batch held, before it is added."""
    keys = common.stored(line_keys(docs, id_col, text_col), "line-batch")
    fresh = common.stored(runs.unseen(keys), "line-fresh")
    runs.add(keys)
    return fresh


def dedup_lines(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_docs: int = MIN_DOCS,
    min_chars: int = MIN_CHARS, n_batches: int = N_BATCHES,
) -> DataFrame:
    """All columns of ``docs`` and ``kept_text``, ``n_lines``, ``n_dropped``.

    A key found in ``min_docs`` documents or more keeps its lines only in the
    largest id that holds it.
    """
    spark, docs = docs.sparkSession, common.set_aside(docs, ["kept_text", "n_lines", "n_dropped"])
    keys = line_keys(docs, id_col, text_col, min_chars)
    path = common.work_path(spark, "line-keys")
    keys.withColumn("batch", F.pmod(F.xxhash64("doc"), F.lit(n_batches)).cast("int")).write.partitionBy("batch").parquet(path)
    keys = spark.read.schema("doc bigint, text_id bigint, pos int, key binary, batch int").parquet(path)
    runs = LineRuns(spark)
    for batch in range(n_batches):
        runs.add(keys.where(F.col("batch") == batch))
    common_keys = runs.totals().where(F.col("n_docs") >= min_docs)
    dropped = (
        keys.join(common_keys.hint("shuffle_hash"), "key").where(F.col("doc") < F.col("keeper"))
        .groupBy("doc", "text_id").agg(F.collect_set("pos").alias("_ld_dropped"))
        .select(F.col("doc").alias("_ld_doc"), F.col("text_id").alias("_ld_text"), "_ld_dropped")
    )
    own = [F.coalesce(docs[id_col].cast("bigint"), F.lit(_LOWEST)) == dropped["_ld_doc"], F.xxhash64(docs[text_col]) == dropped["_ld_text"]]
    joined = docs.join(dropped.hint("shuffle_hash"), reduce(Column.__and__, own), "left")
    lines = lines_of(F.col(text_col))
    kept = common.let(
        lines,
        lambda ls: F.array_join(
            F.transform(F.array_except(F.sequence(F.lit(0), F.size(ls) - 1), F.col("_ld_dropped")), lambda i: F.get(ls, i)), "\n"
        ),
    )
    return joined.select(
        *[docs[f"`{c}`"] for c in docs.columns],
        F.when(F.col("_ld_dropped").isNull(), F.coalesce(F.col(text_col), F.lit(""))).otherwise(kept).alias("kept_text"),
        F.size(lines).cast("bigint").alias("n_lines"),
        F.coalesce(F.size("_ld_dropped"), F.lit(0)).cast("bigint").alias("n_dropped"),
    )


def op1_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents").select("doc_id", "text")
    return dedup_lines(docs).select("doc_id", "n_lines", "n_dropped", F.sha2(F.col("kept_text").cast("binary"), 256).alias("kept_sha256"))


#: Every rule of the contract over whole lines, without digests.
OP1_SQL = r"""
WITH split AS (
  SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line,
         unnest(range(len(string_split(coalesce(text, ''), chr(10))))) AS pos
  FROM documents),
keyed AS (
  SELECT doc_id, pos, line,
         translate(trim(line, chr(32)||chr(9)||chr(10)||chr(11)||chr(12)||chr(13)),
                   'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key
  FROM split),
shared AS (
  SELECT key, max(doc_id) AS keeper FROM keyed WHERE length(key) >= 20
  GROUP BY key HAVING count(DISTINCT doc_id) >= 3),
marked AS (
  SELECT k.doc_id, k.pos, k.line, (s.key IS NOT NULL AND k.doc_id <> s.keeper) AS gone
  FROM keyed k LEFT JOIN shared s ON k.key = s.key)
SELECT doc_id, count(*)::BIGINT AS n_lines, (count(*) FILTER (gone))::BIGINT AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (NOT gone), '')) AS kept_sha256
FROM marked GROUP BY doc_id
"""
