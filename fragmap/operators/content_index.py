"""What the stored values say: numeric ranges, membership, and a prefix index of text.

Each table is scanned once for all probes of a batch of questions, and only words that a
probe's stem begins leave the scan. The text index holds distinct words of distinct values.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fragmap.catalog import NUMERIC, TEMPORAL, TEXT, Attribute, Catalog, table

TOKEN_SPLIT = r"[^a-z0-9_#\-]+"
PREFIX = 3
MENTION = 200
_PROFILE = "relation string, attribute string, func string, lo double, hi double"


def _number(a: Attribute) -> Column:
    c = F.col(a.name)
    return (F.year(c) if a.kind == TEMPORAL else c).cast("double") + 0.0  # + 0.0 turns -0.0 into 0.0


def _numeric(catalog: Catalog, relation: str, temporal_as_year: bool, exclude_keys: bool) -> list[Attribute]:
    keys = {(k.fk_relation, k.fk_attribute) for k in catalog.keys} | {(k.pk_relation, k.pk_attribute) for k in catalog.keys}
    return [
        a for a in catalog.of(relation)
        if (a.kind == NUMERIC or (temporal_as_year and a.kind == TEMPORAL)) and not (exclude_keys and (a.relation, a.name) in keys)
    ]


def numeric_profile(spark: SparkSession, sf_dir: str, catalog: Catalog, temporal_as_year: bool = True, exclude_keys: bool = False) -> DataFrame:
    """(relation, attribute, func, lo, hi): one aggregation per table."""
    out = []
    for relation in catalog.relations:
        attributes = _numeric(catalog, relation, temporal_as_year, exclude_keys)
        if not attributes:
            continue
        ends = table(spark, sf_dir, relation).agg(*[f(_number(a)).alias(f"{e}_{a.name}") for a in attributes for e, f in (("lo", F.min), ("hi", F.max))])
        rows = F.array(*[
            F.struct(
                F.lit(relation).alias("relation"), F.lit(a.name).alias("attribute"), F.lit("year" if a.kind == TEMPORAL else "").alias("func"),
                F.col(f"lo_{a.name}").alias("lo"), F.col(f"hi_{a.name}").alias("hi"),
            )
            for a in attributes
        ])
        out.append(ends.select(F.inline(rows)))
    return reduce(DataFrame.unionByName, out) if out else spark.createDataFrame([], _PROFILE)


def numeric_members(spark: SparkSession, sf_dir: str, catalog: Catalog, numbers: DataFrame, temporal_as_year: bool = True) -> DataFrame:
    """(relation, attribute, num): which of ``numbers`` (num double) occur in which numeric attribute."""
    out = []
    for relation in catalog.relations:
        attributes = _numeric(catalog, relation, temporal_as_year, False)
        if not attributes:
            continue
        values = F.array(*[F.struct(F.lit(a.name).alias("attribute"), _number(a).alias("num")) for a in attributes])
        rows = table(spark, sf_dir, relation).select(*[a.name for a in attributes]).select(F.inline(values))
        found = rows.join(numbers.select("num").distinct(), "num", "left_semi").distinct()
        out.append(found.select(F.lit(relation).alias("relation"), "attribute", "num"))
    return reduce(DataFrame.unionByName, out)


def text_cells(spark: SparkSession, sf_dir: str, catalog: Catalog) -> DataFrame:
    """(relation, attribute, value) of every stored text cell; one scan per table, nothing is moved."""
    out = []
    for relation in catalog.relations:
        names = [a.name for a in catalog.of(relation) if a.kind == TEXT]
        if names:
            cells = F.array(*[F.struct(F.lit(n).alias("attribute"), F.col(n).alias("value")) for n in names])
            rows = table(spark, sf_dir, relation).select(*names).select(F.inline(cells)).where("value is not null")
            out.append(rows.select(F.lit(relation).alias("relation"), "attribute", "value"))
    return reduce(DataFrame.unionByName, out) if out else spark.createDataFrame([], "relation string, attribute string, value string")


def distinct_cells(cells: DataFrame, mention_over: int = MENTION) -> DataFrame:
    """``cells`` with each value of up to ``mention_over`` characters once per attribute; longer ones stay as they are, as they would be large grouping keys."""
    short = F.length("value") <= mention_over
    return cells.where(short).distinct().unionByName(cells.where(~short))


def cell_terms(cells: DataFrame, mention_over: int = MENTION) -> DataFrame:
    """(relation, attribute, value_id, value, term): the distinct words of each cell.

    A value of more than ``mention_over`` characters is text that a question mentions words
    of, not a name that it quotes: ``value`` is null then and predicates keep the keyword.
    """
    terms = F.array_distinct(F.filter(F.split(F.lower("value"), TOKEN_SPLIT), lambda t: t != ""))
    quoted = F.when(F.length("value") <= mention_over, F.col("value"))
    # the cell's own columns come first, so that a word's row does not carry the whole text
    rows = cells.select("relation", "attribute", F.xxhash64("value").alias("value_id"), quoted.alias("value"), terms.alias("terms"))
    return rows.select("relation", "attribute", "value_id", "value", F.explode("terms").alias("term"))


def text_terms(cells: DataFrame, mention_over: int = MENTION) -> DataFrame:
    """The index: (relation, attribute, value_id, value, term, prefix), a posting once however many cells hold the value."""
    postings = cell_terms(cells, mention_over).groupBy("relation", "attribute", "value_id", "term").agg(F.first("value").alias("value"))
    return postings.withColumn("prefix", F.substring("term", 1, PREFIX))


def save_terms(terms: DataFrame, path: str) -> None:
    """Sorted by term inside each prefix, so that a probe reads few row groups."""
    terms.repartition("prefix").sortWithinPartitions("prefix", "term").write.partitionBy("prefix").parquet(path)


def match_terms(probes: DataFrame, terms: DataFrame) -> DataFrame:
    """(probe_id, relation, attribute, value_id, value, terms) of values in which every stem of a probe begins some word.

    ``probes``: probe_id, relation, attribute, stems; they are as many as a batch of questions
    has keywords and a schema has text attributes, and are broadcast. ``terms`` is read once:
    only words that some stem begins leave the scan. Of the words that one stem begins the
    shortest (the least of equals) stands for it in the result's ``terms``.
    """
    stems = probes.select("probe_id", "relation", "attribute", F.size("stems").alias("need"), F.explode("stems").alias("stem"))
    stems = stems.withColumn("start", F.substring("stem", 1, PREFIX))
    sizes = sorted(r[0] for r in stems.select(F.length("start")).distinct().collect())
    starts = F.explode(F.array_distinct(F.array(*[F.substring("term", 1, n) for n in sizes or [PREFIX]]))).alias("start")
    hits = terms.select("relation", "attribute", "value_id", "value", "term", starts).join(F.broadcast(stems), ["relation", "attribute", "start"])
    hits = hits.where(F.col("term").startswith(F.col("stem")))
    by = ["probe_id", "relation", "attribute", "value_id"]
    word = F.min(F.struct(F.length("term").alias("size"), "term")).alias("word")
    nearest = hits.groupBy(*by, "stem").agg(word, F.max("value").alias("value"), F.first("need").alias("need"))
    return (
        nearest.groupBy(*by).agg(F.max("value").alias("value"), F.count("*").alias("found"), F.first("need").alias("need"), F.array_sort(F.collect_set("word.term")).alias("terms"))
        .where("found = need").drop("found", "need")
    )
