"""The fragment graph: occurrence counts, co-occurrence counts and what is read off them.

Counting works on distinct kinds of statements with multiplicities. Pairs are made
inside a statement's row, so there is no self-join; both counts combine in the task
before they are shuffled, and counts of disjoint logs add up.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from fragmap.catalog import Catalog
from fragmap.operators import fragments as fr

STATEMENT, OCCURRENCE = "statement", "occurrence"
#: rows up to which a graph's edges may be broadcast in a lookup
BROADCAST_EDGES = 1_000_000


def _sorted_distinct(keys: Column) -> Column:
    return F.array_sort(F.array_distinct(keys))


def fragment_counts(statements: DataFrame, count_mode: str = STATEMENT, by: tuple[str, ...] = ()) -> DataFrame:
    """(by.., clause, expr, n_v): once per statement, or per textual occurrence."""
    keys = F.array_distinct("keys") if count_mode == STATEMENT else F.col("keys")
    return statements.select(*by, "n", F.explode(keys).alias("f")).groupBy(*by, "f.clause", "f.expr").agg(F.sum("n").alias("n_v"))


def pairs_of(keys: Column) -> Column:
    """array<struct<a, b>> over distinct keys in order, with (a, a) where a key is repeated."""
    ks = _sorted_distinct(keys)
    apart = F.flatten(F.transform(ks, lambda a, i: F.transform(F.slice(ks, i + 2, F.size(ks)), lambda b: F.struct(a.alias("a"), b.alias("b")))))
    twice = F.transform(F.filter(ks, lambda k: F.size(F.filter(keys, lambda x: x == k)) >= 2), lambda k: F.struct(k.alias("a"), k.alias("b")))
    return F.concat(apart, twice)


def fragment_pairs(statements: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """(by.., a_clause, a_expr, b_clause, b_expr, n_e), a before b; a = b counts statements that hold a twice or more."""
    exploded = statements.select(*by, "n", F.explode(pairs_of(F.col("keys"))).alias("p"))
    return exploded.groupBy(
        *by, F.col("p.a.clause").alias("a_clause"), F.col("p.a.expr").alias("a_expr"), F.col("p.b.clause").alias("b_clause"), F.col("p.b.expr").alias("b_expr")
    ).agg(F.sum("n").alias("n_e"))


@dataclass
class FragmentGraph:
    vertices: DataFrame  # clause, expr, n_v
    edges: DataFrame  # a_clause, a_expr, b_clause, b_expr, n_e
    level: str = fr.NOCONSTOP

    def cached(self) -> FragmentGraph:
        return FragmentGraph(self.vertices.cache(), self.edges.cache(), self.level)

    def save(self, path: str) -> None:
        self.vertices.withColumn("level", F.lit(self.level)).write.partitionBy("level").parquet(f"{path}/vertices")
        self.edges.withColumn("level", F.lit(self.level)).write.partitionBy("level").parquet(f"{path}/edges")

    @staticmethod
    def load(spark: SparkSession, path: str, level: str = fr.NOCONSTOP) -> FragmentGraph:
        read = lambda kind: spark.read.parquet(f"{path}/{kind}").where(F.col("level") == level).drop("level")
        return FragmentGraph(read("vertices"), read("edges"), level)

    def save_bucketed(self, spark: SparkSession, name: str, buckets: int = 64) -> None:
        """Tables bucketed by fragment, for lookups without a shuffle where edges are too many to broadcast."""
        self.vertices.write.bucketBy(buckets, "clause", "expr").sortBy("clause", "expr").saveAsTable(f"{name}_vertex")
        self.edges.write.bucketBy(buckets, "a_clause", "a_expr").sortBy("a_clause", "a_expr").saveAsTable(f"{name}_edge")

    def register(self, prefix: str = "qfg") -> None:
        self.vertices.createOrReplaceTempView(f"{prefix}_vertex")
        self.edges.createOrReplaceTempView(f"{prefix}_edge")

    def merge(self, other: FragmentGraph) -> FragmentGraph:
        """The graph of both logs together."""
        v = self.vertices.unionByName(other.vertices).groupBy("clause", "expr").agg(F.sum("n_v").alias("n_v"))
        keys = ["a_clause", "a_expr", "b_clause", "b_expr"]
        return FragmentGraph(v, self.edges.unionByName(other.edges).groupBy(*keys).agg(F.sum("n_e").alias("n_e")), self.level)

    def minus(self, other: FragmentGraph) -> FragmentGraph:
        """The graph without a part of its log."""
        v = self.vertices.unionByName(other.vertices.withColumn("n_v", -F.col("n_v"))).groupBy("clause", "expr").agg(F.sum("n_v").alias("n_v")).where("n_v > 0")
        keys = ["a_clause", "a_expr", "b_clause", "b_expr"]
        e = self.edges.unionByName(other.edges.withColumn("n_e", -F.col("n_e"))).groupBy(*keys).agg(F.sum("n_e").alias("n_e")).where("n_e > 0")
        return FragmentGraph(v, e, self.level)

    def prune(self, min_nv: int = 1, min_ne: int = 1) -> FragmentGraph:
        v = self.vertices.where(F.col("n_v") >= min_nv)
        kept = v.select("clause", "expr")
        e = self.edges.where(F.col("n_e") >= min_ne)
        for side in "ab":
            e = e.join(kept.withColumnsRenamed({"clause": f"{side}_clause", "expr": f"{side}_expr"}), [f"{side}_clause", f"{side}_expr"], "left_semi")
        return FragmentGraph(v, e, self.level)


def build_qfg(log: DataFrame, catalog: Catalog, level: str = fr.NOCONSTOP, clauses: tuple[str, ...] = fr.CLAUSES, count_mode: str = STATEMENT) -> FragmentGraph:
    statements = fr.statement_fragments(log, catalog, level, clauses)
    return FragmentGraph(fragment_counts(statements, count_mode), fragment_pairs(statements), level)


def dice_expr(ne: Column, nv1: Column, nv2: Column, floor: float = 0.0) -> Column:
    """2 n_e / (n_v + n_v); 0 where nothing was seen."""
    both = F.coalesce(nv1, F.lit(0)) + F.coalesce(nv2, F.lit(0))
    value = F.when(both > 0, 2.0 * F.coalesce(ne, F.lit(0)) / both).otherwise(0.0)
    return F.greatest(value, F.lit(float(floor)))


def dice(qfg: FragmentGraph, pairs: DataFrame, floor: float = 0.0) -> DataFrame:
    """``pairs`` (a_clause, a_expr, b_clause, b_expr, in any order) with ``dice``; lookups join by fragment, sides decide by size."""
    rows = pairs.withColumns({"_a": F.struct(F.col("a_clause").alias("clause"), F.col("a_expr").alias("expr")), "_b": F.struct(F.col("b_clause").alias("clause"), F.col("b_expr").alias("expr"))})
    rows = rows.withColumns({"_lo": F.least("_a", "_b"), "_hi": F.greatest("_a", "_b")})
    v = qfg.vertices
    for side in ("_a", "_b"):
        rows = rows.join(v.select(F.struct("clause", "expr").alias(side), F.col("n_v").alias(f"{side}_n")), side, "left")
    e = qfg.edges.select(
        F.struct(F.col("a_clause").alias("clause"), F.col("a_expr").alias("expr")).alias("_lo"), F.struct(F.col("b_clause").alias("clause"), F.col("b_expr").alias("expr")).alias("_hi"), "n_e"
    )
    rows = rows.join(e, ["_lo", "_hi"], "left")
    return rows.withColumn("dice", dice_expr(F.col("n_e"), F.col("_a_n"), F.col("_b_n"), floor)).select(*pairs.columns, "dice")


def edge_dice(qfg: FragmentGraph) -> DataFrame:
    """Dice of every pair of different fragments that was seen."""
    e = qfg.edges.where("a_clause <> b_clause or a_expr <> b_expr")
    v = qfg.vertices
    a = v.select(F.col("clause").alias("a_clause"), F.col("expr").alias("a_expr"), F.col("n_v").alias("n_a"))
    b = v.select(F.col("clause").alias("b_clause"), F.col("expr").alias("b_expr"), F.col("n_v").alias("n_b"))
    joined = e.join(a, ["a_clause", "a_expr"]).join(b, ["b_clause", "b_expr"])
    return joined.select("a_clause", "a_expr", "b_clause", "b_expr", dice_expr(F.col("n_e"), F.col("n_a"), F.col("n_b")).alias("dice"))


def top_partners(qfg: FragmentGraph, n: int = 3) -> DataFrame:
    """The n partners of highest Dice of every fragment."""
    d = edge_dice(qfg)
    flipped = d.select(F.col("b_clause").alias("a_clause"), F.col("b_expr").alias("a_expr"), F.col("a_clause").alias("b_clause"), F.col("a_expr").alias("b_expr"), "dice")
    both = d.unionByName(flipped).withColumn("dice", F.round("dice", 9))
    best = Window.partitionBy("a_clause", "a_expr").orderBy(F.desc("dice"), "b_clause", "b_expr")
    return both.withColumn("place", F.row_number().over(best)).where(F.col("place") <= n)


def graph_as_of(log: DataFrame, catalog: Catalog, questions: DataFrame) -> DataFrame:
    """(qid, clause, expr, n_v) counting only statements older than each question (qid, asked_at).

    Closed days are added up once per stretch between the days that questions fall on, and a
    stretch counts for every later one: no join by range. The open day's statements join by day.
    """
    by_time = fr.statement_fragments(log, catalog, by=("ts",))
    seen = by_time.select("ts", "n", F.explode(F.array_distinct("keys")).alias("f")).select("ts", "n", "f.clause", "f.expr")
    day = lambda c: F.date_trunc("day", F.col(c)).cast("bigint")
    asked = questions.select("qid", "asked_at", day("asked_at").alias("open"))
    opens = F.array(*[F.lit(r[0]).cast("bigint") for r in asked.select("open").distinct().orderBy("open").collect()])  # calendar days
    after = F.filter(opens, lambda d: d > day("ts"))
    stretches = seen.where(F.size(after) > 0).groupBy(after[0].alias("first"), "clause", "expr").agg(F.sum("n").alias("n"))
    totals = stretches.select("clause", "expr", "n", F.explode(F.filter(opens, lambda d: d >= F.col("first"))).alias("open")).groupBy("open", "clause", "expr").agg(F.sum("n").alias("n"))
    closed = asked.join(totals, "open").select("qid", "clause", "expr", "n")
    today = asked.join(seen.withColumn("open", day("ts")), "open").where("ts < asked_at").select("qid", "clause", "expr", "n")
    return closed.unionByName(today).groupBy("qid", "clause", "expr").agg(F.sum("n").alias("n_v"))
