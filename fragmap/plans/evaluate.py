"""Measures and experiments: folds, accuracies, ablations and sweeps."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from fragmap.catalog import BENCHMARKS, given_catalog, table
from fragmap.functions.similarity import LexiconSimilarity, SimilarityModel
from fragmap.operators import fragments as fr
from fragmap.operators import mapping
from fragmap.operators import qfg as qg
from fragmap.plans import hosts as hs
from fragmap.plans.lineage import cut
from fragmap.sources.glossary import glossary
from fragmap.sources.questions import load_questions

FOLDS = 4
KAPPAS = (1, 3, 5, 7, 10)
LAMBDAS = (0.0, 0.1, 0.25, 0.4, 0.5, 0.625, 0.75, 0.8, 0.875, 0.9, 0.95, 0.99, 1.0)


def assign_folds(questions: DataFrame, folds: int = FOLDS, seed: int = 5, split: str = "question") -> DataFrame:
    """Near-equal folds per benchmark by hash; ``template`` keeps questions of a template together."""
    if split == "template":
        place = F.dense_rank().over(Window.partitionBy("benchmark").orderBy("template"))
        fold = F.pmod(place, F.lit(folds)) + 1
    else:
        fold = F.ntile(folds).over(Window.partitionBy("benchmark").orderBy(F.md5(F.concat(F.lit(f"{seed}:"), F.col("qid")))))
    return questions.withColumn("fold", fold.cast("int")).withColumn("ns", F.concat_ws(":", "benchmark", F.col("fold").cast("string")))


def gold_statements(questions: DataFrame, level: str = fr.NOCONSTOP, keep: float = 1.0) -> DataFrame:
    """Statements of the gold SQL with benchmark and fold; ``keep`` takes a share of them by hash."""
    log = questions.where("gold_sql is not null").select("benchmark", "fold", F.col("gold_sql").alias("sql"), "qid")
    if keep < 1:
        log = log.where(F.pmod(F.xxhash64("qid", F.lit(3)), F.lit(1000)) < int(keep * 1000))
    return fr.statement_fragments(log, given_catalog(), level, by=("benchmark", "fold"))


def _canonical(frags: Column) -> Column:
    """Fragments outside FROM in keyword order, values as text."""
    own = F.filter(frags, lambda f: f["clause"] != "FROM")
    return F.array_sort(F.transform(own, lambda f: F.concat_ws("|", f["clause"], f["relation"], f["attribute"], f["func"], F.array_join(f["aggs"], ">"), f["op"], F.coalesce(f["value"], F.lit("")))))


def judge(answers: DataFrame, questions: DataFrame, ties_wrong: bool = True) -> DataFrame:
    """(system, benchmark, fold, qid, kw, fq, tied): a tie for first place counts as wrong where asked."""
    gold = questions.select("qid", "fold", "gold", "gold_edges")
    rows = answers.join(gold, "qid")
    kw = F.coalesce(_canonical(F.col("frags")) == _canonical(F.col("gold")), F.lit(False))
    edges = F.coalesce(F.array_sort("edges.edge_id") == F.array_sort("gold_edges"), F.lit(False))
    tied = F.coalesce("tied", F.lit(False))
    fair = ~tied if ties_wrong else F.lit(True)
    return rows.select(
        "system", "benchmark", "fold", "qid", (kw & fair).alias("kw"),
        (kw & edges & fair & (~F.coalesce("path_tied", F.lit(False)) if ties_wrong else F.lit(True))).alias("fq"), tied.alias("tied"),
    )


def accuracy(judged: DataFrame, by: tuple[str, ...] = ("system", "benchmark")) -> DataFrame:
    pct = lambda c: F.round(100 * F.avg(F.col(c).cast("double")), 1)
    return judged.groupBy(*by).agg(F.count("*").alias("n"), pct("kw").alias("kw_pct"), pct("fq").alias("fq_pct"))


def accuracy_cube(judged: DataFrame) -> DataFrame:
    """Accuracy by system, benchmark and fold with all totals."""
    return judged.cube("system", "benchmark", "fold").agg(F.count("*").alias("n"), F.round(100 * F.avg(F.col("fq").cast("double")), 1).alias("fq_pct")).where("system is not null")


def improvement(base: Column, new: Column) -> Column:
    return F.round(100 * (new - base) / base, 0)


def exec_equal(spark: SparkSession, sql1: str, sql2: str) -> bool:
    """Whether two statements return equal multisets of rows; doubles are compared to four places, as sums may be added in any order."""
    a, b = (rounded(spark.sql(x)) for x in (sql1, sql2))
    if [k for _, k in a.dtypes] != [k for _, k in b.dtypes]:
        return False
    b = b.toDF(*a.columns)
    return a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()


def rounded(rows: DataFrame, places: int = 4) -> DataFrame:
    return rows.select(*[(F.round(c, places) if k == "double" else F.col(c)).alias(c) for c, k in rows.dtypes])


def register_tables(spark: SparkSession, sf_dir: str) -> None:
    for name in BENCHMARKS["all"]:
        table(spark, sf_dir, name).createOrReplaceTempView(name)


def translation_report(spark: SparkSession, sf_dir: str, host: hs.Host, qids: list[str]) -> DataFrame:
    """(qid, template, sql, tied, same_text, same_rows): the host's SQL beside the gold SQL, run against the same tables."""
    x = Experiment(spark, sf_dir, only=qids)
    register_tables(spark, sf_dir)
    found = x.answers(host).select("qid", "sql", "tied").join(x.asked.select("qid", "template", "gold_sql"), "qid")
    rows = []
    for r in found.collect():  # as many as the questions asked
        same_rows = r["sql"] is not None and (r["sql"] == r["gold_sql"] or exec_equal(spark, r["sql"], r["gold_sql"]))
        rows.append((r["qid"], r["template"], r["sql"], r["tied"], r["sql"] == r["gold_sql"], same_rows))
    return spark.createDataFrame(rows, "qid string, template string, sql string, tied boolean, same_text boolean, same_rows boolean")


class Experiment:
    """Questions, folds, candidates and fold graphs, each made once."""

    def __init__(self, spark: SparkSession, sf_dir: str, sim: SimilarityModel | None = None, split: str = "question", level: str = fr.NOCONSTOP, keep: float = 1.0, only: list[str] | None = None, noises: tuple[float, ...] = (0.0,)):
        """``only`` names the questions to translate; the logs hold all of them. ``noises``: shares of parser errors of the hosts to come."""
        self.spark, self.sf_dir = spark, sf_dir
        self.sim = sim or LexiconSimilarity(glossary(spark))
        self.questions = assign_folds(load_questions(spark, sf_dir), split=split)
        self.questions = cut(self.questions)
        self.asked = self.questions if only is None else cut(self.questions.where(F.col("qid").isin(only)))
        self.parsed = hs.parsed_candidates(spark, sf_dir, self.asked, self.sim, tuple(sorted(set(noises))))
        self.scored = self.parsed.get(0.0)
        self.use_level(level, keep)

    def use_level(self, level: str, keep: float = 1.0) -> None:
        graph = hs.fold_graph(gold_statements(self.questions, level, keep), FOLDS)
        self.level, self.graph = level, qg.FragmentGraph(cut(graph.vertices), cut(graph.edges), level)
        self.dice = hs.relation_dice_by_ns(self.graph)

    def run(self, host: hs.Host) -> DataFrame:
        return judge(self.answers(hs.replace_host(host, level=self.level)), self.asked, host.ties_wrong)

    def answers(self, host: hs.Host) -> DataFrame:
        return hs.translate(self.spark, self.sf_dir, self.asked, host, self.sim, self.graph, self.dice, self.parsed.get(host.noise))


def systems() -> list[hs.Host]:
    return [
        hs.parse_tree_host("H3"), hs.parse_tree_host("H4", log_layer=True), hs.vector_pipeline_host("H1"), hs.vector_pipeline_host("H2", log_layer=True),
    ]


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def run_main_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = Experiment(spark, sf_dir, noises=tuple(h.noise for h in systems()))
    return accuracy(_union([x.run(h) for h in systems()]))


def run_join_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = Experiment(spark, sf_dir)
    off = hs.vector_pipeline_host("H2a", log_layer=True, log_joins=False)
    return accuracy(_union([x.run(off), x.run(hs.vector_pipeline_host("H2", log_layer=True))]))


def run_kappa_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = Experiment(spark, sf_dir)
    parts = [x.run(hs.vector_pipeline_host("H2", log_layer=True, kappa=k)).withColumn("kappa", F.lit(k)) for k in KAPPAS]
    return accuracy(_union(parts), ("kappa", "benchmark"))


def run_lambda_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scores are linear in lambda, so configurations are scored once and ranked per value; keyword accuracy only."""
    x = Experiment(spark, sf_dir)
    ranked, numbered = hs.configurations(spark, x.scored, x.questions, hs.vector_pipeline_host("H2", log_layer=True), x.graph)
    lams = F.explode(F.array(*[F.lit(v) for v in LAMBDAS])).alias("lam")
    per = ranked.select("qid", "picks", "s_sigma", "s_qfg", lams).withColumn("score", mapping.combine(F.col("s_sigma"), F.col("s_qfg"), F.col("lam")))
    best = mapping.rank_configs(per, ("lam", "qid")).where("rank = 1")
    rows = best.select("lam", "qid", "tied", F.explode("picks.no").alias("no")).join(numbered.select("qid", "no", F.struct("k", "clause", "relation", "attribute", "func", "aggs", "grouped", "op", "value", "numeric").alias("f")), ["qid", "no"])
    mapped = rows.groupBy("lam", "qid", "tied").agg(F.array_sort(F.collect_list("f")).alias("frags"))
    asked = x.questions.select("qid", "benchmark", "gold", lams)
    hit = F.coalesce((_canonical(F.col("frags")) == _canonical(F.col("gold"))) & ~F.col("tied"), F.lit(False))
    return asked.join(mapped, ["lam", "qid"], "left").groupBy("lam", "benchmark").agg(F.count("*").alias("n"), F.round(100 * F.avg(hit.cast("double")), 1).alias("kw_pct"))


def run_level_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    x, parts = Experiment(spark, sf_dir), []
    for level in fr.LEVELS:
        x.use_level(level)
        parts.append(x.run(hs.vector_pipeline_host("H2", log_layer=True)).withColumn("level", F.lit(level)))
    return accuracy(_union(parts), ("level", "benchmark"))


def run_template_split(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stricter split: no question of a template has a sibling in its log."""
    x = Experiment(spark, sf_dir, split="template")
    return accuracy(_union([x.run(hs.vector_pipeline_host("H1")), x.run(hs.vector_pipeline_host("H2", log_layer=True))]))


def run_log_fraction(spark: SparkSession, sf_dir: str, shares: tuple[float, ...] = (0.1, 0.25, 0.5, 1.0)) -> DataFrame:
    x, parts = Experiment(spark, sf_dir), []
    for share in shares:
        x.use_level(fr.NOCONSTOP, share)
        parts.append(x.run(hs.vector_pipeline_host("H2", log_layer=True)).withColumn("log_share", F.lit(share)))
    return accuracy(_union(parts), ("log_share", "benchmark"))


def benchmark_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Relations, attributes, key edges, questions and stored rows of each benchmark."""
    q = {r["benchmark"]: r["n"] for r in load_questions(spark, sf_dir).groupBy("benchmark").agg(F.count("*").alias("n")).collect()}
    rows = []
    for b in ("trade", "activity", "corpus"):
        c = given_catalog(b)
        rows.append((b, len(c.relations), len(c.attributes), len(c.keys), q[b]))
    sizes = _union([table(spark, sf_dir, t).agg(F.count("*").alias("n")).withColumn("benchmark", F.lit(b)) for b in ("trade", "activity", "corpus") for t in BENCHMARKS[b]])
    stats = spark.createDataFrame(rows, "benchmark string, relations bigint, attributes bigint, key_edges bigint, questions bigint")
    return stats.join(sizes.groupBy("benchmark").agg(F.sum("n").alias("stored_rows")), "benchmark")
