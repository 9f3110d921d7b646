"""Hosts: translators that map keywords, infer joins and print SQL, with or without the log layer.

A batch holds questions of several benchmarks, folds and settings at once. ``ns`` names
the log that a question may see; it prefixes fragments on both sides of every lookup, so
one pass serves all folds.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field, replace

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fragmap.catalog import Catalog, given_catalog
from fragmap.functions.similarity import SimilarityModel
from fragmap.operators import fragments as fr
from fragmap.operators import joins, mapping
from fragmap.operators import qfg as qg
from fragmap.operators import schema_graph as sg
from fragmap.plans import sqlgen
from fragmap.plans.lineage import cut

_MARK = "\x02"


@dataclass(frozen=True)
class Host:
    """Settings of one system. ``log`` switches log evidence for keywords, ``log_joins`` for joins."""

    name: str
    log: bool = False
    log_joins: bool = False
    kappa: int = mapping.KAPPA
    lam: float = mapping.LAMBDA
    relevance: bool = False  # collective score of the parse-tree predecessor
    noise: float = 0.0  # share of questions that its parser gets wrong
    preset: dict[str, float] = field(default_factory=dict)
    ties_wrong: bool = True
    level: str = fr.NOCONSTOP

    # hooks that a host may override; identity by default
    def rescore(self, configs: DataFrame) -> DataFrame:
        return configs

    def post_process(self, sql: Column) -> Column:
        return sql

    def choose(self, configs: DataFrame) -> DataFrame:
        """Interactive choice; off means the first configuration."""
        return configs.where(F.col("rank") == 1)


def vector_pipeline_host(name: str = "H1", log_layer: bool = False, log_joins: bool | None = None, **kw) -> Host:
    """Hand-parsed keywords, similarity alone and shortest joins; with the log layer, both kinds of log evidence."""
    return Host(name, log_layer, log_layer if log_joins is None else log_joins, **kw)


#: Hand-set edge weights of the parse-tree host (many-to-many detours cost more).
PRESET = {"F1": 1.0, "F2": 1.0, "F3": 1.0, "F4": 1.0, "F5": 0.9, "F6": 0.9, "F7": 1.1, "F8": 1.0, "F9": 1.0}


def parse_tree_host(name: str = "H3", log_layer: bool = False, noise: float = 0.3, **kw) -> Host:
    """Its own parser with a share of errors, lexical similarity with mutual relevance, preset join weights."""
    return Host(name, log_layer, log_layer, relevance=not log_layer, noise=noise, preset=PRESET, ties_wrong=False, **kw)


def noisy_parse(questions: DataFrame, rate: float, seed: int = 11, kinds: tuple[str, ...] = ("relation", "operator", "nested")) -> DataFrame:
    """Errors of a whole-question parser, decided by a hash of qid: a relation mention read as a projection, an operator lost, an intent dropped."""
    if rate <= 0:
        return questions
    h = F.pmod(F.xxhash64(F.col("qid"), F.lit(seed)), F.lit(1000))
    kind = F.element_at(F.array(*map(F.lit, kinds)), (F.pmod(F.xxhash64(F.col("qid"), F.lit(seed + 1)), F.lit(len(kinds))) + 1).cast("int"))
    kws = F.col("keywords")
    relation = F.transform(kws, lambda x: x.withField("clause", F.when(x["clause"] == "FROM", "SELECT").otherwise(x["clause"])))
    swapped = F.transform(kws, lambda x, i: x.withField("clause", F.when((i == 0) & (F.size(kws) > 1), "FROM").otherwise(x["clause"])))
    relation = F.when(F.exists(kws, lambda x: x["clause"] == "FROM"), relation).otherwise(swapped)
    operator = F.transform(kws, lambda x: x.withField("op", F.lit(None).cast("string")))
    nested = F.slice(kws, 1, F.greatest(F.size(kws) - 1, F.lit(1)))
    wrong = F.when(kind == "relation", relation).when(kind == "operator", operator).otherwise(nested)
    return questions.withColumn("keywords", F.when(h < int(rate * 1000), wrong).otherwise(kws))


#: Reserved words of questions: operators, aggregates, grouping, words without meaning of their own.
_OPERATORS = {"after": ">", "over": ">", "above": ">", "more than": ">", "longer than": ">", "before": "<", "under": "<", "below": "<", "cheaper than": "<", "less than": "<"}
_AGGREGATES = {"number of": "count", "how many": "count", "average": "avg", "mean": "avg", "total": "sum", "sum of": "sum", "most": "max", "least": "min"}
_STOP = {"the", "a", "an", "of", "in", "from", "with", "by", "for", "to", "on", "that", "who", "having", "both", "and", "any", "has", "out", "return"}


def parse_question(text: str) -> list[dict]:
    """A minimal rule-based parser: content words become keywords, reserved words their metadata."""
    words, out, at = text.lower().split(), [], 0
    raw = text.split()
    op, agg, grouped, first = None, [], False, True
    while at < len(words):
        two = " ".join(words[at : at + 2])
        if two in _OPERATORS or words[at] in _OPERATORS:
            n = 2 if two in _OPERATORS else 1
            op = _OPERATORS[two if n == 2 else words[at]]
            at += n
        elif two in _AGGREGATES or words[at] in _AGGREGATES:
            n = 2 if two in _AGGREGATES else 1
            agg.append(_AGGREGATES[two if n == 2 else words[at]])
            at += n
        elif words[at] in ("per", "each"):
            grouped = True
            at += 1
        elif words[at] in _STOP:
            at += 1
        else:
            clause = "SELECT" if first or grouped else "WHERE"
            out.append({"text": raw[at], "clause": clause, "op": op, "aggs": agg if clause == "SELECT" else [], "grouped": grouped})
            op, agg, grouped, first = None, [], False, False
            at += 1
    return out


def prefixed(graph: DataFrame, ns: Column, columns: tuple[str, ...]) -> DataFrame:
    return graph.withColumns({c: F.concat(ns, F.lit(_MARK), F.col(c)) for c in columns})


def fold_graph(statements: DataFrame, folds: int) -> qg.FragmentGraph:
    """Graph of each (benchmark, fold) from statements of the other folds, clauses prefixed by ``benchmark:fold``.

    ``statements``: benchmark, fold, n, keys. Counts are made once per fold and added up
    for the folds that may see them.
    """
    others = F.explode(F.filter(F.sequence(F.lit(1), F.lit(folds)), lambda f: f != F.col("fold"))).alias("of")
    by = ("benchmark", "fold")
    v, e = qg.fragment_counts(statements, by=by), qg.fragment_pairs(statements, by=by)
    ns = F.concat_ws(":", "benchmark", F.col("of").cast("string"))
    keys = ["a_clause", "a_expr", "b_clause", "b_expr"]
    v = v.select("*", others).select(ns.alias("ns"), "clause", "expr", "n_v").groupBy("ns", "clause", "expr").agg(F.sum("n_v").alias("n_v"))
    e = e.select("*", others).select(ns.alias("ns"), *keys, "n_e").groupBy("ns", *keys).agg(F.sum("n_e").alias("n_e"))
    return qg.FragmentGraph(prefixed(v, F.col("ns"), ("clause",)).drop("ns"), prefixed(e, F.col("ns"), ("a_clause", "b_clause")).drop("ns"))


def relation_dice_by_ns(graph: qg.FragmentGraph) -> dict[str, dict[tuple[str, str], float]]:
    """Dice of relation pairs per log name; as many rows as schemas have relations and edges."""
    end = f"{_MARK}FROM"
    v = {}
    for r in graph.vertices.where(F.col("clause").endswith(end)).collect():
        v[r["clause"].split(_MARK)[0], r["expr"]] = r["n_v"]
    out: dict[str, dict[tuple[str, str], float]] = {}
    for r in graph.edges.where(F.col("a_clause").endswith(end) & F.col("b_clause").endswith(end)).collect():
        ns = r["a_clause"].split(_MARK)[0]
        total = v[ns, r["a_expr"]] + v[ns, r["b_expr"]]
        for pair in ((r["a_expr"], r["b_expr"]), (r["b_expr"], r["a_expr"])):
            out.setdefault(ns, {})[pair] = 2 * r["n_e"] / total
    return out


def batch_candidates(spark: SparkSession, sf_dir: str, questions: DataFrame, sim: SimilarityModel, benchmarks: tuple[str, ...] = ("trade", "activity", "corpus")) -> DataFrame:
    """Scored candidates of all questions, each against its own benchmark's catalog."""
    out = None
    for b in benchmarks:
        cands = cut(mapping.keyword_candidates(spark, sf_dir, given_catalog(b), questions.where(F.col("benchmark") == b)))
        own = cut(mapping.score_candidates(cands, sim))
        out = own if out is None else out.unionByName(own)
    return out


def parsed_candidates(spark: SparkSession, sf_dir: str, questions: DataFrame, sim: SimilarityModel, noises: tuple[float, ...] = (0.0,)) -> dict[float, DataFrame]:
    """By share of parser errors: scored candidates of the questions as such a parser reads them. All are found in one pass over the tables."""
    own = lambda noise: f"{noise}{_MARK}"
    read = None
    for noise in noises:
        part = noisy_parse(questions, noise).withColumn("qid", F.concat(F.lit(own(noise)), "qid"))
        read = part if read is None else read.unionByName(part)
    scored = batch_candidates(spark, sf_dir, cut(read), sim)
    return {n: scored.where(F.col("qid").startswith(own(n))).withColumn("qid", F.substring_index("qid", _MARK, -1)) for n in noises}


def relation_hops(spark: SparkSession, catalog: Catalog) -> DataFrame:
    """(a, b, dist) over all pairs of relations that keys join."""
    near: dict[str, set[str]] = {r: set() for r in catalog.relations}
    for k in catalog.keys:
        near[k.fk_relation].add(k.pk_relation)
        near[k.pk_relation].add(k.fk_relation)
    rows = []
    for start in near:
        dist, ring = {start: 0}, [start]
        while ring:
            ring = [x for r in ring for x in sorted(near[r]) if x not in dist and not dist.update({x: dist[r] + 1})]
        rows += [(start, x, d) for x, d in dist.items()]
    return spark.createDataFrame(rows, "a string, b string, dist int")


def configurations(
    spark: SparkSession, scored: DataFrame, questions: DataFrame, host: Host, graph: qg.FragmentGraph | None
) -> tuple[DataFrame, DataFrame]:
    """Ranked configurations and numbered candidates. ``questions``: qid, ns, keywords."""
    # constraints inferred from the key's nested cases would grow with every filter above
    own = cut(scored.join(questions.select("qid", "ns"), "qid").withColumn("expr", mapping.fragment_key(host.level)))
    spaced = own.withColumn("space", F.concat("ns", F.lit(_MARK), "clause"))
    own = mapping.value_slot(spaced, host.level, graph.vertices if graph is not None and host.log else None, "space").drop("space")
    own = mapping.collapse_values(own, ("qid", "k", "clause", "slot"))
    numbered = mapping.number_candidates(mapping.score_and_prune(own, host.kappa, tie=("expr", "value")))
    numbered = cut(numbered)
    n = questions.select("qid", F.size("keywords").alias("n_keywords"))
    if host.relevance:
        configs = mapping.scored_configs(numbered, n, None)
        score = mapping.score_mutual_relevance(numbered, configs, relation_hops(spark, given_catalog()))
        configs = configs.drop("score").join(score, ["qid", "picks"])
    elif host.log:
        spaced = numbered.withColumn("plain", F.col("clause")).withColumn("clause", F.concat("ns", F.lit(_MARK), "clause"))
        proof = mapping.evidence(spaced, graph).drop("is_from").join(
            numbered.groupBy("qid").agg(F.array_sort(F.collect_list(F.struct("no", (F.col("clause") == "FROM").alias("f")))).alias("fs")), "qid"
        )
        configs = mapping.generate_configs(numbered, n).withColumn("s_sigma", mapping.similarity_score(F.col("picks"))).join(proof, "qid")
        configs = configs.withColumn("s_qfg", mapping.log_score(F.col("picks"), F.col("dice"), F.col("n_cands"), F.col("fs.f")))
        configs = configs.select("qid", "picks", "s_sigma", "s_qfg", mapping.combine(F.col("s_sigma"), F.col("s_qfg"), host.lam).alias("score"))
    else:
        configs = mapping.scored_configs(numbered, n, None)
    return cut(mapping.rank_configs(host.rescore(configs))), numbered


def picked_fragments(chosen: DataFrame, numbered: DataFrame) -> DataFrame:
    """(qid, frags, tied, score): the mapped fragments of each chosen configuration in keyword order."""
    frag = F.struct("k", "clause", "relation", "attribute", "func", "aggs", "grouped", "op", "value", "numeric")
    rows = chosen.select("qid", "score", "tied", F.explode("picks.no").alias("no")).join(numbered.select("qid", "no", frag.alias("f")), ["qid", "no"])
    return rows.groupBy("qid", "score", "tied").agg(F.array_sort(F.collect_list("f")).alias("frags"))


def with_paths(spark: SparkSession, mapped: DataFrame, host: Host, dice: dict[str, dict] | None) -> DataFrame:
    """Adds vertices, edges, path_tied and sql; distinct (log, bag) pairs are solved once. ``mapped``: qid, benchmark, ns, frags."""
    bag = _bag_column(F.col("frags"))
    rows = mapped.withColumn("bag", bag).withColumn("bag_key", F.concat_ws("\x01", "ns", F.array_join("bag", "\x01")))
    graphs = {}
    for b in ("trade", "activity", "corpus"):
        base = sg.build_schema_graph(given_catalog(b))
        graphs[b] = sg.preset_weights(base, host.preset) if host.preset and not host.log_joins else base
    use_log = host.log_joins and dice is not None

    def solve(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            out = []
            for key, benchmark, ns, elements in zip(batch["bag_key"], batch["benchmark"], batch["ns"], batch["bag"]):
                catalog = given_catalog(benchmark)
                graph = sg.weights_from_dice(graphs[benchmark], dice.get(ns, {})) if use_log else graphs[benchmark]
                keys = {r: catalog.primary_key(r) or "" for r in catalog.relations}
                out += [(key, *p) for p in joins.paths_of(list(elements), graph, keys)]
            yield pd.DataFrame(out, columns=["bag_key", "vertices", "edges", "terminals", "n_edges", "total_w"])

    paths = rows.select("bag_key", "benchmark", "ns", "bag").distinct().mapInPandas(solve, joins._PATH)
    best = joins.rank_paths(paths).where("path_rank = 1").select("bag_key", "vertices", "edges", F.col("tied").alias("path_tied"), "total_w")

    @F.pandas_udf("string")
    def sql_of(frags: pd.Series, vertices: pd.Series, edges: pd.Series) -> pd.Series:
        def text(f, v, e):
            if f is None or v is None:
                return None
            own = [{k: (list(x[k]) if k == "aggs" else x[k]) for k in x} for x in f]
            return sqlgen.build_sql(own, list(v), list(e))

        return pd.Series([text(*x) for x in zip(frags, vertices, edges)])

    joined = rows.join(best, "bag_key", "left")
    return joined.withColumn("sql", host.post_process(sql_of(F.col("frags"), F.col("vertices"), F.col("edges")))).drop("bag_key")


def _bag_column(frags: Column) -> Column:
    """The bag of known elements, as ``sqlgen.bag_of`` gives it."""
    key = lambda f: F.concat(f["relation"], F.lit("."), f["attribute"])
    predicates = F.transform(F.filter(frags, lambda f: f["clause"] == "WHERE"), key)
    others = F.transform(F.filter(frags, lambda f: ~f["clause"].isin("WHERE", "FROM")), key)
    elements = F.concat(predicates, F.array_distinct(F.array_except(others, predicates)))
    covered = F.transform(elements, lambda e: F.split_part(e, F.lit("."), F.lit(1)))
    relations = F.array_distinct(F.transform(F.filter(frags, lambda f: f["clause"] == "FROM"), lambda f: f["relation"]))
    return F.array_sort(F.concat(elements, F.array_except(relations, covered)))


def translate(
    spark: SparkSession, sf_dir: str, questions: DataFrame, host: Host, sim: SimilarityModel, graph: qg.FragmentGraph | None = None, dice: dict | None = None,
    scored: DataFrame | None = None,
) -> DataFrame:
    """(qid, .., frags, vertices, edges, sql, score, tied, path_tied) of the top configuration of each question; without one, nulls.

    ``scored``, where given, are the candidates of the questions as the host's parser reads them.
    """
    questions = noisy_parse(questions, host.noise)
    scored = scored if scored is not None else batch_candidates(spark, sf_dir, questions, sim)
    ranked, numbered = configurations(spark, scored, questions, host, graph)
    mapped = cut(picked_fragments(host.choose(ranked), numbered))
    asked = questions.select("qid", "benchmark", "ns")
    full = with_paths(spark, asked.join(mapped, "qid"), host, dice)
    return asked.join(full.drop("benchmark", "ns"), "qid", "left").withColumn("system", F.lit(host.name))


def replace_host(host: Host, **kw) -> Host:
    return replace(host, **kw)
