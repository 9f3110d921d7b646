"""Keyword mapping: candidates, pruning, configurations and their scores.

Everything runs for a whole batch of questions at once. Candidates are numbered inside
their question, log evidence is looked up once per pair of candidates and kept as a
matrix in the question's row, and configurations are arrays of candidate numbers, so a
configuration costs a few array reads whatever the log's size.

Stored values are bound late: values of one fragment share its evidence, so a fragment is
one candidate with its best value and the number of values that are as good (``ways``).
Candidates therefore follow the schema and the log, not the stored values, and a tie among
values still counts as a tie.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from fragmap.catalog import TEXT, Catalog
from fragmap.functions.similarity import SimilarityModel, words_in
from fragmap.functions.stem import porter_stem, stem_tokens
from fragmap.operators import content_index as ci
from fragmap.operators import fragments as fr
from fragmap.operators import qfg as qg

EPSILON = 1e-6
KAPPA, LAMBDA = 5, 0.8
MAX_CONFIGS = 20_000
_NUMBER = r"(?:^|\s)([0-9]+(?:\.[0-9]+)?)(?:\s|$)"
_DIGIT = r"([0-9]+(?:\.[0-9]+)?)"
SQUARE, ORDERED, UNORDERED = "square", "ordered", "unordered"
_CAND = ["qid", "k", "keyword", "clause", "relation", "attribute", "func", "aggs", "grouped", "op", "value", "words", "targets", "numeric", "holds", "ways"]


def explode_keywords(questions: DataFrame, number_mode: str = "token") -> DataFrame:
    """(qid, k, keyword, clause, op, aggs, grouped, num, rest): the number of a keyword and its remaining text."""
    pattern = _NUMBER if number_mode == "token" else _DIGIT
    rows = questions.select("qid", F.posexplode("keywords").alias("k", "kw")).select("qid", "k", "kw.*").withColumnRenamed("text", "keyword")
    found = F.regexp_extract("keyword", pattern, 1)
    return rows.withColumns({
        "num": F.when(found != "", found.cast("double")), "num_text": F.when(found != "", found),
        "rest": F.trim(F.regexp_replace("keyword", pattern, " ")),
    })


def _schema(spark: SparkSession, catalog: Catalog) -> DataFrame:
    rows = []
    for a in catalog.attributes:
        names = [porter_stem(w) for w in (*a.words, *catalog.words.get(a.relation, ()))]
        rows.append((a.relation, a.name, a.kind, list(dict.fromkeys(names))))
    return spark.createDataFrame(rows, "relation string, attribute string, kind string, names array<string>")


def keyword_candidates(
    spark: SparkSession, sf_dir: str, catalog: Catalog, questions: DataFrame, value_binding: str = "stored", number_mode: str = "token", prefilter: bool = True,
    terms: DataFrame | None = None, profile: DataFrame | None = None, temporal_as_year: bool = True, exclude_keys: bool = False,
) -> DataFrame:
    """All candidate fragments of every keyword, with the stems to compare, before scoring."""
    kws = explode_keywords(questions, number_mode)
    kws = kws.withColumn("words", stem_tokens(words_in(F.col("keyword"))))
    schema = F.broadcast(_schema(spark, catalog))  # metadata
    text_kws = kws.where("num is null")
    none = F.lit(None).cast("string")

    def finish(df: DataFrame, clause, relation="relation", attribute="attribute", func=F.lit(""), aggs=None, op=F.lit(""), value=none, targets="names", numeric=False, holds=F.lit(True), ways=F.lit(1)) -> DataFrame:
        return df.select(
            "qid", "k", "keyword", clause.alias("clause"), F.col(relation).alias("relation"), (F.col(attribute) if attribute else F.lit("")).alias("attribute"), func.alias("func"),
            (aggs if aggs is not None else F.array().cast("array<string>")).alias("aggs"), F.coalesce("grouped", F.lit(False)).alias("grouped"), op.alias("op"), value.alias("value"),
            "words", F.col(targets).alias("targets") if isinstance(targets, str) else targets.alias("targets"), F.lit(numeric).alias("numeric"),
            holds.alias("holds"), ways.cast("double").alias("ways"),
        )

    relations = spark.createDataFrame(
        [(r, [porter_stem(w) for w in catalog.words.get(r, (r,))]) for r in catalog.relations], "relation string, names array<string>"
    )
    from_ = finish(text_kws.where("clause = 'FROM'").join(F.broadcast(relations)), F.lit("FROM"), attribute=None)
    select = finish(text_kws.where("clause = 'SELECT'").join(schema), F.lit("SELECT"), aggs=F.coalesce("aggs", F.array().cast("array<string>")))
    numeric = numeric_candidates(spark, sf_dir, catalog, kws.where("num is not null"), profile, prefilter, temporal_as_year, exclude_keys)
    numeric = finish(
        numeric.join(schema, ["relation", "attribute"]).withColumn("words", stem_tokens(words_in(F.col("rest")))), F.lit("WHERE"), func=F.col("func"),
        op=F.coalesce("op", F.lit("=")), value=F.col("num_text"), numeric=True, holds=F.col("holds"),
    )
    probing = text_kws.where("clause not in ('FROM', 'SELECT')")
    text = text_candidates(spark, sf_dir, catalog, probing, terms)
    value = F.col("keyword") if value_binding == "keyword" else F.coalesce("value", "keyword")
    ways = F.lit(1) if value_binding == "keyword" else F.col("ways")
    with_value = F.array_distinct(F.concat("names", F.col("value_words")))
    text = finish(
        text.withColumn("value_words", stem_tokens(words_in(F.array_join("terms", " ")))), F.col("clause"), op=F.coalesce("op", F.lit("=")), value=value, targets=with_value, ways=ways,
    )
    return from_.unionByName(select).unionByName(numeric).unionByName(text).dropDuplicates(["qid", "k", "clause", "relation", "attribute", "func", "op", "value"])


def numeric_candidates(
    spark: SparkSession, sf_dir: str, catalog: Catalog, kws: DataFrame, profile: DataFrame | None = None, prefilter: bool = True,
    temporal_as_year: bool = True, exclude_keys: bool = False,
) -> DataFrame:
    """Keywords with a number, each with the numeric attributes and whether some value satisfies the comparison; only those where one does with ``prefilter``."""
    profile = profile if profile is not None else ci.numeric_profile(spark, sf_dir, catalog, temporal_as_year, exclude_keys)
    rows = kws.withColumn("cmp", F.coalesce("op", F.lit("="))).join(F.broadcast(profile))
    rows = rows.where((F.col("func") != "year") | F.col("num").between(1000, 9999))
    n, lo, hi = F.col("num"), F.col("lo"), F.col("hi")
    members = ci.numeric_members(spark, sf_dir, catalog, kws.where("coalesce(op, '=') = '='").select("num"), temporal_as_year).withColumn("is_member", F.lit(True))
    rows = rows.join(members, ["relation", "attribute", "num"], "left")
    holds = (
        F.when(F.col("cmp") == ">", hi > n).when(F.col("cmp") == ">=", hi >= n).when(F.col("cmp") == "<", lo < n).when(F.col("cmp") == "<=", lo <= n)
        .when(F.col("cmp") == "<>", (lo != n) | (hi != n)).otherwise(F.coalesce("is_member", F.lit(False)))
    )
    rows = rows.withColumn("holds", F.coalesce(holds, F.lit(False)))
    return rows.where("holds") if prefilter else rows


def text_matches(spark: SparkSession, sf_dir: str, catalog: Catalog, kws: DataFrame, terms: DataFrame | None = None) -> DataFrame:
    """(keyword, relation, attribute, value_id, value, terms) of stored values with a word for each stem; stems of the attribute's own names are not required."""
    terms = terms if terms is not None else ci.cell_terms(ci.distinct_cells(ci.text_cells(spark, sf_dir, catalog)))
    schema = F.broadcast(_schema(spark, catalog).where(F.col("kind") == TEXT))
    tokens = F.filter(F.split(F.lower("keyword"), r"\s+"), lambda w: w != "")
    probes = (
        kws.select("keyword").distinct().withColumn("stems", stem_tokens(tokens)).join(schema)
        .select(F.col("keyword").alias("probe_id"), "relation", "attribute", F.array_distinct(F.array_except("stems", "names")).alias("stems")).where(F.size("stems") > 0)
    )
    return ci.match_terms(probes, terms).withColumnRenamed("probe_id", "keyword")


def text_candidates(spark: SparkSession, sf_dir: str, catalog: Catalog, kws: DataFrame, terms: DataFrame | None = None) -> DataFrame:
    """Keywords with the text attributes that hold a match, once per set of matched words: the least such value and how many there are.

    A value that is the keyword itself stands alone; a long text is mentioned, so its value is null and it counts once.
    """
    schema = F.broadcast(_schema(spark, catalog).where(F.col("kind") == TEXT))
    found = text_matches(spark, sf_dir, catalog, kws, terms)
    same, long = F.coalesce(F.lower("value") == F.lower("keyword"), F.lit(False)), F.col("value").isNull()
    groups = found.groupBy("keyword", "relation", "attribute", "terms", same.alias("same"), long.alias("long")).agg(F.min("value").alias("value"), F.count("*").alias("n"))
    groups = groups.withColumn("ways", F.when(F.col("long"), 1).otherwise(F.col("n"))).drop("n", "same", "long")
    return kws.join(groups, "keyword").join(schema.drop("kind"), ["relation", "attribute"])


def score_candidates(cands: DataFrame, sim: SimilarityModel, epsilon: float = EPSILON) -> DataFrame:
    """Adds sigma. Of a text predicate whose value is the keyword itself the value words decide, so it scores 1; a number
    that no stored value satisfies, or without a word beside it, scores epsilon."""
    scored = sim.score(cands)
    same = (~F.col("numeric")) & (F.col("op") != "") & (F.lower("value") == F.lower("keyword"))
    vain = F.col("numeric") & (~F.col("holds") | (F.size("words") == 0))
    return scored.withColumn("sigma", F.when(same, 1.0).when(vain, epsilon).otherwise(F.col("sigma")))


def collapse_values(scored: DataFrame, by: tuple[str, ...] = ("qid", "k", "clause", "expr")) -> DataFrame:
    """One candidate per fragment: its best sigma, the least value that has it, and in how many ways it can be bound so."""
    rest = [c for c in scored.columns if c not in {*by, "sigma", "ways", "value"}]
    best = scored.groupBy(*by, "sigma").agg(F.sum("ways").alias("ways"), F.min(F.struct("value", *rest)).alias("own"))
    top = best.groupBy(*by).agg(F.max(F.struct("sigma", "ways", "own")).alias("t"))
    return top.select(*by, "t.sigma", "t.ways", "t.own.*").select(*scored.columns)


def value_slot(scored: DataFrame, level: str, logged: DataFrame | None, clause: str = "clause") -> DataFrame:
    """Adds ``slot``, by which values collapse: the fragment, but where constants are kept only logged fragments stand alone,
    as all that the log never saw have the same evidence. ``logged``: clause, expr."""
    if level != fr.FULL or logged is None:
        return scored.withColumn("slot", F.col("expr"))
    seen = logged.select(F.col("clause").alias("_clause"), F.col("expr").alias("_expr"), F.lit(True).alias("_seen")).distinct()
    joined = scored.join(seen, (F.col(clause) == F.col("_clause")) & (F.col("expr") == F.col("_expr")), "left")
    return joined.withColumn("slot", F.when(F.col("_seen"), F.col("expr")).otherwise(fragment_key(fr.NOCONST))).drop("_clause", "_expr", "_seen")


def fragment_key(level: str) -> Column:
    """Canonical text of a candidate, the same as that of a logged fragment."""
    base = F.concat("relation", F.when(F.col("attribute") == "", "").otherwise(F.concat(F.lit("."), "attribute")))
    base = F.when(F.col("func") == "", base).otherwise(F.concat("func", F.lit("("), base, F.lit(")")))
    base = F.aggregate("aggs", base, lambda text, agg: F.concat(agg, F.lit("("), text, F.lit(")")))
    if level == fr.NOCONSTOP:
        tail = F.lit(" ?op ?val")
    elif level == fr.NOCONST:
        tail = F.concat(F.lit(" "), "op", F.lit(" ?val"))
    else:
        quoted = F.when(F.col("numeric"), F.col("value")).otherwise(F.concat(F.lit("'"), F.regexp_replace("value", "'", "''"), F.lit("'")))
        tail = F.concat(F.lit(" "), "op", F.lit(" "), quoted)
    return F.when(F.col("op") == "", base).otherwise(F.concat(base, tail))


def score_and_prune(cands: DataFrame, kappa: int = KAPPA, epsilon: float = EPSILON, by: tuple[str, ...] = ("qid", "k"), tie: tuple[str, ...] = ("expr",)) -> DataFrame:
    """Only exact matches where there are any; else the first kappa, with all that tie with the last if its score is above 0.

    Scores are clamped at 1 - epsilon before ranking, so that no exact match is lost to
    kappa; the rank filter stands alone, which lets Spark cut each group early.
    """
    clamped = F.when(F.col("sigma") >= 1 - epsilon, 1.0).otherwise(F.col("sigma"))
    group = Window.partitionBy(*by)
    ranked = cands.withColumn("_s", clamped).withColumn("_rank", F.rank().over(group.orderBy(F.desc("_s"))))
    # every exact match shares rank 1
    near = ranked.where(F.col("_rank") <= kappa)
    near = near.withColumn("_row", F.row_number().over(group.orderBy(F.desc("_s"), *tie))).where((F.col("_s") > 0) | (F.col("_row") <= kappa))
    near = near.withColumn("_top", F.max("_s").over(group))
    return near.where((F.col("_top") < 1 - epsilon) | (F.col("_s") >= 1 - epsilon)).withColumn("place", F.col("_row")).drop("_s", "_rank", "_row", "_top")


def number_candidates(pruned: DataFrame) -> DataFrame:
    """Adds ``no``, the candidate's number in its question."""
    return pruned.withColumn("no", F.row_number().over(Window.partitionBy("qid").orderBy("k", "place", "expr")) - 1)


_PICK = "struct<no:int,k:int,sigma:double,ways:double>"


def generate_configs(
    numbered: DataFrame, n_keywords: DataFrame, strategy: str = "exact", beam: int = 200, allow_partial: bool = False, max_configs: int = MAX_CONFIGS
) -> DataFrame:
    """(qid, picks): every way of taking one candidate per keyword, as an array of picks.

    ``beam`` keeps the best partial choices by similarity; so does ``exact`` for a question that
    would have more than ``max_configs``, which bounds what one row holds. Questions with a
    keyword that has no candidate get none unless ``allow_partial``.
    """
    ways = (F.col("ways") if "ways" in numbered.columns else F.lit(1)).cast("double").alias("ways")
    per_k = numbered.groupBy("qid", "k").agg(F.array_sort(F.collect_list(F.struct(F.col("no").cast("int").alias("no"), F.col("k").cast("int").alias("k"), "sigma", ways))).alias("options"))
    rows = per_k.groupBy("qid").agg(F.array_sort(F.collect_list(F.struct("k", "options"))).alias("ks")).join(n_keywords, "qid")
    if not allow_partial:
        rows = rows.where(F.size("ks") == F.col("n_keywords"))
    pick = f"array<{_PICK}>"
    width = beam if strategy == "beam" else max_configs

    def best(grown: Column) -> Column:
        keyed = F.transform(grown, lambda c: F.struct((-F.aggregate(c, F.lit(1.0), lambda s, o: s * o["sigma"])).alias("order"), c.alias("c")))
        return F.transform(F.slice(F.array_sort(keyed), 1, width), lambda x: x["c"])

    def extend(done: Column, k: Column) -> Column:
        grown = F.flatten(F.transform(done, lambda c: F.transform(k["options"], lambda o: F.concat(c, F.array(o.cast(_PICK))))))
        return F.transform(F.array(grown), lambda g: F.when(F.size(g) > width, best(g)).otherwise(g))[0]

    start = F.array(F.array().cast(pick))
    return rows.select("qid", F.explode(F.aggregate("ks", start.cast(f"array<{pick}>"), extend)).alias("picks"))


def similarity_score(picks: Column, mean: str = "geometric") -> Column:
    n = F.size(picks)
    if mean == "arithmetic":
        return F.aggregate(picks, F.lit(0.0), lambda s, p: s + p["sigma"]) / n
    product = F.aggregate(picks, F.lit(1.0), lambda s, p: s * p["sigma"])
    return F.pow(product, 1.0 / n)


def evidence(numbered: DataFrame, graph: qg.FragmentGraph, dice_floor: float = 0.0) -> DataFrame:
    """(qid, n_cands, dice, is_from): a row-major matrix of Dice between the candidates of each question.

    The diagonal is 1 for a fragment that was seen; equal fragments at different places
    use the count of statements that hold them twice.
    """
    side = numbered.select("qid", "no", "clause", "expr")
    pairs = side.select("qid", F.col("no").alias("i"), F.col("clause").alias("a_clause"), F.col("expr").alias("a_expr")).join(
        side.select("qid", F.col("no").alias("j"), F.col("clause").alias("b_clause"), F.col("expr").alias("b_expr")), "qid"
    )
    distinct = pairs.select("a_clause", "a_expr", "b_clause", "b_expr").distinct()
    looked = qg.dice(graph, distinct, dice_floor)
    seen = graph.vertices.select(F.col("clause").alias("a_clause"), F.col("expr").alias("a_expr"), F.lit(1.0).alias("seen"))
    full = pairs.join(looked, ["a_clause", "a_expr", "b_clause", "b_expr"]).join(seen, ["a_clause", "a_expr"], "left")
    cell = F.when(F.col("i") == F.col("j"), F.greatest(F.coalesce("seen", F.lit(0.0)), F.lit(dice_floor))).otherwise(F.col("dice"))
    matrix = full.groupBy("qid").agg(F.array_sort(F.collect_list(F.struct("i", "j", cell.alias("d")))).alias("cells"))
    flags = numbered.groupBy("qid").agg(F.count("*").cast("int").alias("n_cands"), F.array_sort(F.collect_list(F.struct("no", (F.col("clause") == "FROM").alias("f")))).alias("fs"))
    return matrix.join(flags, "qid").select("qid", "n_cands", F.col("cells.d").alias("dice"), F.col("fs.f").alias("is_from"))


def log_score(picks: Column, dice: Column, n_cands: Column, is_from: Column, scheme: str = SQUARE) -> Column:
    """Product of Dice over pairs of non-FROM picks, to the power 1 / number of picks."""
    own = F.filter(picks, lambda p: ~F.get(is_from, p["no"]))

    def row(a: Column, i: Column) -> Column:
        def cell(b: Column, j: Column) -> Column:
            d = F.get(dice, a["no"] * n_cands + b["no"])
            if scheme == SQUARE:
                return d
            return F.when(i == j, 1.0).otherwise(d) if scheme == ORDERED else F.when(i < j, d).otherwise(1.0)

        return F.aggregate(F.transform(own, cell), F.lit(1.0), lambda s, d: s * d)

    return F.pow(F.aggregate(F.transform(own, row), F.lit(1.0), lambda s, d: s * d), 1.0 / F.size(picks))


def combine(s: Column, q: Column, lam: float | Column = LAMBDA, how: str = "linear") -> Column:
    """Linear mixture, or Dempster's rule on the two scores as masses for and against."""
    if how == "linear":
        lam = lam if isinstance(lam, Column) else F.lit(float(lam))
        return lam * s + (1 - lam) * q
    conflict = s * (1 - q) + q * (1 - s)
    return F.when(conflict < 1, s * q / (1 - conflict)).otherwise(0.0)


def rank_configs(configs: DataFrame, by: tuple[str, ...] = ("qid",)) -> DataFrame:
    """Adds rank and tied (several share the first place, or one that can be bound in several ways) on ``score`` rounded to 12 places."""
    score = F.round("score", 12)
    group = Window.partitionBy(*by)
    ranked = configs.withColumn("rank", F.row_number().over(group.orderBy(F.desc(score), F.col("picks.no"))))
    place = F.rank().over(group.orderBy(F.desc(score)))
    ways = F.aggregate("picks", F.lit(1.0), lambda n, p: n * p["ways"])
    return ranked.withColumn("_p", place).withColumn("tied", F.sum(F.when(F.col("_p") == 1, ways).otherwise(0.0)).over(group) > 1).drop("_p")


def scored_configs(
    numbered: DataFrame, n_keywords: DataFrame, graph: qg.FragmentGraph | None, lam: float = LAMBDA, scheme: str = SQUARE, mean: str = "geometric",
    how: str = "linear", strategy: str = "exact", dice_floor: float = 0.0, allow_partial: bool = False,
) -> DataFrame:
    """(qid, picks, s_sigma, s_qfg, score); without a graph the log score is 0 and similarity alone counts."""
    configs = generate_configs(numbered, n_keywords, strategy, allow_partial=allow_partial).withColumn("s_sigma", similarity_score(F.col("picks"), mean))
    if graph is None:
        return configs.withColumns({"s_qfg": F.lit(0.0), "score": F.col("s_sigma")})
    found = configs.join(evidence(numbered, graph, dice_floor), "qid")
    found = found.withColumn("s_qfg", log_score(F.col("picks"), F.col("dice"), F.col("n_cands"), F.col("is_from"), scheme)).drop("dice", "n_cands", "is_from")
    return found.withColumn("score", combine(F.col("s_sigma"), F.col("s_qfg"), lam, how))


def score_frequency(numbered: DataFrame, configs: DataFrame, graph: qg.FragmentGraph, log_size: int) -> DataFrame:
    """The rejected boost: product of each fragment's share of the log."""
    share = numbered.join(graph.vertices, ["clause", "expr"], "left").select("qid", "no", (F.coalesce("n_v", F.lit(0)) / F.lit(log_size)).alias("share"))
    parts = configs.select("qid", "picks", F.explode("picks.no").alias("no")).join(share, ["qid", "no"])
    return parts.groupBy("qid", "picks").agg(F.product("share").alias("score"))


def score_whole_query(numbered: DataFrame, configs: DataFrame, statements: DataFrame) -> DataFrame:
    """The rejected retrieval: 1 if some statement has exactly these fragments outside FROM, else 0."""
    frags = configs.select("qid", "picks", F.explode("picks.no").alias("no")).join(numbered.select("qid", "no", "clause", "expr"), ["qid", "no"])
    asked = frags.where("clause <> 'FROM'").groupBy("qid", "picks").agg(F.array_sort(F.collect_list(F.struct("clause", "expr"))).alias("set"))
    known = statements.select(F.array_sort(F.filter("keys", lambda f: f["clause"] != "FROM")).alias("set")).distinct().withColumn("hit", F.lit(1.0))
    return asked.join(known, "set", "left").select("qid", "picks", F.coalesce("hit", F.lit(0.0)).alias("score"))


def score_mutual_relevance(numbered: DataFrame, configs: DataFrame, hops: DataFrame) -> DataFrame:
    """The predecessor's collective score: over pairs of picks, similarities times nearness in question and schema.

    ``hops`` (a, b, dist): key edges between relations, 0 for a relation with itself.
    """
    frags = configs.select("qid", "picks", F.explode("picks").alias("p")).select("qid", "picks", "p.no", "p.k", "p.sigma").join(numbered.select("qid", "no", "relation"), ["qid", "no"])
    a = frags.select("qid", "picks", F.col("k").alias("k1"), F.col("sigma").alias("s1"), F.col("relation").alias("a"))
    b = frags.select("qid", "picks", F.col("k").alias("k2"), F.col("sigma").alias("s2"), F.col("relation").alias("b"))
    pairs = a.join(b, ["qid", "picks"]).where("k1 < k2").join(F.broadcast(hops), ["a", "b"], "left")
    near = F.col("s1") * F.col("s2") / (F.abs(F.col("k2") - F.col("k1")) * (1 + F.coalesce("dist", F.lit(99))))
    base = frags.groupBy("qid", "picks").agg(F.avg("sigma").alias("own"))
    return base.join(pairs.groupBy("qid", "picks").agg(F.avg(near).alias("rel")), ["qid", "picks"], "left").select(
        "qid", "picks", (F.col("own") * (1 + F.coalesce("rel", F.lit(0.0)))).alias("score")
    )


def map_keywords(
    spark: SparkSession, sf_dir: str, questions: DataFrame, catalog: Catalog, qfg: qg.FragmentGraph | None, sim: SimilarityModel, kappa: int = KAPPA, lam: float = LAMBDA,
    level: str = fr.NOCONSTOP, epsilon: float = EPSILON, top: int | None = None, scored: DataFrame | None = None,
) -> tuple[DataFrame, DataFrame]:
    """Ranked configurations and the numbered candidates that they pick from."""
    scored = scored if scored is not None else score_candidates(keyword_candidates(spark, sf_dir, catalog, questions), sim, epsilon)
    slots = value_slot(scored.withColumn("expr", fragment_key(level)), level, qfg.vertices if qfg is not None else None)
    numbered = number_candidates(score_and_prune(collapse_values(slots, ("qid", "k", "clause", "slot")), kappa, epsilon, tie=("expr", "value")))
    n_keywords = questions.select("qid", F.size("keywords").alias("n_keywords"))
    ranked = rank_configs(scored_configs(numbered, n_keywords, qfg, lam))
    return (ranked if top is None else ranked.where(F.col("rank") <= top)), numbered
