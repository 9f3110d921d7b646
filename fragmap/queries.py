"""Registered queries of the log layer; each takes (spark, sf_dir)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from fragmap import catalog as cat
from fragmap.functions import similarity as sm
from fragmap.functions.stem import stem_tokens
from fragmap.operators import content_index as ci
from fragmap.operators import fragments as fr
from fragmap.operators import joins, mapping
from fragmap.operators import qfg as qg
from fragmap.operators import schema_graph as sg
from fragmap.plans import evaluate as ev
from fragmap.plans import hosts as hs
from fragmap.plans.lineage import cut
from fragmap.sources import logs
from fragmap.sources.questions import load_questions
from fragmap.streaming import logstream

_ALL = cat.given_catalog()


def _log(spark, sf):
    return logs.synth_log(spark, sf)


def _graph(spark, sf, level=fr.NOCONSTOP, mode=qg.STATEMENT):
    return qg.build_qfg(_log(spark, sf), _ALL, level, count_mode=mode)


# --- log and graph ---


def log_synth(spark, sf):
    log = _log(spark, sf)
    return log.groupBy((F.col("log_id") % 20).alias("template"), (F.col("log_id") % 3).alias("spelling")).agg(
        F.count("*").alias("n"), F.count_distinct("user_id").alias("users"), F.sum(F.col("sql").contains("SELECT").cast("bigint")).alias("upper_case")
    )


def log_templates(spark, sf):
    return fr.fold_templates(_log(spark, sf)).groupBy("n").agg(F.count("*").alias("templates"))


def _frags(level):
    def query(spark, sf):
        return qg.fragment_counts(fr.statement_fragments(_log(spark, sf), _ALL, level), qg.OCCURRENCE).select("clause", "expr", F.col("n_v").alias("n"))

    return query


def frag_parse_errors(spark, sf):
    """The log with a nested statement for every event whose id is 7 modulo 100."""
    nested = F.lit("SELECT p_name FROM part WHERE p_size > (SELECT avg(p_size) FROM part)")
    log = _log(spark, sf).withColumn("sql", F.when(F.col("log_id") % 100 == 7, nested).otherwise(F.col("sql")))
    return fr.parse_errors(log, _ALL).groupBy("error").agg(F.sum("n").alias("n"))


def frag_all_clauses(spark, sf):
    clauses = ("SELECT", "FROM", "WHERE", "GROUP BY", "HAVING", "ORDER BY")
    counts = qg.fragment_counts(fr.statement_fragments(_log(spark, sf), _ALL, clauses=clauses))
    return counts.where("clause in ('GROUP BY', 'HAVING', 'ORDER BY')")


def qfg_vertices(spark, sf):
    return _graph(spark, sf).vertices


def qfg_vertices_occurrence(spark, sf):
    return _graph(spark, sf, mode=qg.OCCURRENCE).vertices


def qfg_edges(spark, sf):
    return _graph(spark, sf).edges


def qfg_self_pairs(spark, sf):
    return _graph(spark, sf).edges.where("a_clause = b_clause and a_expr = b_expr").select("a_clause", "a_expr", "n_e")


def qfg_dice(spark, sf):
    return qg.edge_dice(_graph(spark, sf)).withColumn("dice", F.round("dice", 9))


def qfg_top_partners(spark, sf):
    return qg.top_partners(_graph(spark, sf))


def qfg_merge(spark, sf):
    log = _log(spark, sf)
    half = lambda k: qg.build_qfg(log.where(F.col("log_id") % 2 == k), _ALL)
    return half(0).merge(half(1)).vertices


def qfg_minus(spark, sf):
    log = _log(spark, sf)
    return qg.build_qfg(log, _ALL).minus(qg.build_qfg(log.where("log_id % 2 = 0"), _ALL)).vertices


def qfg_support_cut(spark, sf):
    """Fragments of at least a twentieth of the log, and edges between them."""
    least = cat.table(spark, sf, "events").count() // 20
    g = _graph(spark, sf).prune(2 * least, least)
    return g.edges


def qfg_clause_rollup(spark, sf):
    relation = F.regexp_extract("expr", r"(?:^|\()([a-z]+)(?:\.|$)", 1)
    v = qg.fragment_counts(fr.statement_fragments(_log(spark, sf), _ALL))
    return v.rollup("clause", relation.alias("relation")).agg(F.sum("n_v").alias("n_v"), F.grouping_id().cast("bigint").alias("gid"))


def _daily(spark, sf):
    log = _log(spark, sf).withColumn("day", F.to_date("ts"))
    return qg.fragment_counts(fr.statement_fragments(log, _ALL, by=("day",)), by=("day",))


def qfg_daily(spark, sf):
    return _daily(spark, sf).withColumn("day", F.col("day").cast("string"))


def qfg_sliding7(spark, sf):
    """Running count of each fragment over the seven days that end on each day it occurs."""
    number = F.datediff("day", F.lit("2024-01-01"))
    week = Window.partitionBy("clause", "expr").orderBy("number").rangeBetween(-6, 0)
    return _daily(spark, sf).withColumn("number", number).select(F.col("day").cast("string").alias("day"), "clause", "expr", F.sum("n_v").over(week).alias("n_week"))


def qfg_sessions(spark, sf):
    s = _log(spark, sf).groupBy("user_id", F.session_window("ts", "30 minutes")).agg(F.count("*").alias("n"))
    return s.groupBy("n").agg(F.count("*").alias("sessions"))


def qfg_stream_equals_batch(spark, sf):
    return logstream.count_stream(spark, sf, _ALL)


def qfg_as_of(spark, sf):
    """Graphs as they stood at three moments; only older statements count."""
    asked = spark.createDataFrame([("q1", "2024-01-05 12:00:00"), ("q2", "2024-01-15 00:00:00"), ("q3", "2024-01-29 18:30:00")], "qid string, at string")
    asked = asked.select("qid", F.to_timestamp("at").alias("asked_at"))
    return qg.graph_as_of(_log(spark, sf), _ALL, asked)


# --- candidates ---

_KEYWORDS = "qid string, keywords array<struct<text:string,clause:string,op:string,aggs:array<string>,grouped:boolean>>"


def _asked(spark, rows):
    return spark.createDataFrame([(q, [dict(text=t, clause=c, op=o, aggs=a, grouped=g) for t, c, o, a, g in ks]) for q, ks in rows], _KEYWORDS)


_TRADE = cat.given_catalog("trade")
_NUMBERS = [("n1", [("size over 45", "WHERE", ">", [], False)]), ("n2", [("price above 104000", "WHERE", ">", [], False)]), ("n3", [("discount under 0", "WHERE", "<", [], False)]), ("n4", [("size 7", "WHERE", None, [], False)])]


def _numeric(spark, sf, rows, year):
    kws = mapping.explode_keywords(_asked(spark, rows))
    found = mapping.numeric_candidates(spark, sf, _TRADE, kws, temporal_as_year=year)
    return found.select("qid", "relation", "attribute", "func", F.col("cmp").alias("op"), "num")


def cand_numeric(spark, sf):
    return _numeric(spark, sf, _NUMBERS, False)


def cand_numeric_year(spark, sf):
    return _numeric(spark, sf, [("y1", [("after 1998", "WHERE", ">", [], False)]), ("y2", [("in 1997", "WHERE", None, [], False)])], True)


def cand_relation(spark, sf):
    q = _asked(spark, [("r1", [("supplier", "FROM", None, [], False)]), ("r2", [("goods", "FROM", None, [], False)])])
    return mapping.keyword_candidates(spark, sf, _TRADE, q).select("qid", "clause", "relation")


def cand_select(spark, sf):
    q = _asked(spark, [("s1", [("orders", "SELECT", None, ["count", "max"], True)])])
    c = mapping.keyword_candidates(spark, sf, _TRADE, q).withColumn("expr", mapping.fragment_key(fr.NOCONSTOP))
    return c.select("qid", "relation", "attribute", "grouped", "expr")


def _text(spark, sf, rows, catalog=_TRADE):
    kws = mapping.explode_keywords(_asked(spark, rows))
    found = mapping.text_matches(spark, sf, catalog, kws)
    return kws.select("qid", "keyword").join(found, "keyword").select("qid", "relation", "attribute", F.col("value_id"), "value")


def cand_text(spark, sf):
    found = _text(spark, sf, [("t1", [("red widgets", "WHERE", None, [], False)]), ("t2", [("small", "WHERE", None, [], False)])])
    return found.select("qid", "relation", "attribute", "value")


def cand_text_namedrop(spark, sf):
    found = _text(spark, sf, [("d1", [("part small ring", "WHERE", None, [], False)]), ("d2", [("part", "WHERE", None, [], False)])])
    return found.select("qid", "relation", "attribute", "value")


def cand_text_corpus(spark, sf):
    """Matches in long texts too: how many distinct values of each attribute hold the words, and how many are short enough to be quoted."""
    found = _text(spark, sf, [("c1", [("system", "WHERE", None, [], False)]), ("c2", [("released license", "WHERE", None, [], False)]), ("c3", [("src1", "WHERE", None, [], False)])], cat.given_catalog("corpus"))
    return found.groupBy("qid", "relation", "attribute").agg(F.count("*").alias("values"), F.count("value").alias("quoted"))


def cand_text_bound(spark, sf):
    """The candidates that a keyword's matches become: a value bound late, with the number of values as good."""
    asked = _asked(spark, [("b1", [("small", "WHERE", None, [], False)]), ("b2", [("red", "WHERE", None, [], False)]), ("b3", [("NATION_1", "WHERE", None, [], False)])])
    scored = mapping.score_candidates(mapping.keyword_candidates(spark, sf, _TRADE, asked), sm.NgramSimilarity())
    best = mapping.collapse_values(scored.withColumn("expr", mapping.fragment_key(fr.NOCONSTOP)))
    return best.where("sigma = 1").select("qid", "expr", "value", "ways")


def numeric_profile(spark, sf):
    return ci.numeric_profile(spark, sf, _ALL, temporal_as_year=True)


def text_terms(spark, sf):
    t = ci.text_terms(ci.text_cells(spark, sf, _TRADE))
    return t.groupBy("relation", "attribute").agg(F.count_distinct("value_id").alias("values"), F.count_distinct("term").alias("terms"), F.count("*").alias("postings"))


def stem_tokens_query(spark, sf):
    words = spark.createDataFrame([(a.relation, a.name, list(a.words)) for a in _ALL.attributes], "relation string, attribute string, words array<string>")
    return words.select("relation", "attribute", F.array_join(stem_tokens(F.col("words")), " ").alias("stems"))


# --- similarity ---


def sim_ngram(spark, sf):
    """Dice of character trigrams between part names and brands' types."""
    p = cat.table(spark, sf, "part")
    names, types = p.select(F.lower("p_name").alias("a")).distinct(), p.select(F.lower("p_type").alias("b")).distinct()
    return names.join(types).select("a", "b", F.round(sm.ngram_similarity(F.col("a"), F.col("b")), 9).alias("sigma"), F.round(sm.ngram_similarity(F.col("a"), F.col("b"), 3, "jaccard"), 9).alias("jaccard"))


_PHRASES = [("vendor balance", "account balance supplier"), ("client", "market segment customer"), ("revenue", "extended price line item"), ("thing", "name part"), ("order date", "date order")]


def sim_lexicon(spark, sf):
    pairs = spark.createDataFrame([(a.split(), b.split()) for a, b in _PHRASES], "words array<string>, targets array<string>")
    plain = spark.createDataFrame([("vendor", "supplier", 0.9), ("client", "customer", 0.9), ("revenue", "price", 0.7)], "word string, synonym string, score double")
    return sm.LexiconSimilarity(plain).score(pairs).select(F.array_join("words", " ").alias("phrase"), F.array_join("targets", " ").alias("target"), "sigma")


def sim_vector(spark, sf):
    """Cosine of every vector with vector 0, rescaled to [0, 1]."""
    e = cat.table(spark, sf, "embeddings").select("vec_id", "embedding")
    first = e.where("vec_id = 0").select(F.col("embedding").alias("first"))
    return e.join(F.broadcast(first)).select("vec_id", F.round((sm.cosine(F.col("embedding"), F.col("first")) + 1) / 2, 6).alias("sigma"))


def sim_vector_words(spark, sf):
    """Word vectors trained on statements of the log and schema words, then a few phrase similarities."""
    folded = fr.fold_templates(_log(spark, sf)).select(sm.words_in(F.col("template")).alias("words"))
    schema = _ALL.frame(spark).select(F.concat("words", "relation_words").alias("words"))
    vectors = sm.train_vectors(folded.unionByName(schema), 16, 1)
    pairs = spark.createDataFrame([(["customer"], ["orders"]), (["part"], ["lineitem"])], "words array<string>, targets array<string>")
    return sm.VectorSimilarity(vectors).score(pairs).select(F.array_join("words", " ").alias("phrase"), F.array_join("targets", " ").alias("target"), "sigma")


def sim_numeric_eps(spark, sf):
    """Without the value prefilter a numeric candidate that no value satisfies keeps only epsilon."""
    asked = _asked(spark, _NUMBERS)
    every = mapping.keyword_candidates(spark, sf, _TRADE, asked, prefilter=False, temporal_as_year=False)
    scored = mapping.score_candidates(every, sm.NgramSimilarity())
    return scored.select("qid", "relation", "attribute", F.when(F.col("sigma") == mapping.EPSILON, mapping.EPSILON).otherwise(1.0).alias("factor"))


# --- pruning: candidates are parts, a group per brand ---


def _prune(kappa, sigma):
    def query(spark, sf):
        rows = cat.table(spark, sf, "part").select(F.col("p_brand").alias("qid"), F.lit(0).alias("k"), F.lpad(F.col("p_partkey").cast("string"), 8, "0").alias("expr"), sigma().alias("sigma"))
        return mapping.score_and_prune(rows, kappa).select("qid", "expr", "sigma", F.col("place").cast("bigint").alias("place"))

    return query


# --- configurations on the log's graph ---

#: Question, keyword number, clause, fragment, similarity.
CANDIDATES = [
    ("c1", 0, "SELECT", "part.p_name", 0.6), ("c1", 0, "SELECT", "supplier.s_name", 0.7), ("c1", 1, "WHERE", "nation.n_name ?op ?val", 0.9),
    ("c2", 0, "SELECT", "part.p_name", 0.6), ("c2", 1, "WHERE", "nation.n_name ?op ?val", 0.9), ("c2", 2, "FROM", "orders", 0.8), ("c2", 2, "FROM", "supplier", 0.4),
    ("c3", 0, "SELECT", "orders.o_orderkey", 0.7), ("c3", 1, "WHERE", "customer.c_mktsegment ?op ?val", 0.8), ("c3", 2, "WHERE", "orders.o_totalprice ?op ?val", 0.5), ("c3", 2, "WHERE", "supplier.s_acctbal ?op ?val", 0.6),
    ("c4", 0, "SELECT", "orders.o_orderkey", 0.7), ("c4", 1, "WHERE", "part.p_name ?op ?val", 0.9), ("c4", 2, "WHERE", "part.p_name ?op ?val", 0.9),
    ("c5", 0, "SELECT", "part.p_name", 0.6), ("c5", 0, "SELECT", "part.p_type", 0.65), ("c6", 0, "SELECT", "customer.c_name", 0.5), ("c6", 0, "SELECT", "events.value", 0.5),
]


def _numbered(spark):
    return _placed(spark.createDataFrame(CANDIDATES, "qid string, k int, clause string, expr string, sigma double"))


def _order_candidates(spark, sf):
    """Numbered candidates of the stored orders and the keywords of each question: a year asks for the priority of orders
    of each status; a priority is as similar as its share of them."""
    o = cat.table(spark, sf, "orders").select(
        F.year("o_orderdate").cast("string").alias("qid"), (F.instr(F.lit("FOP"), F.col("o_orderstatus")) - 1).alias("k"), F.col("o_orderpriority").alias("expr")
    )
    n = o.groupBy("qid", "k", "expr").agg(F.count("*").alias("n"))
    rows = n.select("qid", "k", F.lit("WHERE").alias("clause"), "expr", (F.col("n") / F.sum("n").over(Window.partitionBy("qid", "k"))).alias("sigma"))
    numbered = _placed(rows)
    return numbered, numbered.groupBy("qid").agg((F.max("k") + 1).alias("n_keywords"))


def _placed(rows):
    place = F.row_number().over(Window.partitionBy("qid", "k").orderBy(F.desc("sigma"), "expr"))
    return mapping.number_candidates(rows.withColumn("place", place))


def _label(numbered, configs):
    """Configurations named by their fragments in keyword order."""
    rows = configs.select("qid", "picks", F.posexplode("picks.no").alias("at", "no")).join(numbered.select("qid", "no", "expr"), ["qid", "no"])
    named = rows.groupBy("qid", "picks").agg(F.array_sort(F.collect_list(F.struct("at", "expr"))).alias("xs"))
    return configs.join(named.select("qid", "picks", F.array_join("xs.expr", " + ").alias("config")), ["qid", "picks"])


def _configs(spark, sf, **kw):
    numbered = _numbered(spark)
    n = numbered.groupBy("qid").agg((F.max("k") + 1).alias("n_keywords"))
    graph = _graph(spark, sf)
    return numbered, mapping.scored_configs(numbered, n, graph, **kw)


def cfg_all(spark, sf):
    numbered, n = _order_candidates(spark, sf)
    return _label(numbered, mapping.generate_configs(numbered, n)).select("qid", "config")


def cfg_beam(spark, sf):
    numbered, n = _order_candidates(spark, sf)
    return _label(numbered, mapping.generate_configs(numbered, n, "beam", 1)).select("qid", "config")


def _sigma(mean):
    def query(spark, sf):
        numbered, n = _order_candidates(spark, sf)
        c = _label(numbered, mapping.generate_configs(numbered, n))
        return c.select("qid", "config", F.round(mapping.similarity_score(F.col("picks"), mean), 9).alias("s_sigma"))

    return query


def _qfg_score(scheme):
    def query(spark, sf):
        numbered, c = _configs(spark, sf, scheme=scheme)
        return _label(numbered, c).select("qid", "config", F.round("s_qfg", 9).alias("s_qfg"))

    return query


def cfg_final(spark, sf):
    numbered, c = _configs(spark, sf)
    return _label(numbered, c).select("qid", "config", F.round("score", 9).alias("score"))


def cfg_dempster(spark, sf):
    numbered, c = _configs(spark, sf, how="dempster")
    return _label(numbered, c).select("qid", "config", F.round("score", 9).alias("score"))


def cfg_rank_ties(spark, sf):
    numbered, n = _order_candidates(spark, sf)
    ranked = mapping.rank_configs(mapping.scored_configs(numbered, n, None))
    return _label(numbered, ranked.where("rank = 1")).select("qid", F.round("score", 9).alias("score"), "tied")


def cfg_frequency(spark, sf):
    numbered, c = _configs(spark, sf)
    size = cat.table(spark, sf, "events").count()
    return _label(numbered, mapping.score_frequency(numbered, c, _graph(spark, sf), size)).select("qid", "config", F.round("score", 9).alias("score"))


def cfg_whole_query(spark, sf):
    numbered, c = _configs(spark, sf)
    st = fr.statement_fragments(_log(spark, sf), _ALL)
    return _label(numbered, mapping.score_whole_query(numbered, c, st)).select("qid", "config", "score")


def cfg_mutual_relevance(spark, sf):
    numbered, c = _configs(spark, sf)
    named = numbered.withColumn("relation", F.regexp_extract("expr", "^([a-z]+)", 1))
    score = mapping.score_mutual_relevance(named, c, hs.relation_hops(spark, _ALL))
    return _label(numbered, score).select("qid", "config", F.round("score", 9).alias("score"))


# --- joins ---

#: Bags of known elements.
BAGS = [
    ("A1", ["part", "nation"]), ("A2", ["orders", "nation"]), ("A3", ["supplier", "customer"]), ("A4", ["nation", "orders", "supplier"]), ("A5", ["part", "region"]),
    ("A6", ["events", "part"]), ("A7", ["documents", "pages"]), ("A8", ["orders"]),
]


def _bags(spark, rows=BAGS):
    return spark.createDataFrame(rows, "bag_id string, bag array<string>")


def _paths(spark, sf, weights, rows=BAGS, **kw):
    graph = _graph(spark, sf) if weights == "log" else None
    found = joins.infer_joins(_bags(spark, rows), _ALL, graph, weights, **kw)
    return found.select(
        "bag_id", F.array_join(F.array_sort("edges.edge_id"), " ").alias("path"), F.col("n_edges").cast("bigint").alias("n_edges"), F.round("total_w", 9).alias("total_w"), F.round("score", 9).alias("score"), "path_rank", "tied"
    )


def steiner_default(spark, sf):
    return _paths(spark, sf, "default").select("bag_id", "path", "n_edges", "total_w", "tied")


def steiner_log(spark, sf):
    return _paths(spark, sf, "log").select("bag_id", "path", "n_edges", "total_w", "tied")


def steiner_brute(spark, sf):
    return _paths(spark, sf, "log", method="brute").select("bag_id", "path", "n_edges", "total_w", "tied")


def steiner_mst(spark, sf):
    return _paths(spark, sf, "log", method="mst").select("bag_id", "path", "n_edges", "total_w")


def steiner_preset(spark, sf):
    return _paths(spark, sf, "preset", preset={"F3": 3.0}).select("bag_id", "path", "n_edges", "total_w")


def path_scores(spark, sf):
    return _paths(spark, sf, "log").select("bag_id", "path", "score")


def path_k_best(spark, sf):
    return _paths(spark, sf, "log", BAGS[:2] + BAGS[3:4], k_paths=2).where("path_rank <= 2").select("bag_id", "path", "path_rank", "total_w")


def path_rank_modes(spark, sf):
    """The first path of the two best under each way of ranking."""
    out = None
    for mode in joins.RANKS:
        p = _paths(spark, sf, "log", BAGS[:1], k_paths=2, rank_by=mode).where("path_rank = 1").select(F.lit(mode).alias("rank_by"), "bag_id", "path")
        out = p if out is None else out.unionByName(p)
    return out


def disconnected_bag(spark, sf):
    """Days of a user in the log whose relations no join path connects."""
    held = F.array(*[F.array(*[F.lit(r) for r in dict.fromkeys(x.split("#")[0] for x in t[1])]) for t in logs.TEMPLATES])
    day = F.concat_ws(":", F.col("user_id").cast("string"), F.date_format("ts", "yyyy-MM-dd"))
    bags = cat.table(spark, sf, "events").select(day.alias("bag_id"), F.explode(F.get(held, (F.col("event_id") % len(logs.TEMPLATES)).cast("int"))).alias("relation"))
    bags = cut(bags.groupBy("bag_id").agg(F.sort_array(F.collect_set("relation")).alias("bag")))
    found = joins.infer_joins(bags.select(F.array_join("bag", " ").alias("bag_id"), "bag").distinct(), _ALL, None, "default")
    lost = bags.join(F.broadcast(found.select(F.col("bag_id").alias("path_of")).distinct()), F.array_join("bag", " ") == F.col("path_of"), "left_anti")
    return lost.select("bag_id")


def bag_to_relations(spark, sf):
    """The attributes that each kind of statement in the log holds outside FROM, repeats kept, and their relations."""
    said = fr.statement_fragments(_log(spark, sf), _ALL)
    names = F.transform(F.filter("keys", lambda f: f["clause"] != "FROM"), lambda f: F.regexp_extract(f["expr"], r"([a-z]+\.[a-z_]+)", 1))
    bags = said.groupBy(F.array_sort(names).alias("bag")).agg(F.sum("n").alias("n"))
    relations = F.pandas_udf(lambda bag: bag.map(lambda b: " ".join(sg.relations_of(list(b)))), "string")
    return bags.select(F.array_join("bag", " ").alias("bag"), relations("bag").alias("relations"), "n")


def _held(spark, sf):
    """(name, n): rows of each relation and values of each attribute that the tables hold, one aggregation per table."""
    out = None
    for relation in _ALL.relations:
        names = [a.name for a in _ALL.of(relation)]
        counts = cat.table(spark, sf, relation).agg(F.count("*").alias("n"), *[F.count(c).alias(f"n_{c}") for c in names])
        cells = [F.struct(F.lit(relation).alias("name"), F.col("n").alias("n"))] + [F.struct(F.lit(f"{relation}.{c}").alias("name"), F.col(f"n_{c}").alias("n")) for c in names]
        rows = counts.select(F.inline(F.array(*cells)))
        out = rows if out is None else out.unionByName(rows)
    return out


def graph_vertices(spark, sf):
    """Vertices of the schema graph with the rows or values stored for each."""
    v = sg.build_schema_graph(_ALL).frames(spark)[0]
    return v.join(_held(spark, sf), v["vid"] == F.col("name")).select("vid", "kind", "relation", "n")


def graph_edges(spark, sf):
    """Edges of the schema graph with the values stored in the attribute that is projected or refers."""
    e = sg.build_schema_graph(_ALL).frames(spark)[1]
    return e.join(_held(spark, sf), F.when(F.col("kind") == sg.KEY, F.col("src")).otherwise(F.col("dst")) == F.col("name")).select("src", "dst", "kind", "n")


def key_check(spark, sf):
    return cat.check_keys(spark, sf, _ALL)


def relgraph_default(spark, sf):
    rows = [(i, a, b, w) for i, a, b, _, _, w in sg.default_weights(sg.build_schema_graph(_ALL)).contracted()]
    return spark.createDataFrame(rows, "edge_id string, fk_relation string, pk_relation string, w double")


def relgraph_log(spark, sf):
    g = sg.log_weights(sg.build_schema_graph(_ALL), _graph(spark, sf))
    rows = [(i, a, b, round(w, 9)) for i, a, b, _, _, w in g.contracted()]
    return spark.createDataFrame(rows, "edge_id string, fk_relation string, pk_relation string, w double")


def paths_two_terminal(spark, sf):
    """All simple paths between part and nation, by recursion in SQL."""
    rows = [(i, a, b) for i, a, b, *_ in sg.build_schema_graph(_ALL).contracted()]
    e = spark.createDataFrame(rows, "edge_id string, a string, b string")
    both = e.unionByName(e.select("edge_id", F.col("b").alias("a"), F.col("a").alias("b")))
    both.createOrReplaceTempView("fragmap_key_edges")
    return spark.sql(
        """WITH RECURSIVE walk(at, seen, path, n) AS (
             SELECT 'part', array('part'), array(cast(null as string)), 0
             UNION ALL
             SELECT e.b, array_append(w.seen, e.b), array_append(w.path, e.edge_id), w.n + 1
             FROM walk w JOIN fragmap_key_edges e ON e.a = w.at WHERE NOT array_contains(w.seen, e.b) AND w.at <> 'nation')
           SELECT array_join(array_sort(filter(path, x -> x is not null)), ' ') AS path, cast(n as bigint) AS n_edges FROM walk WHERE at = 'nation'"""
    )


_FORKS = [("trade", "part.p_name"), ("corpus", "labels.quality"), ("corpus", "documents.lang"), ("trade", "orders.o_orderstatus"), ("trade", "customer.c_name"), ("activity", "events.event_type"), ("trade", "nation.n_name")]


def _forked(mode):
    for benchmark, start in _FORKS:
        yield start, sg.fork(sg.build_schema_graph(cat.given_catalog(benchmark)), start, 1, mode)


def fork_vertices(spark, sf):
    """Relations that a fork copies, with the rows stored for each."""
    rows = [(s, v.split("#")[0]) for s, g in _forked(sg.PUBLISHED) for v in g.vertices if "#" in v and "." not in v]
    cloned = spark.createDataFrame(rows, "start string, cloned string")
    return cloned.join(_held(spark, sf), F.col("cloned") == F.col("name")).select("start", "cloned", "n")


def _fork_edges(mode):
    """Key edges of the copies, with the values stored in the key that refers."""

    def query(spark, sf):
        rows = [(s, a, b) for s, g in _forked(mode) for a, b, kind, _ in g.edges if kind == sg.KEY and "#" in a]
        edges = spark.createDataFrame(rows, "start string, fk string, pk string")
        return edges.join(_held(spark, sf), F.regexp_replace("fk", "#[0-9]+", "") == F.col("name")).select("start", "fk", "pk", "n")

    return query


def fork_self_join_path(spark, sf):
    bags = [("S1", ["orders.o_orderkey", "part.p_name", "part.p_name"]), ("S2", ["part.p_name", "part.p_name"])]
    return _paths(spark, sf, "log", bags).select("bag_id", "path", "n_edges", "total_w", "score")


# --- translation and measures ---


def _translate(host):
    def query(spark, sf):
        own = host()
        found = ev.Experiment(spark, sf, noises=(own.noise,)).answers(own)
        return found.select("qid", "benchmark", "sql", F.round("score", 9).alias("score"), "tied", "path_tied")

    return query


def flagship(spark: SparkSession, sf: str) -> DataFrame:
    """Questions of ``trade`` through the vector-pipeline host with the log layer: top SQL and score."""
    return _translate(lambda: hs.vector_pipeline_host("H2", log_layer=True))(spark, sf).where("benchmark = 'trade'")


_GENERATED: dict[tuple[str, str], dict[str, str]] = {}


def _generated(spark, sf) -> dict[str, str]:
    """SQL that the vector-pipeline host with the log layer builds for the first question of each template, made once a session."""
    key = (spark.sparkContext.applicationId, sf)
    if key not in _GENERATED:
        x = ev.Experiment(spark, sf, only=[f"{t}-00" for t in RUN_TEMPLATES])
        rows = x.answers(hs.vector_pipeline_host("H2", log_layer=True)).select("qid", "sql").collect()
        _GENERATED[key] = {r["qid"]: r["sql"] for r in rows}
    return _GENERATED[key]


def _run(template):
    """Executes the SQL that the host builds for the first question of a template from its keywords: mapping, join path and all."""

    def query(spark, sf):
        sql = _generated(spark, sf).get(f"{template}-00")
        if sql is None:  # no mapping or no path: no answer
            return spark.createDataFrame([], "c0 string")
        ev.register_tables(spark, sf)
        return ev.rounded(spark.sql(sql))

    return query


def translation_report(spark, sf):
    """For the first question of each template: whether the built SQL is the gold SQL and returns its rows."""
    return ev.translation_report(spark, sf, hs.vector_pipeline_host("H2", log_layer=True), [f"{t}-00" for t in RUN_TEMPLATES])


def bench_stats(spark, sf):
    return ev.benchmark_stats(spark, sf)


def folds(spark, sf):
    q = ev.assign_folds(load_questions(spark, sf))
    return q.groupBy("benchmark", "fold").agg(F.count("*").alias("n"))


#: Published accuracies without and with a change, and the printed gains.
PUBLISHED = [
    ("fq_vp", "biblio", 32.0, 76.3), ("fq_vp", "reviews", 54.3, 85.0), ("fq_vp", "movies", 27.3, 64.8), ("fq_pt", "biblio", 33.0, 40.2), ("fq_pt", "reviews", 47.2, 52.8), ("fq_pt", "movies", 38.3, 50.0),
    ("kw_vp", "biblio", 39.7, 77.8), ("kw_vp", "reviews", 56.7, 85.0), ("kw_vp", "movies", 32.0, 67.2), ("kw_pt", "biblio", 43.3, 45.4), ("kw_pt", "reviews", 52.8, 59.8), ("kw_pt", "movies", 40.6, 57.8),
    ("fq_joins", "biblio", 68.6, 76.3), ("fq_joins", "reviews", 68.5, 85.0), ("fq_joins", "movies", 60.9, 64.8),
]


def published_improvements(spark, sf):
    rows = spark.createDataFrame(PUBLISHED, "measure string, benchmark string, base double, changed double")
    return rows.select("measure", "benchmark", ev.improvement(F.col("base"), F.col("changed")).alias("gain_pct"))


def candidate_counts(spark, sf):
    """Cost counters of a batch: candidates, configurations and distinct log lookups per benchmark."""
    x = ev.Experiment(spark, sf)
    ranked, numbered = hs.configurations(spark, x.scored, x.questions, hs.vector_pipeline_host("H2", log_layer=True), x.graph)
    of = x.questions.select("qid", "benchmark")
    c = x.scored.join(of, "qid").groupBy("benchmark").agg(F.count("*").alias("candidates"))
    k = numbered.join(of, "qid").groupBy("benchmark").agg(F.count("*").alias("kept"), F.count_distinct("clause", "expr").alias("fragments"))
    n = ranked.join(of, "qid").groupBy("benchmark").agg(F.count("*").alias("configurations"))
    return c.join(k, "benchmark").join(n, "benchmark")


RUN_TEMPLATES = ["T01", "T02", "T03", "T04", "T05", "T06", "T07", "T08", "T09", "T10", "T11", "T12", "T13", "T14", "T15", "T16", "T17", "T18", "V01", "V02", "V03", "V04", "V05", "V06", "V07", "V08", "D01", "D02", "D03", "D04", "D05", "D06", "D07", "D08"]

QUERIES = {
    "log_synth": log_synth, "log_templates": log_templates, "frag_full": _frags(fr.FULL), "frag_noconst": _frags(fr.NOCONST), "frag_noconstop": _frags(fr.NOCONSTOP),
    "frag_parse_errors": frag_parse_errors, "frag_all_clauses": frag_all_clauses, "qfg_vertices": qfg_vertices, "qfg_vertices_occurrence": qfg_vertices_occurrence, "qfg_edges": qfg_edges,
    "qfg_self_pairs": qfg_self_pairs, "qfg_dice": qfg_dice, "qfg_top_partners": qfg_top_partners, "qfg_merge": qfg_merge, "qfg_minus": qfg_minus, "qfg_support_cut": qfg_support_cut,
    "qfg_clause_rollup": qfg_clause_rollup, "qfg_daily": qfg_daily, "qfg_sliding7": qfg_sliding7, "qfg_sessions": qfg_sessions, "qfg_stream_equals_batch": qfg_stream_equals_batch, "qfg_as_of": qfg_as_of,
    "cand_numeric": cand_numeric, "cand_numeric_year": cand_numeric_year, "cand_relation": cand_relation, "cand_select": cand_select, "cand_text": cand_text, "cand_text_namedrop": cand_text_namedrop, "cand_text_corpus": cand_text_corpus, "cand_text_bound": cand_text_bound,
    "numeric_profile": numeric_profile, "text_terms": text_terms, "stem_tokens": stem_tokens_query, "sim_ngram": sim_ngram, "sim_lexicon": sim_lexicon, "sim_vector": sim_vector,
    "sim_vector_words": sim_vector_words, "sim_numeric_eps": sim_numeric_eps,
    "prune_exact": _prune(5, lambda: F.col("p_size") / 49.0), "prune_kappa": _prune(3, lambda: F.round(F.col("p_retailprice") / 10000, 6)), "prune_kappa_ties": _prune(5, lambda: F.col("p_size") / 100.0),
    "prune_zero_ties": _prune(5, lambda: F.when(F.col("p_partkey") % 40 == 0, 0.5).otherwise(0.0)),
    "cfg_all": cfg_all, "cfg_beam": cfg_beam, "cfg_sigma_geo": _sigma("geometric"), "cfg_sigma_arith": _sigma("arithmetic"), "cfg_qfg_square": _qfg_score(mapping.SQUARE), "cfg_qfg_ordered": _qfg_score(mapping.ORDERED),
    "cfg_qfg_unordered": _qfg_score(mapping.UNORDERED), "cfg_final": cfg_final, "cfg_rank_ties": cfg_rank_ties, "cfg_dempster": cfg_dempster, "cfg_mutual_relevance": cfg_mutual_relevance,
    "cfg_frequency": cfg_frequency, "cfg_whole_query": cfg_whole_query,
    "graph_vertices": graph_vertices, "graph_edges": graph_edges, "key_check": key_check, "relgraph_default": relgraph_default, "relgraph_log": relgraph_log, "paths_two_terminal": paths_two_terminal,
    "steiner_default": steiner_default, "steiner_log": steiner_log, "steiner_brute": steiner_brute, "steiner_mst": steiner_mst, "steiner_preset": steiner_preset, "path_scores": path_scores, "path_k_best": path_k_best,
    "path_rank_modes": path_rank_modes, "fork_vertices": fork_vertices, "fork_edges": _fork_edges(sg.PUBLISHED), "fork_edges_closure": _fork_edges(sg.CLOSURE), "fork_self_join_path": fork_self_join_path,
    "bag_to_relations": bag_to_relations, "disconnected_bag": disconnected_bag,
    "translate_h1": _translate(lambda: hs.vector_pipeline_host("H1")), "translate_h2": _translate(lambda: hs.vector_pipeline_host("H2", log_layer=True)),
    "translate_h3": _translate(lambda: hs.parse_tree_host("H3")), "translate_h4": _translate(lambda: hs.parse_tree_host("H4", log_layer=True)),
    "translation_report": translation_report, "bench_stats": bench_stats, "folds": folds, "published_improvements": published_improvements, "candidate_counts": candidate_counts,
    "main_table": ev.run_main_table, "join_ablation": ev.run_join_ablation, "kappa_sweep": ev.run_kappa_sweep, "lambda_sweep": ev.run_lambda_sweep, "level_sweep": ev.run_level_sweep,
    "template_split": ev.run_template_split, "log_fraction": ev.run_log_fraction,
} | {f"run_{t.lower()}": _run(t) for t in RUN_TEMPLATES}
