"""Questions over the given tables with hand-parsed keywords and gold mappings."""

from __future__ import annotations

from itertools import combinations, product

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fragmap.catalog import given_catalog, table
from fragmap.operators import schema_graph as sg
from fragmap.plans import sqlgen
from fragmap.sources.logs import REGIONS, SEGMENTS

FRAG = "k int, clause string, relation string, attribute string, func string, aggs array<string>, grouped boolean, op string, value string, numeric boolean"
SCHEMA = (
    "qid string, benchmark string, template string, text string, text_rewritten string, "
    "keywords array<struct<text:string,clause:string,op:string,aggs:array<string>,grouped:boolean>>, "
    f"gold array<struct<{FRAG.replace(' ', ':').replace(',:', ',')}>>, gold_edges array<string>, gold_sql string, excluded boolean"
)
#: Slot values in key or alphabetical order.
_NATIONS = [f"NATION_{i}" for i in range(25)]
_CUSTOMERS = [f"Customer#{i:09d}" for i in range(20)]
_BRANDS = [f"Brand#{i}" for i in range(1, 26)]
_TYPES = ["ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD"]
_PRIORITIES = ["1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"]
_PARTS = [f"{a} {b}" for a in ("blue", "cold", "hot", "new", "old", "red") for b in ("anvil", "bolt", "ring", "rod", "widget")]
_EVENTS = ["click", "error", "purchase", "signup", "view"]
_SOURCES = [f"src{i}" for i in range(20)]
_LANGS = ["de", "en", "es", "fr"]


def _q(text, clause, op=None, aggs=(), grouped=False):
    return (text, clause, op, list(aggs), grouped)


def _s(key, aggs=(), grouped=False):
    return ("SELECT", key, "", list(aggs), grouped, "", None, False)


def _w(key, op, value, numeric=False, func=""):
    return ("WHERE", key, func, [], False, op, str(value), numeric)


#: Question, keywords, gold mappings, gold join edges (clones with a mark), slot rows.
def _templates(page_words: list[str]):
    rows = lambda *cols: [tuple(r) for r in cols[0]] if len(cols) == 1 else list(zip(*cols))
    one = lambda xs: [(x,) for x in xs]
    return {
        "trade": {
            "T01": (lambda n: (f"parts ordered from {n}", [_q("parts", "SELECT"), _q(n, "WHERE")], [_s("part.p_name"), _w("nation.n_name", "=", n)], "F6 F5 F4 F2"), one(_NATIONS[:20])),
            "T02": (lambda n: (f"items supplied out of {n}", [_q("items", "SELECT"), _q(n, "WHERE")], [_s("part.p_name"), _w("nation.n_name", "=", n)], "F6 F7 F3"), one(_NATIONS[:12])),
            "T03": (lambda y: (f"orders after {y}", [_q("orders", "SELECT"), _q(f"after {y}", "WHERE", ">")], [_s("orders.o_orderkey"), _w("orders.o_orderdate", ">", y, True, "year")], ""), one(range(1996, 2001))),
            "T04": (lambda r: (f"customers in {r}", [_q("customers", "SELECT"), _q(r, "WHERE")], [_s("customer.c_name"), _w("region.r_name", "=", r)], "F2 F1"), one(REGIONS)),
            "T05": (lambda n: (f"vendors with balance over {n}", [_q("vendors", "SELECT"), _q(f"balance over {n}", "WHERE", ">")], [_s("supplier.s_name"), _w("supplier.s_acctbal", ">", n, True)], ""), one(range(500, 6500, 500))),
            "T06": (lambda s, n: (f"orders of {s} clients above {n}", [_q("orders", "SELECT"), _q(s, "WHERE"), _q(f"price above {n}", "WHERE", ">")],
                    [_s("orders.o_orderkey"), _w("customer.c_mktsegment", "=", s), _w("orders.o_totalprice", ">", n, True)], "F4"), list(product(SEGMENTS, (100000, 200000, 300000)))),
            "T07": (lambda: ("number of orders per segment", [_q("orders", "SELECT", None, ["count"]), _q("segment", "SELECT", None, [], True)], [_s("orders.o_orderkey", ["count"]), _s("customer.c_mktsegment", [], True)], "F4"), [()]),
            "T08": (lambda: ("revenue of small parts by brand", [_q("revenue", "SELECT", None, ["sum"]), _q("small", "WHERE"), _q("brand", "SELECT", None, [], True)],
                    [_s("lineitem.l_extendedprice", ["sum"]), _w("part.p_type", "=", "SMALL"), _s("part.p_brand", [], True)], "F6"), [()]),
            "T09": (lambda a, b: (f"orders containing both {a} and {b}", [_q("orders", "SELECT"), _q(a, "WHERE"), _q(b, "WHERE")],
                    [_s("orders.o_orderkey"), _w("part.p_name", "=", a), _w("part.p_name", "=", b)], "F5 F5 F6 F6"), list(combinations(_PARTS, 2))[:20]),
            "T10": (lambda c: (f"suppliers that served {c}", [_q("suppliers", "SELECT"), _q(c, "WHERE")], [_s("supplier.s_name"), _w("customer.c_name", "=", c)], "F7 F5 F4"), one(_CUSTOMERS[:15])),
            "T11": (lambda b, n: (f"names of {b} products with size over {n}", [_q("names", "SELECT"), _q(b, "WHERE"), _q(f"size over {n}", "WHERE", ">")],
                    [_s("part.p_name"), _w("part.p_brand", "=", b), _w("part.p_size", ">", n, True)], ""), [(b, 10 + i) for i, b in enumerate(_BRANDS[:20])]),
            "T12": (lambda p, c: (f"{p} orders by {c}", [_q("orders", "SELECT"), _q(p, "WHERE"), _q(c, "WHERE")],
                    [_s("orders.o_orderkey"), _w("orders.o_orderpriority", "=", p), _w("customer.c_name", "=", c)], "F4"), list(product(_PRIORITIES, _CUSTOMERS[:4]))),
            "T13": (lambda t: (f"average discount on {t} parts", [_q("discount", "SELECT", None, ["avg"]), _q(t, "WHERE")], [_s("lineitem.l_discount", ["avg"]), _w("part.p_type", "=", t)], "F6"), one(_TYPES)),
            "T14": (lambda p: (f"nations of suppliers of {p}", [_q("nations", "SELECT"), _q("supplier", "FROM"), _q(p, "WHERE")], [_s("nation.n_name"), ("FROM", "supplier", "", [], False, "", None, False), _w("part.p_name", "=", p)], "F3 F7 F6"), one(_PARTS[:15])),
            "T15": (lambda: ("most orders any segment has", [_q("orders", "SELECT", None, ["count", "max"]), _q("segment", "SELECT", None, [], True)], [_s("orders.o_orderkey", ["count", "max"]), _s("customer.c_mktsegment", [], True)], "F4"), [()]),
            "T16": (lambda p: (f"part {p} price", [_q("price", "SELECT"), _q(f"part {p}", "WHERE")], [_s("part.p_retailprice"), _w("part.p_name", "=", p)], ""), one(_PARTS[:15])),
            "T17": (lambda r: (f"shipped quantity to {r}", [_q("quantity", "SELECT", None, ["sum"]), _q(r, "WHERE")], [_s("lineitem.l_quantity", ["sum"]), _w("region.r_name", "=", r)], "F5 F4 F2 F1"), one(REGIONS)),
            "T18": (lambda n: (f"returned lines cheaper than {n}", [_q("lines", "SELECT"), _q("returned", "WHERE"), _q(f"cheaper than {n}", "WHERE", "<")],
                    [_s("lineitem.l_orderkey"), _w("lineitem.l_returnflag", "=", "R"), _w("lineitem.l_extendedprice", "<", n, True)], ""), one(range(2000, 14000, 2000))),
        },
        "activity": {
            "V01": (lambda e, n: (f"{e}s over {n}", [_q("value", "SELECT"), _q(e, "WHERE"), _q(f"over {n}", "WHERE", ">")], [_s("events.value"), _w("events.event_type", "=", e), _w("events.value", ">", n, True)], ""), list(product(_EVENTS, (5, 10, 20, 40, 60, 80)))[:28]),
            "V02": (lambda e: (f"clients with {e}s", [_q("clients", "SELECT"), _q(e, "WHERE")], [_s("customer.c_name"), _w("events.event_type", "=", e)], "F8"), one(_EVENTS)),
            "V03": (lambda: ("mean amount per action", [_q("amount", "SELECT", None, ["avg"]), _q("action", "SELECT", None, [], True)], [_s("events.value", ["avg"]), _s("events.event_type", [], True)], ""), [()]),
            "V04": (lambda n: (f"actions by users of {n}", [_q("actions", "SELECT"), _q(n, "WHERE")], [_s("events.event_type"), _w("nation.n_name", "=", n)], "F8 F2"), one(_NATIONS)),
            "V05": (lambda e, r: (f"how many {e}s in {r}", [_q("events", "SELECT", None, ["count"]), _q(e, "WHERE"), _q(r, "WHERE")], [_s("events.event_id", ["count"]), _w("events.event_type", "=", e), _w("region.r_name", "=", r)], "F8 F2 F1"), list(product(_EVENTS, REGIONS))),
            "V06": (lambda e: (f"segments of visitors who {e}", [_q("segments", "SELECT"), _q(e, "WHERE")], [_s("customer.c_mktsegment"), _w("events.event_type", "=", e)], "F8"), one(_EVENTS)),
            "V07": (lambda a, b: (f"users having both a {a} and a {b}", [_q("users", "SELECT"), _q(a, "WHERE"), _q(b, "WHERE")], [_s("customer.c_name"), _w("events.event_type", "=", a), _w("events.event_type", "=", b)], "F8 F8"), list(combinations(_EVENTS, 2))),
            "V08": (lambda s, n: (f"balance of {s} customers with value under {n}", [_q("balance", "SELECT"), _q(s, "WHERE"), _q(f"value under {n}", "WHERE", "<")], [_s("customer.c_acctbal"), _w("customer.c_mktsegment", "=", s), _w("events.value", "<", n, True)], "F8"), list(product(SEGMENTS, (2, 5, 10, 20, 40, 80)))[:28]),
        },
        "corpus": {
            "D01": (lambda q: (f"sources of documents of quality {q}", [_q("sources", "SELECT"), _q(f"quality {q}", "WHERE", "=")], [_s("documents.source"), _w("labels.quality", "=", q, True)], "F9"), one((0, 1))),
            "D02": (lambda: ("documents per language", [_q("documents", "SELECT", None, ["count"]), _q("language", "SELECT", None, [], True)], [_s("documents.doc_id", ["count"]), _s("documents.lang", [], True)], ""), [()]),
            "D03": (lambda x, s: (f"texts with toxic {x} from {s}", [_q("texts", "SELECT"), _q(f"toxic {x}", "WHERE", "="), _q(s, "WHERE")], [_s("documents.text"), _w("labels.toxic", "=", x, True), _w("documents.source", "=", s)], "F9"), list(product((0, 1), _SOURCES))),
            "D04": (lambda g, n: (f"articles longer than {n} in {g}", [_q("articles", "SELECT"), _q(f"longer than {n}", "WHERE", ">"), _q(g, "WHERE")], [_s("documents.text"), _w("documents.n_chars", ">", n, True), _w("documents.lang", "=", g)], ""), list(product(_LANGS, range(500, 4500, 500)))),
            "D05": (lambda r: (f"messages by the {r}", [_q("messages", "SELECT"), _q(r, "WHERE")], [_s("conversations.text"), _w("conversations.role", "=", r)], ""), one(("assistant", "system", "user"))),
            "D06": (lambda w: (f"addresses of pages mentioning {w}", [_q("addresses", "SELECT"), _q(w, "WHERE")], [_s("pages.url"), _w("pages.html", "=", w)], ""), one(page_words)),
            "D07": (lambda n: (f"vectors labelled {n}", [_q("vectors", "SELECT"), _q(f"label {n}", "WHERE", "=")], [_s("embeddings.vec_id"), _w("embeddings.label", "=", n, True)], ""), one(range(10))),
            "D08": (lambda x: (f"average length by source of documents with toxic {x}", [_q("length", "SELECT", None, ["avg"]), _q("source", "SELECT", None, [], True), _q(f"toxic {x}", "WHERE", "=")],
                    [_s("documents.n_chars", ["avg"]), _s("documents.source", [], True), _w("labels.toxic", "=", x, True)], "F9"), one((0, 1))),
        },
    }


#: Questions that are nested or ambiguous, kept apart.
_EXCLUDED = [
    ("trade", "customers above the average of their nation"), ("trade", "parts priced over the mean of their brand"), ("activity", "users more active than their nation"),
    ("corpus", "the best pages"), ("corpus", "long things about the language"), ("corpus", "texts like the others"),
]


def frequent_page_words(spark: SparkSession, sf_dir: str, n: int = 38) -> list[str]:
    """The most frequent words of page texts of four letters or more outside markup, ties by word."""
    text = F.regexp_replace(F.regexp_replace(F.lower("html"), "<script>.*?</script>|<style>.*?</style>", " "), "<[^>]*>", " ")
    words = table(spark, sf_dir, "pages").select(F.explode(F.split(text, "[^a-z]+")).alias("w")).where(F.length("w") >= 4)
    return [r["w"] for r in words.groupBy("w").count().orderBy(F.desc("count"), "w").limit(n).collect()]


def gold_path(benchmark: str, frags: list[dict], edge_ids: list[str]) -> tuple[list[str], list[dict]]:
    """Vertices and edges of the gold join path: the tree with these key edges on the forked graph."""
    from fragmap.operators import steiner

    catalog = given_catalog(benchmark)
    keys = {r: catalog.primary_key(r) or "" for r in catalog.relations}
    graph, terminals = sg.fork_for_bag(sg.build_schema_graph(catalog), sqlgen.bag_of(frags), keys)
    edges = [e for e in graph.contracted() if e[0] in edge_ids]
    if not edge_ids:
        return sorted(terminals), []
    trees = steiner.exact([(i, a, b, w) for i, a, b, _, _, w in edges], terminals)
    own = [edges[i] for i in sorted(trees[0])]
    return sorted({v for e in own for v in e[1:3]}), [{"edge_id": e[0], "fk": e[3], "pk": e[4]} for e in own]


def question_rows(page_words: list[str], include_excluded: bool = False) -> list[tuple]:
    out = []
    for benchmark, templates in _templates(page_words).items():
        for name, (make, slots) in templates.items():
            for i, values in enumerate(slots):
                text, keywords, gold, joins = make(*values)
                frags = []
                for k, (clause, key, func, aggs, grouped, op, value, numeric) in enumerate(gold):
                    relation, _, attribute = key.partition(".")
                    frags.append(dict(k=k, clause=clause, relation=relation, attribute=attribute, func=func, aggs=aggs, grouped=grouped, op=op, value=value, numeric=numeric))
                vertices, edges = gold_path(benchmark, frags, joins.split())
                words = [dict(zip(("text", "clause", "op", "aggs", "grouped"), k)) for k in keywords]
                sql = sqlgen.build_sql(frags, vertices, edges)
                out.append((f"{name}-{i:02d}", benchmark, name, text, f"return {text}", words, frags, sorted(joins.split()), sql, False))
    if include_excluded:
        out += [(f"X{i}", b, "excluded", t, t, [], [], [], None, True) for i, (b, t) in enumerate(_EXCLUDED)]
    return out


def load_questions(spark: SparkSession, sf_dir: str, include_excluded: bool = False) -> DataFrame:
    rows = question_rows(frequent_page_words(spark, sf_dir), include_excluded)
    return spark.createDataFrame([tuple(r) for r in rows], SCHEMA)
