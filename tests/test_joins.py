import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from fragmap.catalog import given_catalog
from fragmap.operators import joins, steiner
from fragmap.operators import schema_graph as sg
from fragmap.plans import sqlgen

EDGES = [("F1", "nation", "region", 5 / 7), ("F2", "customer", "nation", 3 / 8), ("F3", "supplier", "nation", 4 / 5), ("F4", "orders", "customer", 3 / 19), ("F5", "lineitem", "orders", 5 / 17), ("F6", "lineitem", "part", 1 / 8), ("F7", "lineitem", "supplier", 2 / 3)]
NODES = sorted({n for e in EDGES for n in e[1:3]})


def names(trees, edges=EDGES):
    return [sorted(edges[i][0] for i in t) for t in trees]


def test_log_weights_choose_the_longer_route():
    assert names(steiner.exact(EDGES, ["part", "nation"])) == [["F2", "F4", "F5", "F6"]]
    assert names(steiner.exact([(i, a, b, 1.0) for i, a, b, _ in EDGES], ["part", "nation"])) == [["F3", "F6", "F7"]]


def test_ties_are_all_found():
    unit = [(i, a, b, 1.0) for i, a, b, _ in EDGES]
    assert names(steiner.exact(unit, ["nation", "orders", "supplier"])) == [["F2", "F3", "F4"], ["F3", "F5", "F7"]]


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 5), min_size=7, max_size=7), st.sets(st.sampled_from(NODES), min_size=1, max_size=4))
def test_exact_equals_brute_force(weights, terminals):
    edges = [(i, a, b, float(w)) for (i, a, b, _), w in zip(EDGES, weights)]
    exact, brute = steiner.exact(edges, list(terminals)), steiner.brute(edges, list(terminals))
    assert names(exact, edges) == names(brute, edges)
    mst = steiner.mst(edges, list(terminals))
    low = steiner.weight([edges[i] for i in exact[0]])
    assert low <= steiner.weight([edges[i] for i in mst[0]]) <= 2 * low + 1e-9


def test_disconnected_and_single():
    assert steiner.exact(EDGES, ["part", "pages"]) == []
    assert steiner.exact(EDGES, ["part"]) == [frozenset()]


def test_k_best_are_in_order():
    got = steiner.solve(EDGES, ["nation", "orders", "supplier"], k_paths=3)
    assert names(got) == [["F2", "F3", "F4"], ["F2", "F4", "F5", "F7"], ["F3", "F5", "F7"]]


@pytest.mark.parametrize("benchmark, start, cloned, attributes", [
    ("trade", "part.p_name", {"part", "lineitem"}, 17), ("corpus", "labels.quality", {"labels"}, 3), ("corpus", "documents.lang", {"documents", "labels"}, 8),
    ("trade", "customer.c_name", {"customer", "orders", "lineitem"}, 22), ("trade", "nation.n_name", {"nation", "customer", "supplier", "orders", "lineitem"}, 29),
])
def test_forks(benchmark, start, cloned, attributes):
    g = sg.fork(sg.build_schema_graph(given_catalog(benchmark)), start, 1)
    new = [v for v in g.vertices if "#" in v]
    assert {v.split("#")[0] for v in new if "." not in v} == cloned
    assert sum("." in v for v in new) == attributes


def test_references_give_instances():
    graph = sg.build_schema_graph(given_catalog("trade"))
    for d in (1, 2, 3):
        _, terminals = sg.fork_for_bag(graph, ["part.p_name"] * d)
        assert len(terminals) == d


def test_infer_joins_keeps_bags_without_a_path_apart(spark):
    bags = spark.createDataFrame([("a", ["part", "pages"]), ("b", ["orders"]), ("c", ["orders.o_orderkey", "part.p_name", "part.p_name"])], "bag_id string, bag array<string>")
    got = {r["bag_id"]: r for r in joins.infer_joins(bags, given_catalog(), None, "default").collect()}
    assert set(got) == {"b", "c"} and got["b"]["score"] == 1.0 and got["c"]["n_edges"] == 4


def test_sql_of_a_self_join():
    frag = lambda clause, key, **kw: dict(dict(clause=clause, relation=key.split(".")[0], attribute=key.split(".")[1], func="", aggs=[], grouped=False, op="", value=None, numeric=False), **kw)
    frags = [frag("SELECT", "orders.o_orderkey"), frag("WHERE", "part.p_name", op="=", value="it's"), frag("WHERE", "part.p_name", op="=", value="b")]
    assert sqlgen.bag_of(frags) == ["orders.o_orderkey", "part.p_name", "part.p_name"]
    catalog = given_catalog("trade")
    path = joins.paths_of(sqlgen.bag_of(frags), sg.build_schema_graph(catalog), {})[0]
    sql = sqlgen.build_sql(frags, path[0], path[1])
    assert "part.p_name = 'it''s'" in sql and "part_1.p_name = 'b'" in sql and sql.count("JOIN") == 4
