import pytest

from fragmap.catalog import given_catalog
from fragmap.functions import sqltext
from fragmap.operators import fragments as fr
from fragmap.operators import qfg as qg
from fragmap.sources import logs

CAT = given_catalog()


def read(sql):
    return [(f.clause, f.expr, f.op) for f in sqltext.fragments(sql, CAT)]


def test_join_conditions_are_no_fragments_and_aliases_resolve():
    got = read("SELECT p.P_NAME FROM part p, lineitem AS l WHERE p.p_partkey = l.l_partkey AND 5 < p.p_size")
    assert got == [("FROM", "part", ""), ("FROM", "lineitem", ""), ("SELECT", "part.p_name", ""), ("WHERE", "part.p_size", ">")]


@pytest.mark.parametrize("sql, ops", [
    ("select p_name from part where p_size between 1 and 2", [">=", "<="]),
    ("select p_name from part where p_brand in ('a', 'b''c')", ["in"]),
    ("select p_name from part where not (p_name like 'x%' or p_size != 3)", ["like", "<>"]),
    ("select p_name from part where p_name is not null", ["is not null"]),
    ("select p_name /* c */ from part -- x\n where p_size = -3;", ["="]),
])
def test_predicates(sql, ops):
    assert [op for clause, _, op in read(sql) if clause == "WHERE"] == ops


@pytest.mark.parametrize("sql", [
    "select p_name from part where p_size > (select 1)", "select a from part union select b from part", "select p_name from nowhere", "update part", "select x.p_name from part", "",
    "select p_name from (select 1)",
])
def test_unreadable(sql):
    with pytest.raises((sqltext.Unreadable, IndexError)):
        sqltext.fragments(sql, CAT)


def test_slots_number_literals_across_on_and_where():
    f = sqltext.fragments("select count(o.o_orderkey) from orders o join customer c on o.o_custkey = c.c_custkey and c.c_name = 'x' where o.o_totalprice > 5", CAT)
    assert [(x.expr, x.slots) for x in f if x.op] == [("customer.c_name", (0,)), ("orders.o_totalprice", (1,))]


def test_levels_and_merge(spark):
    rows = [(1, "select p_name from part where p_size > 3"), (2, "select p_name from part where p_size < 4"), (3, None), (4, "nonsense")]
    log = spark.createDataFrame(rows, "log_id bigint, sql string").selectExpr("log_id", "cast(null as timestamp) ts", "1L user_id", "sql")
    of = lambda level: {(r["clause"], r["expr"]): r["n_v"] for r in qg.build_qfg(log, CAT, level).vertices.collect()}
    assert of(fr.FULL)["WHERE", "part.p_size > 3"] == 1
    assert of(fr.NOCONST)["WHERE", "part.p_size < ?val"] == 1
    assert of(fr.NOCONSTOP)["WHERE", "part.p_size ?op ?val"] == 2
    assert fr.parse_errors(log, CAT).count() == 1
    whole = qg.build_qfg(log, CAT)
    double = whole.merge(whole)
    assert {r["n_v"] for r in double.vertices.collect()} == {4}
    assert double.minus(whole).edges.count() == whole.edges.count()


def test_empty_log(spark):
    g = qg.build_qfg(spark.createDataFrame([], logs.LOG_SCHEMA), CAT)
    assert g.vertices.count() == g.edges.count() == 0


def test_every_spelling_of_the_log_parses(spark, sf):
    log = logs.synth_log(spark, sf)
    assert fr.parse_errors(log, CAT).count() == 0
    v = {(r["clause"], r["expr"]): r["n_v"] for r in qg.build_qfg(log, CAT).vertices.collect()}
    assert v["FROM", "customer"] == 500 and v["SELECT", "part.p_name"] == 300 and len(v) == 38


def test_counting_runs_without_python_beside_the_parser(spark, sf):
    plan = fr.fold_templates(logs.synth_log(spark, sf))._jdf.queryExecution().toString()
    assert "Python" not in plan and "CartesianProduct" not in plan
