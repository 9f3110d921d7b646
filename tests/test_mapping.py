import pytest
from pyspark.sql import functions as F

from fragmap import queries as q
from fragmap.functions.stem import porter_stem
from fragmap.operators import mapping
from fragmap.plans import hosts


@pytest.mark.parametrize("word, stem", [("restaurant", "restaur"), ("businesses", "busi"), ("ponies", "poni"), ("relational", "relat"), ("hopping", "hop"), ("sky", "sky"), ("controlling", "control"), ("widgets", "widget")])
def test_stems(word, stem):
    assert porter_stem(word) == stem


@pytest.mark.parametrize("sigmas, kappa, kept", [([1.0, 0.99, 0.3], 2, 1), ([1.0, 0.9999999, 0.3], 2, 2), ([0.9, 0.8, 0.8, 0.7], 2, 3), ([0.9, 0.0, 0.0], 2, 2), ([], 2, 0)])
def test_prune(spark, sigmas, kappa, kept):
    rows = spark.createDataFrame([("a", 0, str(i), s) for i, s in enumerate(sigmas)], "qid string, k int, expr string, sigma double")
    assert mapping.score_and_prune(rows, kappa).count() == kept


def test_configuration_scores(spark, sf):
    got = {(r["qid"], r["config"]): r["score"] for r in q.cfg_final(spark, sf).collect()}
    assert got["c1", "part.p_name + nation.n_name ?op ?val"] == pytest.approx(0.769695720, abs=1e-8)
    assert got["c1", "supplier.s_name + nation.n_name ?op ?val"] == pytest.approx(0.634980315, abs=1e-8)
    assert got["c2", "part.p_name + nation.n_name ?op ?val + orders"] == pytest.approx(0.792449398, abs=1e-8)
    assert got["c4", "orders.o_orderkey + part.p_name ?op ?val + part.p_name ?op ?val"] == pytest.approx(0.741511855, abs=1e-8)
    assert got["c5", "part.p_type"] == pytest.approx(0.52, abs=1e-8)


def test_keyword_without_candidates_gives_no_configuration(spark):
    n = spark.createDataFrame([("a", 2)], "qid string, n_keywords int")
    rows = spark.createDataFrame([("a", 0, "SELECT", "x", 0.5, 1)], "qid string, k int, clause string, expr string, sigma double, place int")
    numbered = mapping.number_candidates(rows)
    assert mapping.generate_configs(numbered, n).count() == 0
    assert mapping.generate_configs(numbered, n, allow_partial=True).count() == 1


def test_numbers_are_whole_tokens(spark):
    asked = q._asked(spark, [("a", [("Brand#12", "WHERE", None, [], False)]), ("b", [("after 1998", "WHERE", ">", [], False)]), ("c", [("7", "WHERE", None, [], False)])])
    got = {r["qid"]: (r["num"], r["rest"]) for r in mapping.explode_keywords(asked).collect()}
    assert got == {"a": (None, "Brand#12"), "b": (1998.0, "after"), "c": (7.0, "")}


def test_question_parser():
    got = hosts.parse_question("Return number of orders per segment")
    assert got[0]["aggs"] == ["count"] and got[1]["grouped"]


def test_dempster_prefers_agreement(spark):
    row = spark.range(1).select(mapping.combine(F.lit(0.9), F.lit(0.9), how="dempster").alias("a"), mapping.combine(F.lit(0.9), F.lit(0.1), how="dempster").alias("b")).first()
    assert row["a"] > 0.98 and row["b"] == pytest.approx(0.5)
