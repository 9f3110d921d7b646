from pyspark.sql import functions as F

from fragmap.functions.similarity import LexiconSimilarity
from fragmap.operators import content_index as ci
from fragmap.plans import evaluate as ev
from fragmap.plans import hosts as hs
from fragmap.plans.lineage import cut
from fragmap.sources.glossary import glossary
from fragmap.sources.questions import load_questions


def test_short_values_once_and_long_ones_kept(spark):
    cells = spark.createDataFrame([("r", "a", "x")] * 3 + [("r", "b", "x")] + [("r", "a", "w " * 150)] * 2, "relation string, attribute string, value string")
    assert sorted((r["attribute"], len(r["value"])) for r in ci.distinct_cells(cells).collect()) == [("a", 1), ("a", 300), ("a", 300), ("b", 1)]


def test_candidates_of_all_parsers_come_from_one_pass(spark, sf, monkeypatch):
    questions = cut(ev.assign_folds(load_questions(spark, sf)).where("qid in ('T05-00', 'T06-01', 'T10-02', 'V02-01', 'D04-03')"))
    sim, passes = LexiconSimilarity(glossary(spark)), []
    rows = lambda df: sorted(map(str, df.select("qid", "k", "clause", "relation", "attribute", "func", "op", "value", "ways", F.round("sigma", 9)).collect()))
    apart = {n: rows(hs.batch_candidates(spark, sf, hs.noisy_parse(questions, n), sim)) for n in (0.0, 1.0)}
    once = hs.batch_candidates
    monkeypatch.setattr(hs, "batch_candidates", lambda *a, **k: passes.append(1) or once(*a, **k))
    got = hs.parsed_candidates(spark, sf, questions, sim, (0.0, 1.0))
    assert {n: rows(df) for n, df in got.items()} == apart and apart[0.0] != apart[1.0] and len(passes) == 1
