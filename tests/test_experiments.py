from fragmap.plans import evaluate as ev
from fragmap.plans import hosts as hs
from fragmap.sources.questions import question_rows


def test_question_counts_and_gold():
    rows = question_rows([f"w{i}" for i in range(38)], include_excluded=True)
    by = {b: sum(r[1] == b and not r[9] for r in rows) for b in ("trade", "activity", "corpus")}
    assert by == {"trade": 194, "activity": 127, "corpus": 128} and sum(r[9] for r in rows) == 6


def test_log_layer_wins(spark, sf):
    x = ev.Experiment(spark, sf)
    pct = {}
    for host in (hs.vector_pipeline_host("H1"), hs.vector_pipeline_host("H2", log_layer=True), hs.vector_pipeline_host("L1", log_layer=True, lam=1.0)):
        for r in ev.accuracy(x.run(host)).collect():
            pct[host.name, r["benchmark"]] = (r["kw_pct"], r["fq_pct"])
    for b in ("trade", "activity", "corpus"):
        assert pct["H2", b][0] > pct["H1", b][0] and pct["H2", b][1] > pct["H1", b][1]
        assert all(kw >= fq for kw, fq in pct.values())
        assert pct["L1", b][0] == pct["H1", b][0]  # similarity alone is lambda 1
