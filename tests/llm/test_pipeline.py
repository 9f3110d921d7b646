import re
import tracemalloc
import weakref

import numpy as np
import pyarrow as pa

import corpus_pipeline
from fragmap.llm import common, pieces, simhash
from fragmap.llm.components import connected_components
from fragmap.llm.gray_index import spanning
from test_operators import _brute_kept, _edited_copies


def test_pipeline_decisions_against_plain_checks(spark, sf):
    docs = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    out = corpus_pipeline.run(spark, sf).collect()
    ids = [r["doc_id"] for r in out]
    assert len(ids) == len(set(ids)) and set(ids) <= set(docs)
    assert {"doc_id", "text", "lang", "source", "n_chars", "n_pieces"} <= set(out[0].asDict())
    assert all(r["round_trip"] and r["n_chars"] == len(r["text"]) for r in out)
    texts = [r["text"] for r in out]
    assert len(texts) == len(set(texts))
    items = [r["text"] for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    assert not any(i in t for i in items for t in texts)
    lines = {}
    for r in out:
        for line in {x.strip().lower() for x in r["text"].split("\n")}:
            lines.setdefault(line, []).append(r["doc_id"])
    assert not [x for x, d in lines.items() if len(x) >= 20 and len(d) >= 3]
    assert sum(bool(re.search(r"\b(idiot|moron|scum)\b", t.lower())) for t in texts) <= 2
    assert len(out) > 0.6 * len(docs)


def test_near_copies_are_found_at_any_distance(spark):
    rows = _edited_copies(7, 8, 8, 3)
    far = [(simhash.fingerprint(a, 5) ^ simhash.fingerprint(b, 5)).bit_count() for i, (_, a) in enumerate(rows) for _, b in rows[i // 8 * 8 : i]]
    assert max(far) > 8
    got = corpus_pipeline.drop_near_copies(spark, spark.createDataFrame(rows, "doc_id bigint, text string"), "")
    assert sorted(r["doc_id"] for r in got.collect()) == _brute_kept(rows, 5, None)


def test_near_copies_go_through_the_gray_index(spark, monkeypatch):
    rows = _edited_copies(7, 8, 8, 3)
    own, asked, pairs = simhash.link_edges, [], []
    monkeypatch.setattr(simhash, "link_edges", lambda codes, *a, **k: asked.append(codes.count()) or own(codes, *a, **k))
    verify = simhash.verified_pairs
    monkeypatch.setattr(simhash, "verified_pairs", lambda p, *a: pairs.append({(r["a"], r["b"]) for r in p.collect()}) or verify(p, *a))
    got = corpus_pipeline.drop_near_copies(spark, spark.createDataFrame(rows, "doc_id bigint, text string"), "")
    assert sorted(r["doc_id"] for r in got.collect()) == _brute_kept(rows, 5, None)
    assert asked == [len({simhash.fingerprint(t, 5) for _, t in rows})]
    assert not any(x & y for i, x in enumerate(pairs) for y in pairs[:i])  # nothing that the index linked is verified twice


def test_forest_of_a_large_group_is_a_tree_made_in_little_memory():
    rng, n = np.random.default_rng(5), 1500
    tid, fp, root = (rng.integers(-(2**62), 2**62, n) for _ in range(3))
    hot = [np.zeros(n, np.int64), tid, fp, np.full(n, 90, np.int32), root, np.zeros(n, np.int32)]
    for forest in (0, 1, None):
        tracemalloc.start()
        got = [b for b in simhash._candidates(hot, 0.8, None, forest)]
        made = sum(b.nbytes for b in got)
        most = tracemalloc.get_traced_memory()[1]
        tracemalloc.stop()
        links = {(r["a"], r["b"]) for b in got for r in b.to_pylist()}
        assert most < 60e6 + made
        if forest is None:
            assert links == {(min(a, b), max(a, b)) for i, a in enumerate(tid.tolist()) for b in tid[:i].tolist()}
        else:
            assert len(links) == n - 1
            number = {t: i for i, t in enumerate(tid.tolist())}
            a, b = (np.array([number[x[i]] for x in links]) for i in (0, 1))
            assert len(spanning(n, a, b)) == n - 1


def test_components_of_few_edges_take_no_rounds(spark, monkeypatch):
    rng, saved = np.random.default_rng(11), []
    own = common.checkpoint
    monkeypatch.setattr(common, "checkpoint", lambda df: saved.append(1) or own(df))
    nodes = rng.integers(-(2**62), 2**62, 400).tolist()
    edges = [*zip(nodes[:150], nodes[1:151]), *[(nodes[200], x) for x in nodes[200:300]], *zip(nodes[300:399:2], nodes[301:400:2])]
    edges += [edges[0], edges[0][::-1], (None, nodes[0]), (7, 7)]
    least = {x: x for e in edges for x in e if x is not None and x != 7}
    for _ in range(400):
        for a, b in edges:
            if a in least and b in least:
                least[a] = least[b] = min(least[a], least[b])
    df = spark.createDataFrame(edges, "a bigint, b bigint").repartition(4).persist()
    got = connected_components(df, "a", "b").collect()
    assert len(saved) == 1
    assert len(got) == len(least) and {r["node"]: r["root"] for r in got} == least
    more = connected_components(df, "a", "b", at_once=0).collect()  # more edges than one task takes
    assert len(saved) > 3 and sorted(more) == sorted(got)
    assert connected_components(df.where("a = 7"), "a", "b").count() == 0


class _Here:
    """A frame whose Arrow function runs at once in this process, as a task in a reused worker does."""

    def __init__(self, spark, batches):
        self.sparkSession, self.batches = spark, batches

    def mapInArrow(self, run, schema):
        return list(run(iter(self.batches)))


def test_near_copy_stage_lets_go_of_what_another_stage_kept_in_its_worker(spark):
    common.begin("pieces")
    own = weakref.ref(pieces.codec(pieces.MODEL))
    common.begin("pieces")  # the next task of that stage uses it again
    assert own() is not None and own() is pieces.codec(pieces.MODEL)
    n = 2500
    batch = pa.record_batch([pa.array(range(n)), pa.array(range(n)), pa.array([f"one two three four five {i}" for i in range(n)])], ["doc", "tid", "text"])
    got = simhash.prefixes(_Here(spark, [batch]), np.empty(0, np.uint64), 5, 0.8)
    assert own() is None
    assert sum(b.num_rows for b in got) == n and max(b.num_rows for b in got) <= common.ROWS
    assert [x for b in got for x in b["doc"].to_pylist()] == list(range(n))


def test_groups_of_pieces_hold_each_row_once(monkeypatch):
    monkeypatch.setattr(pieces, "GROUP_CHARS", 10)
    texts = ["abc", None, "defghijklmno", "", "p", "qrstuvwxy", "z"]
    batches = [pa.record_batch([pa.array(texts[a:b], pa.string())], ["text"]) for a, b in ((0, 2), (2, 2), (2, 6), (6, 7))]
    assert [t.column(0).to_pylist() for t in pieces._groups(iter(batches), 0)] == [texts[:3], texts[3:6], texts[6:]]
    assert list(pieces._groups(iter([]), 0)) == []
