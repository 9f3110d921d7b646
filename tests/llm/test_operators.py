"""Small fixtures with nulls, empty and long texts, ties, repeated rows and clashing column names, against plain versions."""

import hashlib
import math
import re
import zlib
from collections import Counter

import numpy as np
import pytest
import xxhash

from fragmap.llm import (
    decontaminate, gray_index, licenses, line_dedup, pieces, sharding, simhash, token_counts, toxicity, winnow,
)

LINE = "This line is long enough to be a key."
ROWS = [
    (1, f"{LINE}\nfirst own line\n{LINE}"), (2, f"  {LINE.upper()}\t\nsecond"), (3, f"third\n{LINE}"), (4, None), (5, ""), (6, "word " * 3000), (7, "Released under the MIT License."),
    (8, "Größe é 漢字 \t x"), (8, "Größe é 漢字 \t x"), (None, f"{LINE}\nno id"),
]


@pytest.fixture
def docs(spark):
    return spark.createDataFrame(ROWS, "doc_id bigint, text string").selectExpr("*", "'k' AS key", "0 AS pos", "1 AS fp", "2 AS score")


@pytest.fixture
def empty(docs):
    return docs.limit(0)


def test_line_dedup(docs, empty):
    got = {r["doc_id"]: r for r in line_dedup.dedup_lines(docs).collect()}
    assert got[1]["kept_text"] == "first own line" and got[1]["n_dropped"] == 2
    assert got[2]["kept_text"] == "second" and got[None]["kept_text"] == "no id"
    assert got[3]["kept_text"] == f"third\n{LINE}" and got[4]["n_lines"] == got[5]["n_lines"] == 1
    assert got[8]["key"] == "k" and line_dedup.dedup_lines(docs).count() == len(ROWS)
    assert line_dedup.dedup_lines(empty).count() == 0


def test_line_runs_are_levelled(spark):
    runs = line_dedup.LineRuns(spark, fanout=2)
    for i in range(4):
        batch = spark.createDataFrame([(i, f"line number {i // 2} that is long enough")], "doc_id bigint, text string")
        fresh = line_dedup.first_seen_lines(runs, batch).count()
        assert fresh == (1 if i % 2 == 0 else 0)
    assert [len(x) for x in runs.levels] == [0, 0, 1] and {r["n_docs"] for r in runs.totals().collect()} == {2}


def test_pieces_equal_the_library(docs, empty):
    import public_tokenizers
    import sentencepiece

    ref = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path(pieces.MODEL))
    got = pieces.encode_documents(docs).collect()
    assert len(got) == len(ROWS)
    for r in got:
        assert r["pieces"] == ref.encode(r["text"] or "") and r["round_trip"]
    own = pieces.codec(pieces.MODEL)
    rng = np.random.default_rng(0)
    texts = ["".join(rng.choice(list("aeinst  \n漢é\0▁"), 40)) for _ in range(300)]
    assert [c.tolist() for c in own.encode(texts)] == ref.encode(texts)
    assert pieces.decode_documents(pieces.encode_documents(docs).drop("round_trip")).where("decoded <> coalesce(text, '')").count() == 0
    assert pieces.encode_documents(empty).count() == 0


def test_token_counts(spark, docs, empty):
    encode = token_counts.encoder(token_counts.VOCABULARY).encode_ordinary
    lengths = sorted(len(encode(t or "")) for _, t in ROWS)
    hist = token_counts.length_histogram(token_counts.token_lengths(docs))
    for r in hist.collect():
        n = r["n_tokens"]
        assert r["n_docs"] == lengths.count(n) and r["docs_at_least"] == sum(x >= n for x in lengths)
        assert r["truncated_tokens"] == sum(min(x, n) for x in lengths) and r["total_tokens"] == sum(lengths)
    limits = spark.createDataFrame([(5,), (100000,)], "context_limit bigint")
    got = {r["context_limit"]: (r["docs_cut"], r["tokens_left"]) for r in token_counts.limits_report(hist, limits).collect()}
    assert got[5] == (sum(x > 5 for x in lengths), sum(min(x, 5) for x in lengths)) and got[100000] == (0, sum(lengths))
    q = {r["quantile"]: r["n_tokens"] for r in token_counts.quantile_report(hist).collect()}
    assert q[0.5] == lengths[math.ceil(len(lengths) / 2) - 1]
    assert token_counts.length_histogram(token_counts.token_lengths(empty)).count() == 0


def test_toxicity(spark, docs):
    bad = ["you awful thing", "so awful. fine day", "what an awful day"] * 20
    good = ["a fine day", "some long text. with parts", "nothing here"] * 20
    model = toxicity.fit(bad + good + [None, ""], [1] * 60 + [0] * 62)
    values = toxicity._WordValues(model[0])
    p = lambda t: toxicity.noisy_or(toxicity.sentence_scores(t, values, model[1]))
    assert p("fine. then awful! end") > 0.5 > p("fine. then long. " * 5) and 0 <= p("") < 0.5
    got = toxicity.score_toxicity(spark.createDataFrame([(1, "all fine. an awful end")], "doc_id int, text string"), model).first()
    assert (got["tox_start"], got["tox_end"]) == (9, 22) and got["tox_sentence"] == 1
    assert toxicity.score_toxicity(docs, model).count() == len(ROWS)
    assert toxicity.fit([], [])[1] < 0
    labels = spark.createDataFrame([(1, None), (2, 1), (2, 0), (99, 1)], "doc_id bigint, toxic int")
    assert len(toxicity.training_rows(docs, labels)[0]) <= 1


def test_sharding(spark, docs, empty):
    keys = np.random.default_rng(1).integers(0, 1 << 63, 20000).astype(np.uint64)
    a, b = sharding.jump_buckets(keys, 24), sharding.jump_buckets(keys, 25)
    assert set(b[a != b]) == {24} and abs((a != b).mean() - 1 / 25) < 0.01 and np.bincount(a).min() > 600
    got = sharding.shard_documents(docs, 3).collect()
    assert len(got) == len(ROWS)
    for s in range(3):
        assert sorted(r["slot"] for r in got if r["shard"] == s) == list(range(sum(r["shard"] == s for r in got)))
    assert all(r["size"] == len((t or "").encode()) + 8 and r["text_crc32"] == zlib.crc32((t or "").encode()) for r in got for d, t in ROWS if d == r["doc_id"])
    assert sharding.shard_documents(empty).count() == 0


def test_decontamination(spark, docs, empty):
    item = "What is the colour of the ninth door? The ninth door is painted in faded olive green."
    bench = spark.createDataFrame([(1, item), (2, "Unrelated question about trains? They leave at noon from the old station."), (3, None), (4, "...")], "item_id bigint, text string")
    index = decontaminate.item_indexes(bench)[0]
    texts = spark.createDataFrame([(1, "noise " * 500 + item.lower() + " noise" * 500), (2, "What is the colour of the ninth door? Nobody knows at all today."), (3, None), (4, "olive green"), (5, item)], "doc_id bigint, text string")
    found = {(r["doc_id"], r["item_id"]) for r in decontaminate.find_leaks(texts, index, ["doc_id"]).collect()}
    assert found == {(1, 1), (5, 1)}
    assert {r["doc_id"] for r in decontaminate.drop_leaking(texts, bench).collect()} == {2, 3, 4}
    assert decontaminate.drop_leaking(docs, bench).count() == len(ROWS) and decontaminate.drop_leaking(empty, bench).count() == 0
    assert decontaminate.drop_leaking(docs, bench.limit(0)).count() == len(ROWS)
    rng = np.random.default_rng(2)
    for _ in range(200):
        terms = np.unique(rng.integers(0, len(index.terms), 12))
        brute = Counter()
        for t in terms:
            for block in index.postings[t].values():
                for i, s in block:
                    brute[i] += s
        assert {i for i, _ in index.retrieve(terms, 0.2)} == {i for i, s in brute.items() if s >= 0.2 - 1e-9}


def test_gray_index_equals_brute_force():
    rng = np.random.default_rng(3)
    base = rng.integers(0, 1 << 63, 60).astype(np.uint64)
    codes = np.unique(np.concatenate([base] + [base ^ (np.uint64(1) << rng.integers(0, 64, 60).astype(np.uint64)) for _ in range(6)]))
    index = gray_index.GrayIndex(codes)
    got = {(i, j) for a, b in index.search(codes, 4) for i, j in zip(a.tolist(), b.tolist())}
    want = {(i, j) for i in range(len(codes)) for j in range(len(codes)) if int(codes[i] ^ index.codes[j]).bit_count() <= 4}
    assert got == want
    a, b = index.forest(4)
    label = np.arange(len(codes))
    gray_index.merge(label, a, b)
    assert len(set(label.tolist())) == len(set(index.components(4).tolist())) and len(a) == len(codes) - len(set(label.tolist()))


def test_simhash_components(spark, docs, empty):
    got = simhash.near_duplicate_groups(docs).collect()
    assert len(got) == len(ROWS)
    for r in got:
        texts = [t for d, t in ROWS if d == r["doc_id"]]
        assert r["fp"] % (1 << 64) == simhash.fingerprint(texts[0])
    assert {r["component_id"] for r in got if r["doc_id"] in (4, 5)} == {4}
    assert simhash.near_duplicate_groups(empty).count() == 0


def test_heavy_keys_lose_no_link(spark):
    codes = [(1 << 40) + (i << 3) for i in range(300)]
    df = spark.createDataFrame([(c,) for c in codes], "fp bigint")
    from fragmap.llm.components import connected_components

    roots = {r["root"] for r in connected_components(simhash.link_edges(df, len(codes), 4, group=40)).collect()}
    assert roots == {min(codes)}


def test_near_duplicates_keep_one(spark, docs):
    text = " ".join(f"w{i}" for i in range(300))
    rows = [(1, text), (2, text), (3, text.replace("w150", "x")), (4, " ".join(f"v{i}" for i in range(300))), (5, None), (6, "")]
    got = simhash.drop_near_duplicates(spark.createDataFrame(rows, "doc_id bigint, text string"), 5, 8)
    assert sorted(r["doc_id"] for r in got.collect()) == [1, 4, 5]
    assert simhash.drop_near_duplicates(docs, 5, 8).where("doc_id = 8").count() == 1


def _brute_kept(rows, shingle, max_diff, similarity=0.8):
    """Least id of each component of all pairs, by plain loops."""
    sets = {d: set(simhash.shingle_set(t, shingle).tolist()) for d, t in rows}
    codes = {d: simhash.fingerprint(t, shingle) for d, t in rows}
    root = {d: d for d, _ in rows}
    for i, (a, _) in enumerate(rows):
        for b, _ in rows[:i]:
            near = max_diff is None or (codes[a] ^ codes[b]).bit_count() <= max_diff
            if near and len(sets[a] & sets[b]) >= similarity * len(sets[a] | sets[b]):
                x, y = sorted((root[a], root[b]))
                root = {d: x if r == y else r for d, r in root.items()}
    return sorted(set(root.values()))


def _edited_copies(seed, groups, copies, edits):
    rng = np.random.default_rng(seed)
    rows = []
    for g in range(groups):
        base = [f"g{g}w{i}" for i in range(120)]
        for _ in range(copies):
            words = list(base)
            for at in rng.choice(120, rng.integers(0, edits + 1), replace=False):
                words[at] = f"x{rng.integers(1 << 30)}"
            rows.append((len(rows), " ".join(words)))
    return rows


def test_every_candidate_within_the_radius_is_verified(spark):
    rows = _edited_copies(5, 6, 25, 6)
    got = simhash.drop_near_duplicates(spark.createDataFrame(rows, "doc_id bigint, text string"), 5, 8)
    assert sorted(r["doc_id"] for r in got.collect()) == _brute_kept(rows, 5, 8)


def test_long_texts_are_compared_by_all_shingles(spark):
    rows = []
    for seed in range(400):
        rng = np.random.default_rng(seed)
        words = [f"s{seed}w{i}" for i in range(1200)]
        other = list(words)
        for at in range(0, 1200, 1200 // 32):
            other[at] = f"x{rng.integers(1 << 40)}"
        x, y = (simhash.shingle_set(" ".join(t), 5) for t in (words, other))
        share = len(np.intersect1d(x, y)) / len(np.union1d(x, y))
        least = np.union1d(x, y)[:256]
        guess = np.isin(least, np.intersect1d(x, y)).mean()
        near = (simhash.fingerprint(" ".join(words), 5) ^ simhash.fingerprint(" ".join(other), 5)).bit_count() <= 8
        if near and (guess >= 0.8) != (share >= 0.8):
            rows += [(len(rows), " ".join(words)), (len(rows) + 1, " ".join(other))]
    assert rows
    got = simhash.drop_near_duplicates(spark.createDataFrame(rows, "doc_id bigint, text string"), 5, 8)
    assert sorted(r["doc_id"] for r in got.collect()) == _brute_kept(rows, 5, 8)


def test_winnowing(spark, docs, empty):
    got = {r["doc_id"]: r for r in winnow.document_fingerprints(docs).collect()}
    assert got[4]["fingerprint"] == got[5]["fingerprint"] == [] and len(got[8]["fingerprint"]) == 1 and "key" in got[8]
    words = [f"w{i}" for i in range(60)]
    df = spark.createDataFrame([(1, " ".join(words)), (2, "x y z " + " ".join(words[10:30]) + " q")], "doc_id bigint, text string")
    a, b = (sorted(r["fingerprint"]) for r in winnow.document_fingerprints(df).collect())
    assert {h for h, _ in a} & {h for h, _ in b}  # a shared run of GRAM + WINDOW - 1 units or more
    rows = {r["doc_id"]: r for r in winnow.edited_fingerprints(docs).collect()}
    assert rows[5]["near_edited"] == 1.0 and rows[5]["near_next"] == 0.0 and len(rows) == len({d for d, _ in ROWS})
    assert winnow.edited_fingerprints(docs).count() == len(ROWS) and winnow.edited_fingerprints(empty).count() == 0


def test_winnowing_finds_short_passages_and_any_offset(spark):
    pairs = []
    for seed in range(30):
        w = [f"s{seed}w{i}" for i in range(8)]
        pairs.append((f"{' '.join(f'a{seed}u{i}' for i in range(20))} {' '.join(w)}", f"{' '.join(w)} {' '.join(f'b{seed}u{i}' for i in range(20))}"))
    run = "".join(chr(0x4E00 + i * 7) for i in range(60))
    pairs.append((run, "五" + run))
    df = spark.createDataFrame([(i, t) for p in pairs for i, t in enumerate(p)], "doc_id bigint, text string").coalesce(1)
    got = [{h for h, _ in r["fingerprint"]} for r in winnow.document_fingerprints(df).collect()]
    assert all(a & b for a, b in zip(got[::2], got[1::2]))


def test_license_scan(docs, spark, empty):
    got = {r["doc_id"]: r for r in licenses.license_scan(docs).collect()}
    assert got[7]["labels"] == "mit" and got[7]["first_word"] == 1 and got[7]["n_base"] == 1 and got[4]["n_words"] == 0 and got[6]["n_words"] == 3000
    texts = ["this work is licensed under the gnu general public license version 3", "filler " * 70 + "licensed under a creative commons attribution 4.0 international license " + "end " * 70, "under the mit", None]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id int, text string")
    got = {r["doc_id"]: r["labels"] for r in licenses.license_scan(df).collect()}
    assert got == {0: "gpl-3", 1: "cc-by", 2: "", 3: ""}
    words = lambda t: re.findall(r"[a-z0-9]+", t or "")
    want = set()
    for i, t in enumerate(texts):
        for k, (_, tpl) in enumerate(licenses.TEMPLATES):
            s, w = set(tpl.split()), words(t)
            n = max(len(x.split()) for _, x in licenses.TEMPLATES)
            if any(len(s & set(w[j : j + 2 * n])) >= math.ceil(0.9 * len(s) - 1e-9) for j in range(0, max(len(w) - n, 0) + 1, n)):
                want.add((i, k))
    assert {(r["doc_id"], r["template"]) for r in licenses.template_matches(df, ["doc_id"]).collect()} == want
    assert licenses.license_scan(empty).count() == 0


def test_columns_named_as_added_ones_stay(spark):
    """Every operator that passes columns through returns clashing ones as input_<name>."""
    rows = spark.createDataFrame([(1, f"{LINE}\nown", "a"), (2, LINE, None), (3, LINE, "c")], "doc_id bigint, text string, x string")
    model = toxicity.fit(["bad thing"] * 5 + ["fine day"] * 5, [1] * 5 + [0] * 5)
    for added, run in [
        (["kept_text", "N_LINES", "n_dropped"], line_dedup.dedup_lines),
        (["n_pieces", "pieces", "round_trip", "pieces_crc32"], pieces.encode_documents),
        (["tox_score", "tox_sentence", "tox_start", "tox_end"], lambda d: toxicity.score_toxicity(d, model)),
        (["fingerprint"], winnow.document_fingerprints),
    ]:
        clash = rows.selectExpr("doc_id", "text", *[f"x AS {n}" for n in added], f"7 AS input_{added[0]}")
        got = run(clash)
        names = [n.lower() for n in got.columns]
        assert len(names) == len(set(names)) and {n.lower() for n in added} <= set(names)
        out = {r["doc_id"]: r for r in got.collect()}
        for n in added:
            held = f"input_input_{n}" if n == added[0] else f"input_{n}"
            assert [out[i][held] for i in (1, 2, 3)] == ["a", None, "c"]
        assert out[1][f"input_{added[0]}"] == 7


def test_license_base_equals_brute_force(spark):
    rng = np.random.default_rng(11)
    parts = ["Under", "the", "MIT", "license", "Apache", "version", "2", "cc", "by", "nc", "worK", "İx", "é", "by-nc", "CC", "x9"]
    seps = [" ", "\n", "-", ", ", "_", "\t"]
    whole = [*licenses.PHRASES, "Under The MIT-License", "CC BY-NC", "licensed under cc by nc 4.0"]
    texts = [None, ""]
    for _ in range(120):
        words = [str(rng.choice(whole if rng.random() < 0.2 else parts)) for _ in range(rng.integers(1, 40))]
        texts.append("".join(w + str(rng.choice(seps)) for w in words))
    got = {r["doc_id"]: r for r in licenses.license_scan(spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")).collect()}
    lower = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    some = 0
    for i, text in enumerate(texts):
        words = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (text or "").translate(lower))
        places = [(j, label) for p, label in licenses.PHRASES.items() for j in range(len(words)) if words[j : j + len(p.split())] == p.split()]
        some += bool(places)
        r, at = got[i], [j for j, _ in places]
        assert (r["n_words"], r["n_base"]) == (len(words), len(places))
        assert (r["first_word"], r["last_word"]) == ((min(at), max(at)) if at else (None, None))
        assert r["base_labels"] == ",".join(sorted({label for _, label in places}))
        assert {label for _, label in places} <= set(r["labels"].split(",")) and 0 <= r["score"] <= 1
    assert some > 20


def test_template_matches_are_distinct_and_the_kelvin_sign_is_no_k(spark):
    text = licenses.TEMPLATES[1][1]
    df = spark.createDataFrame([(1, text), (2, "worK WORK")], "doc_id int, text string")
    rows = [(r["doc_id"], r["block"], r["template"]) for r in licenses.template_matches(df, ["doc_id"]).collect()]
    assert rows and len(rows) == len(set(rows))
    assert df.where("doc_id = 2").select(licenses.words_of(df["text"]).alias("w")).first()["w"] == ["woré", "work"]


def test_simhash_components_equal_all_pairs(spark):
    rows = _edited_copies(13, 10, 6, 2) + [(900, None), (901, ""), (902, "one two"), (903, "ONE  two")]
    got = {r["doc_id"]: r for r in simhash.near_duplicate_groups(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()}
    import xxhash

    codes = {}
    for d, t in rows:
        words = re.findall(r"[^\x20\x09-\x0D]+", (t or "").lower())
        n = min(4, len(words))
        hs = [xxhash.xxh64_intdigest(" ".join(words[i : i + n]).encode(), 42) for i in range(len(words) - n + 1)] if n else []
        codes[d] = sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))
    root = {d: d for d in codes}
    for a in codes:
        for b in codes:
            if (codes[a] ^ codes[b]).bit_count() <= 4 and root[a] != root[b]:
                x, y = sorted((root[a], root[b]))
                root = {d: x if r == y else r for d, r in root.items()}
    assert {d: (r["fp"] % (1 << 64), r["component_id"]) for d, r in got.items()} == {d: (codes[d], root[d]) for d in codes}


def test_winnowing_equals_plain_loops(spark):
    rng = np.random.default_rng(17)
    texts = [None, "", " \n"] + ["".join(str(rng.choice(["ab", "c", "漢", "x" * 20])) + str(rng.choice([" ", "\n", ""])) for _ in range(rng.integers(1, 60))) for _ in range(40)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    units = lambda t: re.findall(r"(?<!\S)\S{1,12}(?!\S)|\S", t or "", re.ASCII)
    grams = [(i, j, *[u[j + k] if j + k < len(u) else None for k in range(3)]) for i, t in enumerate(texts) if (u := units(t)) for j in range(max(len(u) - 2, 1))]
    hashed = spark.createDataFrame(grams, "i int, j int, a string, b string, c string").selectExpr("i", "j", "xxhash64(a, b, c) & 2147483647 AS h").collect()
    by = {}
    for r in sorted(hashed, key=lambda r: (r["i"], r["j"])):
        by.setdefault(r["i"], []).append((r["h"], r["j"]))
    for r in winnow.document_fingerprints(df).collect():
        hs = by.get(r["doc_id"], [])
        want = []
        for s in range(max(len(hs) - 5, 1) if hs else 0):
            least = min(hs[s : s + 6], key=lambda v: (v[0], -v[1]))
            if least not in want:
                want.append(least)
        assert [tuple(x) for x in r["fingerprint"]] == want
    rows = {r["doc_id"]: r for r in winnow.edited_fingerprints(df).collect()}
    for i, t in enumerate(texts):
        t, after = t or "", texts[(i + 1) % len(texts)] or ""
        cut = len(t) // 4
        assert rows[i]["n_chars"] == len(t)
        assert rows[i]["edited_sha256"] == hashlib.sha256((t[: len(t) - cut] + after[:cut]).encode()).hexdigest()


def _plain_leaks(text, items):
    """(item id, score) by plain loops: BM25 shares of every passage, then the overlaps of the best one."""
    words = [(i, re.findall(r"[^\W_]+", (t or "").lower()), t) for i, t in items]
    words = [w for w in words if w[1]]
    mean, longest = sum(len(w) for _, w, _ in words) / len(words), max(len(w) for _, w, _ in words)
    df = Counter(x for _, w, _ in words for x in set(w))
    here, found = re.findall(r"[^\W_]+", (text or "").lower()), {}
    for start in range(0, max(len(here) - longest, 1), longest):
        passage = set(here[start : start + 2 * longest])
        wide = here[max(0, start - longest) : start + 3 * longest]
        for i, w, t in words:
            share = {
                x: math.log(1 + (len(words) - df[x] + 0.5) / (df[x] + 0.5)) * n * 2.2 / (n + 1.2 * (0.25 + 0.75 * len(w) / mean))
                for x, n in Counter(w).items()
            }
            score = sum(v for x, v in share.items() if x in passage) / sum(share.values())
            if score < 0.5 - 1e-9:
                continue
            overlaps = []
            for part in decontaminate.question_and_answer(t):
                size = min(5, len(part))
                grams = {tuple(part[k : k + size]) for k in range(len(part) - size + 1)}
                overlaps.append(len(grams & {tuple(wide[k : k + size]) for k in range(len(wide) - size + 1)}) / len(grams))
            if min(overlaps) >= 0.5:
                found[i] = max(found.get(i, 0.0), score)
    return found


def test_decontamination_equals_plain_loops(spark):
    rng = np.random.default_rng(11)
    vocabulary = [f"w{k}" for k in range(300)]
    say = lambda n: " ".join(rng.choice(vocabulary, n))
    items = [(k, f"{say(int(rng.integers(6, 25)))}? {say(int(rng.integers(3, 9)))}.") for k in range(60)] + [(60, None), (61, "..."), (62, "one")]
    texts = [None, "", say(2000)]
    for k in range(40):
        body = items[k][1].split()
        for at in rng.integers(0, len(body), k % 3):
            body[at] = "changed"
        texts.append(" ".join([say(int(rng.integers(0, 200))), *body, say(int(rng.integers(0, 200)))]))
    bench = spark.createDataFrame(items, "item_id bigint, text string")
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    want = {(d, i): s for d, t in enumerate(texts) for i, s in _plain_leaks(t, items).items()}
    assert len(want) > 20
    for chars in (10**9, 1500):  # one index, and parts that must give the same scores
        indexes = decontaminate.item_indexes(bench, index_chars=chars)
        assert (len(indexes) > 3) == (chars == 1500)
        rows = [r for index in indexes for r in decontaminate.find_leaks(docs, index, ["doc_id"]).collect()]
        got = {(r["doc_id"], r["item_id"]): r["score"] for r in rows}
        assert len(rows) == len(got) and got == pytest.approx(want)
        clean = {r["doc_id"] for r in decontaminate.drop_leaking(docs, bench, index_chars=chars).collect()}
        assert clean == set(range(len(texts))) - {d for d, _ in want}


def _plain_shard(key, n):
    at, ahead = -1, 0
    while ahead < n:
        at = ahead
        key = (key * 2862933555777941757 + 1) % 2**64
        ahead = int((at + 1) * ((1 << 31) / ((key >> 33) + 1)))
    return at


def test_sharding_query_equals_plain_loops(spark, sf):
    texts = {r["doc_id"]: (r["text"] or "").encode() for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    rows = sharding.op6_sharding(spark, sf).collect()
    assert len(rows) == len(texts)
    slots = {}
    for r in rows:
        data = texts[r["doc_id"]]
        key = xxhash.xxh64_intdigest(r["doc_id"].to_bytes(8, "little", signed=True), seed=42)
        assert (r["size"], r["text_crc32"], r["law"]) == (len(data) + 8, zlib.crc32(data), "key")
        assert (r["shard"], r["grown_shard"]) == (_plain_shard(key, 24), _plain_shard(key, 25))
        assert r["grown_shard"] in (r["shard"], 24)
        slots.setdefault(r["shard"], []).append(r["slot"])
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())


def test_distinct_units_are_decoded_once_and_a_lost_one_is_seen():
    import public_tokenizers

    own = pieces.PieceCodec(public_tokenizers.path(pieces.MODEL))
    texts = ["a  b\n\nc", "日本語 \U0001f600 é", "▁ x", "", None, " y" * 400]
    got = own.encode(texts)
    assert own.exact and [own.decode(c) for c in got] == [(t or "").replace(pieces.SPACE, " ") for t in texts]
    own.encode(["a\ud800b"])
    assert not own.exact
    rounds = []
    own = pieces.PieceCodec(public_tokenizers.path(pieces.MODEL))
    search = np.argsort
    try:
        np.argsort = lambda *a, **k: rounds.append(a[0].dtype) or search(*a, **k)
        own.encode_units(["▁plain", "▁words", "▁again"])
    finally:
        np.argsort = search
    assert len([k for k in rounds if k == np.int64]) == 2  # sixteen characters in two rounds: few kinds of characters, many to a key
