"""SimHash near-duplicates through a Gray-order hierarchical index.

Equal fingerprints are one node with its least ``doc_id``. The 64 bits are cut into
pieces; two fingerprints within ``max_diff`` bits agree on at least
``pieces - max_diff`` of them, so every choice of that many pieces is a key and links
never cross keys. Inside a key's rows a Gray index finds the links, which are reduced
at once to one edge per fingerprint. More pieces make longer keys: their number grows
with the count of fingerprints. A key of more than ``GROUP`` fingerprints is cut into
blocks and each pair of blocks is a task of its own, so nothing is unbounded and no
link is lost.

Defined cases: a null or empty text has fingerprint 0 and is linked like any other;
fewer words than a shingle make one shingle; repeated rows link as equal texts; a null
``doc_id`` takes part without being a component's name unless it is alone; an empty
table gives an empty result.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fragmap.llm import common
from fragmap.llm.components import connected_components
from fragmap.llm.gray_index import GrayIndex, spanning

SHINGLE = 4
MAX_DIFF = 4
SEED = 42
GROUP = 1024
PART = 16
BITMAP = 2048
OFTEN = 8
PAIRS = 1 << 17
BLOOM_BITS = 26
SHIPPED = 0.25
FORESTS = 2
SIMILARITY = 0.8


def shingle_hashes(text: str | None, shingle: int = SHINGLE) -> np.ndarray:
    """Big-endian XXH64 digests of all shingles; bytes.lower and bytes.split follow ASCII alone, as asked."""
    import xxhash

    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.empty((0, 8), np.uint8)
    data = b" ".join(words)
    ends = np.cumsum([len(w) + 1 for w in words]) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    size = min(shingle, len(words))
    digest = xxhash.xxh64_digest
    hashes = b"".join([digest(data[a:b], SEED) for a, b in zip(starts[: len(words) - size + 1].tolist(), ends[size - 1 :].tolist())])
    return np.frombuffer(hashes, np.uint8).reshape(-1, 8)


def majority(hashes: np.ndarray) -> int:
    """Unsigned 64-bit SimHash: the bits set in over half of the hashes."""
    ones = np.unpackbits(hashes, axis=1).sum(axis=0, dtype=np.int64) if len(hashes) else np.zeros(64, np.int64)
    return int.from_bytes(np.packbits(ones * 2 > len(hashes)).tobytes(), "big")


def fingerprint(text: str | None, shingle: int = SHINGLE) -> int:
    return majority(shingle_hashes(text, shingle))


def fingerprints(docs: DataFrame, keep: list[str], text_col: str = "text", shingle: int = SHINGLE) -> DataFrame:
    """``keep`` columns and ``fp`` (bigint with the bits of the fingerprint)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            codes = [fingerprint(t.as_py(), shingle) for t in batch.column("_fp_text")]
            yield pa.record_batch([*[batch.column(c) for c in keep], pa.array(np.array(codes, np.uint64).view(np.int64))], [*keep, "fp"])

    kinds = [f"`{n}` {k}" for n, k in docs.select(*keep).dtypes]
    return docs.select(*keep, F.col(text_col).alias("_fp_text")).mapInArrow(run, ", ".join([*kinds, "fp bigint"]))


def piece_keys(n: int, max_diff: int = MAX_DIFF, group: int = GROUP) -> list[int]:
    """Masks whose bits two linked fingerprints share in at least one case, chosen so that evenly spread keys hold few."""
    for extra in range(1, 4):
        pieces = max_diff + extra
        cuts = np.linspace(0, 64, pieces + 1).round().astype(int)
        bits = [((1 << int(b)) - 1) ^ ((1 << int(a)) - 1) for a, b in zip(cuts[:-1], cuts[1:])]
        masks = [sum(c) for c in combinations(bits, extra)]
        if n <= group // 4 * (1 << min(m.bit_count() for m in masks)):
            break
    return masks


def _signed(mask: int) -> int:
    return mask - (1 << 64) if mask >= 1 << 63 else mask


def link_edges(codes: DataFrame, n: int, max_diff: int = MAX_DIFF, group: int = GROUP) -> DataFrame:
    """(u, v) edges over distinct ``fp``, at most one per fingerprint, key and block pair, with all components of the links."""
    masks = piece_keys(n, max_diff, group)
    keys = F.explode(F.array(*[F.struct(F.lit(i).alias("k"), F.col("fp").bitwiseAND(F.lit(_signed(m))).alias("part")) for i, m in enumerate(masks)]))
    keyed = codes.select("fp", keys.alias("key")).select("fp", "key.k", "key.part")
    heavy = (
        keyed.groupBy("k", "part").agg(F.count("*").alias("n")).where(F.col("n") > group)
        .select("k", "part", F.ceil(F.col("n") / group).cast("int").alias("blocks"))
    )
    own = F.pmod(F.xxhash64("fp"), F.col("blocks")).cast("int")
    pairs = F.when(F.col("blocks").isNull(), F.array(F.struct(F.lit(0).alias("lo"), F.lit(0).alias("hi")))).otherwise(
        F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), lambda o: F.struct(F.least(o, own).alias("lo"), F.greatest(o, own).alias("hi")))
    )
    tasks = (
        keyed.join(heavy.hint("shuffle_hash"), ["k", "part"], "left").select("fp", "k", "part", F.explode(pairs).alias("b"))
        .select("fp", F.xxhash64("k", "part", "b.lo", "b.hi").alias("task"))
    )
    parts = max(int(codes.sparkSession.conf.get("spark.sql.shuffle.partitions")), 1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.begin("simhash")
        tail_task, tail_fp = np.empty(0, np.int64), np.empty(0, np.int64)
        for batch in batches:
            task = np.concatenate([tail_task, batch.column("task").to_numpy(zero_copy_only=False)])
            fp = np.concatenate([tail_fp, batch.column("fp").to_numpy(zero_copy_only=False)])
            cut = int(np.searchsorted(task, task[-1], "left")) if len(task) else 0
            tail_task, tail_fp = task[cut:], fp[cut:]
            if cut:
                yield _edges(task[:cut], fp[:cut], max_diff)
        if len(tail_task):
            yield _edges(tail_task, tail_fp, max_diff)

    return tasks.repartition(parts, "task").sortWithinPartitions("task").mapInArrow(run, "u bigint, v bigint")


def _edges(task: np.ndarray, fp: np.ndarray, max_diff: int) -> pa.RecordBatch:
    """Links of each run of equal ``task``: from every code to the first of its local component.

    Two keys that hash to one task only add rows to an exact search.
    """
    us, vs = [], []
    bounds = np.concatenate([[0], np.flatnonzero(np.diff(task)) + 1, [len(task)]])
    sizes = np.diff(bounds)
    two = bounds[:-1][sizes == 2]  # the commonest group of more than one
    if len(two):
        a, b = fp[two], fp[two + 1]
        near = (np.bitwise_count(a.view(np.uint64) ^ b.view(np.uint64)) <= max_diff) & (a != b)
        us.append(a[near])
        vs.append(b[near])
    for i in np.flatnonzero(sizes > 2):
        index = GrayIndex(fp[bounds[i] : bounds[i + 1]].view(np.uint64))
        label = index.components(max_diff)
        own = np.flatnonzero(label != np.arange(len(label)))
        to = label[own]
        us.append(index.codes[own].view(np.int64))
        vs.append(index.codes[to].view(np.int64))
    join = lambda xs: pa.array(np.concatenate(xs) if xs else np.empty(0, np.int64))
    return pa.record_batch([join(us), join(vs)], ["u", "v"])


def near_duplicate_groups(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE, max_diff: int = MAX_DIFF
) -> DataFrame:
    """(doc_id, fp, component_id), one row per row of ``docs``."""
    ids = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias("text"))
    rows = common.stored(fingerprints(ids, ["doc_id"], "text", shingle), "simhash")
    codes = common.checkpoint(rows.groupBy("fp").agg(F.min("doc_id").alias("first_doc")))
    edges = link_edges(codes.select("fp"), codes.count(), max_diff)
    roots = connected_components(edges)
    named = codes.join(roots, codes["fp"] == roots["node"], "left").select("fp", "first_doc", F.coalesce("root", "fp").alias("root"))
    least = named.groupBy("root").agg(F.min("first_doc").alias("component_id"))
    known = named.join(least, "root").select("fp", "component_id")
    return rows.join(known, "fp").select("doc_id", "fp", "component_id")


def shingle_set(text: str | None, shingle: int = SHINGLE) -> np.ndarray:
    """Distinct shingle hashes in order."""
    return np.unique(np.ascontiguousarray(shingle_hashes(text, shingle)).view(">u8").ravel().astype(np.uint64))


def prefix_size(n: int, similarity: float) -> int:
    return n - math.ceil(similarity * n - 1e-9) + 1


def frequent_shingles(texts: DataFrame, shingle: int) -> tuple[np.ndarray, np.ndarray]:
    """Shingle hashes of many texts, in order, and about how many hold each.

    Counted over a part of the texts: it only orders shingles and sizes blocks, so no result
    depends on it. The least count grows with the input, so the list is bounded.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in common.sliced("simhash", batches):
            sets = [shingle_set(t.as_py(), shingle) for t in batch.column(0)]
            yield pa.record_batch([pa.array(np.concatenate(sets).view(np.int64) if sets else np.empty(0, np.int64))], ["h"])

    part = common.checkpoint(texts.where(F.pmod("tid", F.lit(PART)) == 0).dropDuplicates(["tid"]).select("text"))
    least = max(OFTEN, part.count() // 2000)
    table = part.mapInArrow(run, "h bigint").groupBy("h").agg(F.count("*").alias("n")).where(F.col("n") >= least).toArrow()
    often, n = table["h"].to_numpy().view(np.uint64), table["n"].to_numpy()
    order = np.argsort(often)
    return often[order], n[order] * PART


def prefixes(texts: DataFrame, often: np.ndarray, shingle: int, similarity: float) -> DataFrame:
    """doc, tid, fp, the number of distinct shingles, those of the prefix and a bitmap of all.

    In any one order of all shingles, two sets of Jaccard ``similarity`` or more share one
    among their first ``prefix_size``; frequent shingles come last in this order.
    """
    shared = texts.sparkSession.sparkContext.broadcast(often)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        often = shared.value
        for batch in common.sliced("simhash", batches):
            codes, sizes, firsts, maps = [], [], [], []
            for t in batch.column("text"):
                hashes = shingle_hashes(t.as_py(), shingle)
                codes.append(majority(hashes))
                own = np.unique(np.ascontiguousarray(hashes).view(">u8").ravel().astype(np.uint64))
                sizes.append(len(own))
                bits = np.zeros(BITMAP, np.uint8)
                bits[(own % np.uint64(BITMAP)).astype(np.int64)] = 1
                maps.append(np.packbits(bits).view(np.int64))
                if len(often) and len(own):
                    late = often[np.minimum(np.searchsorted(often, own), len(often) - 1)] == own
                    own = np.concatenate([own[~late], own[late]])
                firsts.append((own[: prefix_size(len(own), similarity)].copy() if len(own) else np.zeros(1, np.uint64)).view(np.int64))
            yield pa.record_batch(
                [batch.column("doc"), batch.column("tid"), pa.array(np.array(codes, np.uint64).view(np.int64)), pa.array(sizes, pa.int32()), pa.array(firsts, pa.list_(pa.int64())), pa.array(maps, pa.list_(pa.int64()))],
                ["doc", "tid", "fp", "size", "prefix", "bitmap"],
            )

    return texts.mapInArrow(run, "doc bigint, tid bigint, fp bigint, size int, prefix array<bigint>, bitmap array<bigint>")


def candidate_pairs(
    texts: DataFrame, often: np.ndarray, counts: np.ndarray, similarity: float, max_diff: int | None, forest: int | None, group: int = GROUP
) -> DataFrame:
    """Distinct (a, b) of texts of different ``root`` that share a prefix shingle and may reach ``similarity``.

    With ``forest`` only links that join the components inside a batch of tasks, no more than it
    has texts: the nearest fingerprints first if 0, in another order for every other number.
    Without, all of them.
    """
    spark = texts.sparkSession
    keyed = texts.select("tid", "fp", "size", "root", F.posexplode("prefix").alias("pos", "h"))
    many = counts > group
    # an Arrow table: rows of Python would start workers of another kind on the executors
    blocks = spark.createDataFrame(pa.table({"h": pa.array(often[many].view(np.int64), pa.int64()), "blocks": pa.array(-(-counts[many] // group), pa.int32())}))
    own = F.pmod(F.xxhash64("tid"), F.col("blocks")).cast("int")
    cut = F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), lambda o: F.xxhash64("h", F.least(o, own), F.greatest(o, own)))
    tasks = keyed.join(F.broadcast(blocks), "h", "left").select(
        F.explode(F.when(F.col("blocks").isNull(), F.array("h")).otherwise(cut)).alias("task"), "tid", "fp", "size", "root", "pos"
    )
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 1)
    names = ["task", "tid", "fp", "size", "root", "pos"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.begin("simhash")
        tail = None
        for batch in batches:
            cols = [batch.column(c).to_numpy(zero_copy_only=False) for c in names]
            cols = cols if tail is None else [np.concatenate(x) for x in zip(tail, cols)]
            end = int(np.searchsorted(cols[0], cols[0][-1], "left")) if len(cols[0]) else 0
            tail = [c[end:] for c in cols]
            yield from _candidates([c[:end] for c in cols], similarity, max_diff, forest)
        if tail is not None:
            yield from _candidates(tail, similarity, max_diff, forest)

    return tasks.repartition(parts, "task").sortWithinPartitions("task").mapInArrow(run, "a bigint, b bigint").distinct()


def _candidates(cols: list[np.ndarray], similarity: float, max_diff: int | None, forest: int | None) -> Iterator[pa.RecordBatch]:
    """Pairs inside each run of equal task, made in chunks of about ``PAIRS``; a forest is carried from chunk to chunk."""
    task, tid, fp, size, root, pos = cols
    if not len(task):
        return
    size, fp = size.astype(np.int64), fp.view(np.uint64)
    bounds = np.concatenate([[0], np.flatnonzero(np.diff(task)) + 1, [len(task)]])
    later = np.repeat(bounds[1:], np.diff(bounds)) - np.arange(len(task)) - 1
    before = np.concatenate([[0], np.cumsum(later)])
    known, number = np.unique(root, return_inverse=True)
    held = np.empty((2, 0), np.int64)
    first = 0
    while first < len(task):
        end = max(first + 1, int(np.searchsorted(before, before[first] + PAIRS, "right")) - 1)
        n = later[first:end]
        a = np.repeat(np.arange(first, end), n)
        b = a + 1 + np.arange(len(a)) - np.repeat(before[first:end] - before[first], n)
        first = end
        # at the first shingle that two texts share, no more than what follows in both can be shared
        most = np.minimum(size[a] - pos[a], size[b] - pos[b])
        keep = (root[a] != root[b]) & ((1 + similarity) * most >= similarity * (size[a] + size[b]) - 1e-6)
        if max_diff is not None:
            keep &= np.bitwise_count(fp[a] ^ fp[b]) <= max_diff
        a, b = a[keep], b[keep]
        if not len(a):
            continue
        if forest is not None:
            a, b = np.concatenate([held[0], a]), np.concatenate([held[1], b])
        lo, hi = np.minimum(tid[a], tid[b]), np.maximum(tid[a], tid[b])
        if forest is not None:
            with np.errstate(over="ignore"):
                mixed = (lo * np.int64(0x9E3779B97F4A7C1 + 2 * forest)) ^ (hi * np.int64(0x2545F4914F6CDD1D))
                mixed = (mixed ^ (mixed >> np.int64(29))) * np.int64(0x3C79AC492BA7B653 + 2 * forest)
            order = np.lexsort((mixed, np.bitwise_count(fp[a] ^ fp[b]))) if forest == 0 else np.argsort(mixed, kind="stable")
            own = order[spanning(len(known), number[a[order]], number[b[order]])]
            held = np.stack([a[own], b[own]])
            continue
        order = np.lexsort((hi, lo))
        lo, hi = lo[order], hi[order]
        new = np.concatenate([[True], (lo[1:] != lo[:-1]) | (hi[1:] != hi[:-1])])
        yield pa.record_batch([pa.array(lo[new]), pa.array(hi[new])], ["a", "b"])
    if held.size:
        ends = np.sort(tid[held], axis=0)
        yield pa.record_batch([pa.array(ends[0]), pa.array(ends[1])], ["a", "b"])


def _bloom_places(ids: np.ndarray) -> list[np.ndarray]:
    ids = np.asarray(ids, np.int64).view(np.uint64)
    with np.errstate(over="ignore"):
        return [((ids * np.uint64(m)) >> np.uint64(64 - BLOOM_BITS)).astype(np.int64) for m in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F)]


def bloom_words(ids: DataFrame) -> np.ndarray:
    """A Bloom filter over ``tid``: 2 ** BLOOM_BITS bits whatever the number of ids, put together by partial aggregation."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.begin("simhash")
        for batch in batches:
            at = np.concatenate(_bloom_places(batch.column(0).to_numpy(zero_copy_only=False)))
            yield pa.record_batch([pa.array(at >> 6), pa.array(np.left_shift(np.uint64(1), (at & 63).astype(np.uint64)).view(np.int64))], ["word", "bits"])

    table = ids.select("tid").mapInArrow(run, "word bigint, bits bigint").groupBy("word").agg(F.bit_or("bits").alias("bits")).toArrow()
    words = np.zeros(1 << (BLOOM_BITS - 6), np.uint64)
    words[table["word"].to_numpy()] = table["bits"].to_numpy().view(np.uint64)
    return words


def shingle_sets(texts: DataFrame, asked: DataFrame, shingle: int) -> DataFrame:
    """(tid, shingles): all distinct shingle hashes of each text that is ``asked`` for (tid, doc).

    Texts stay where they are read: a Bloom filter of fixed size passes over most that are not
    asked for, the rest become sets there, and a join leaves the ones asked for.
    """
    shared = texts.sparkSession.sparkContext.broadcast(bloom_words(asked))  # 2 ** BLOOM_BITS bits

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = shared.value
        for batch in common.sliced("simhash", batches):
            hit = np.ones(batch.num_rows, bool)
            for at in _bloom_places(batch.column("tid").to_numpy(zero_copy_only=False)):
                hit &= ((words[at >> 6] >> (at & 63).astype(np.uint64)) & np.uint64(1)).astype(bool)
            batch = batch.filter(pa.array(hit))
            if batch.num_rows:
                sets = [shingle_set(t.as_py(), shingle).view(np.int64) for t in batch.column("text")]
                yield pa.record_batch([batch.column("tid"), batch.column("doc"), pa.array(sets, pa.list_(pa.int64()))], ["tid", "doc", "shingles"])

    found = texts.select("tid", "doc", "text").mapInArrow(run, "tid bigint, doc bigint, shingles array<bigint>")
    return found.join(asked.hint("shuffle_hash"), ["tid", "doc"]).dropDuplicates(["tid", "doc"]).select("tid", "shingles")


def possible_pairs(pairs: DataFrame, texts: DataFrame, similarity: float) -> DataFrame:
    """The (a, b) that their bitmaps leave possible: as many shingles differ as bits do, or more."""
    own = texts.select("tid", "size", "bitmap")
    first = pairs.withColumnRenamed("a", "tid").join(own, "tid").select(F.col("tid").alias("a"), F.col("b").alias("tid"), F.col("size").alias("m"), F.col("bitmap").alias("x"))
    bits = F.aggregate(F.zip_with("x", "bitmap", lambda p, q: F.bit_count(p.bitwiseXOR(q))), F.lit(0), lambda s, n: s + n)
    both = F.col("m") + F.col("size")
    return first.join(own, "tid").where((1 + similarity) * (both - bits) / 2 >= similarity * both - 1e-6).select("a", F.col("tid").alias("b"))


def similar_pairs(pairs: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """The (a, b) whose shingle sets have Jaccard ``similarity`` or more, or are both empty."""
    first = pairs.withColumnRenamed("a", "tid").join(sets, "tid").select(F.col("tid").alias("a"), F.col("b").alias("tid"), F.col("shingles").alias("x"))
    both = F.size(F.array_intersect("x", "shingles"))
    either = F.size("x") + F.size("shingles") - both
    return first.join(sets, "tid").where((either == 0) | (both / F.greatest(either, F.lit(1)) >= similarity)).select("a", F.col("tid").alias("b"))


def verified_pairs(pairs: DataFrame, texts: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """``similar_pairs`` in batches, as a pair carries a whole set to the other text: a batch
    ships about ``SHIPPED`` of the bytes that the sets of all texts have, and its shuffle files go before the next."""
    free = pairs.sparkSession._jvm.java.lang.System.gc
    ends = pairs.withColumnRenamed("a", "tid").join(texts.select("tid", "size"), "tid").agg(F.sum("size")).first()[0] or 0
    whole = texts.agg(F.sum("size")).first()[0] or 0
    batches = max(1, math.ceil(ends / max(SHIPPED * whole, 1)))
    out = None
    for batch in range(batches):
        own = pairs.where(F.pmod(F.xxhash64("a", "b"), F.lit(batches)) == batch)
        passed = common.checkpoint(similar_pairs(own, sets, similarity))
        out = passed if out is None else out.unionByName(passed)
        free()
    return out


def indexed_pairs(texts: DataFrame, max_diff: int) -> DataFrame:
    """Distinct (a, b) of ``tid``: links of the Gray index, each between the least texts of two fingerprints, and every other text with the least of its own."""
    codes = common.checkpoint(texts.groupBy("fp").agg(F.min("tid").alias("least")))
    first, second = codes.toDF("u", "a"), codes.toDF("v", "b")
    near = link_edges(codes.select("fp"), codes.count(), max_diff).join(first, "u").join(second, "v").select("a", "b")
    same = texts.join(codes, "fp").where("tid <> least").select(F.col("least").alias("a"), F.col("tid").alias("b"))
    return near.unionByName(same).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def similar_components(keyed: DataFrame, nodes: DataFrame, shingle: int, max_diff: int | None, similarity: float) -> DataFrame:
    """(node, root) of the texts that some verified pair joins.

    Links that the Gray index finds between fingerprints are verified first and make the first
    components. What lies beyond its radius follows: every candidate that shares a prefix
    shingle is verified or lies inside a component already. A few rounds verify only links that
    join components, so that a large group is joined without its pairs; the last round takes
    every candidate left between different components. Shuffle files of a step are let go
    before the next.
    """
    gc = keyed.sparkSession._jvm.java.lang.System.gc

    def free() -> None:
        common.release()
        gc()

    often, counts = frequent_shingles(keyed, shingle)
    rows = prefixes(keyed, often, shingle, similarity)
    texts = rows.groupBy("tid").agg(*[F.first(c).alias(c) for c in ("fp", "size", "prefix", "bitmap")])
    texts = common.stored(texts, "simhash-prefixes")

    def verified(pairs: DataFrame) -> DataFrame:
        fresh = common.checkpoint(possible_pairs(pairs, texts, similarity))
        if fresh.isEmpty():
            return fresh
        asked = fresh.select(F.explode(F.array("a", "b")).alias("tid")).distinct().join(nodes, "tid").select("tid", F.col("first_doc").alias("doc"))
        sets = common.stored(shingle_sets(keyed, common.checkpoint(asked), shingle), "simhash-sets")
        free()
        passed = verified_pairs(fresh, texts, sets, similarity)
        common.discard(sets)
        return passed

    named = lambda df: df.join(roots.withColumnRenamed("node", "tid"), "tid", "left").withColumn("root", F.coalesce("root", "tid"))
    seen = common.checkpoint(indexed_pairs(texts, MAX_DIFF if max_diff is None else min(MAX_DIFF, max_diff)))
    roots = common.checkpoint(connected_components(verified(seen), "a", "b"))
    live = named(texts)
    for step in range(FORESTS + 1):
        free()
        found = common.checkpoint(candidate_pairs(live, often, counts, similarity, max_diff, step if step < FORESTS else None))
        free()
        ends = found.select(F.explode(F.array("a", "b")).alias("tid")).distinct()
        if step == 0:  # a component without a candidate now has none later
            every, texts = texts, common.stored(live.join(named(ends).select("root").distinct(), "root", "left_semi").drop("root"), "simhash-linked")
            common.discard(every)
        links = verified(found.join(seen, ["a", "b"], "left_anti"))
        roots = common.checkpoint(connected_components(links.unionByName(roots.toDF("a", "b")), "a", "b"))
        if step == FORESTS or found.isEmpty():
            break
        seen = seen.unionByName(found)
        live = named(texts).join(named(ends).select("root").distinct(), "root", "left_semi")
    free()
    return roots


def drop_near_duplicates(
    docs: DataFrame, shingle: int, max_diff: int | None = None, similarity: float = SIMILARITY, id_col: str = "doc_id", text_col: str = "text"
) -> DataFrame:
    """The rows of ``docs`` that stay: of each group the one of least id.

    Groups are the components of the pairs whose shingle sets have Jaccard ``similarity`` or
    more and, with ``max_diff``, whose fingerprints are within that many bits. Texts without a
    word are copies of each other; of repeated rows of one id and text one stays.
    """
    names = docs.columns
    keyed = docs.select(F.coalesce(F.col(id_col).cast("bigint"), F.lit(-(2**63))).alias("doc"), F.xxhash64(text_col).alias("tid"), F.col(text_col).alias("text"))
    nodes = common.checkpoint(keyed.groupBy("tid").agg(F.min("doc").alias("first_doc"), F.count("*").alias("n"), F.count_distinct("doc").alias("ids")))
    roots = similar_components(keyed, nodes, shingle, max_diff, similarity)
    named = nodes.join(roots, nodes["tid"] == roots["node"], "left").select("tid", "first_doc", F.coalesce("root", "tid").alias("root"))
    keeper = named.groupBy("root").agg(F.min(F.struct("first_doc", "tid")).alias("k")).select(F.col("k.first_doc").alias("_sim_doc"), F.col("k.tid").alias("_sim_tid"))
    own = (F.coalesce(docs[id_col].cast("bigint"), F.lit(-(2**63))) == keeper["_sim_doc"]) & (F.xxhash64(docs[text_col]) == keeper["_sim_tid"])
    kept = docs.join(keeper.hint("shuffle_hash"), own)
    if nodes.where("n > ids").limit(1).count():
        kept = kept.dropDuplicates(["_sim_doc", "_sim_tid"])
    return kept.select(*[F.col(f"`{c}`") for c in names])


def op8_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicate_groups(common.table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")
