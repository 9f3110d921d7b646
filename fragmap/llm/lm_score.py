"""LM scoring by context-tree weighting, beside the unigram base.

The model's text is the base's: words of the text with A-Z lower-cased, joined by one
space, and one end. Every text is scored whole by trees over ``DEPTH`` bytes of context
at any input size; nothing of the model is held in one place but the nodes of the two
nearest context bytes (at most 256 * 256 * 255).

1. Texts are read once, in blocks of about ``BLOCK_BYTES``. A block keeps its texts
   compressed and asks about its distinct windows and words, packed by hash bucket.
2. A bucket adds up the counts of its windows over all blocks, each window once.
3. Windows are dealt by their nearest ``SPLIT`` context bytes, which keeps subtrees
   whole; depths from ``SPLIT`` down are built there, those above on the driver.
4. The same subtrees score each distinct window, seen in training or not.
5. A bucket answers each block's question in the order asked, so answers carry no keys;
   word counts are answered in the same way. A block adds up what its texts need.

Rows that cross the network follow the distinct windows and words of a block, and what
a task holds follows the number of partitions, never one hot key: a block asks about a
window once, however often it has it.

Defined cases: a null text is empty and consists of its end; a null id is in the
training part; repeated rows count and are scored each time; without training rows the
trees are empty and every bit has chance 1/2; an empty table gives an empty result;
columns other than the id and the text are not read.
"""

from __future__ import annotations

import math
import pickle
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fragmap.llm import common
from fragmap.llm.context_tree import BITS, counted, log10_chances, lower_levels, upper_levels, windows

DEPTH = 5
SPLIT = 3
BLOCK_BYTES = 32 << 20
PIECE_BYTES = 4 << 20
CHUNK_BYTES = 4 << 20
CHUNK_TEXTS = 1 << 16
HOLD = 1_000_000
FOLDS = 5
HELD_OUT = 1
TEXTS, WINDOWS, WORDS = 0, 1, 2
_ASKED = "kind int, block bigint, bucket int, keys binary, counts binary"
_ZSTD = 6


def held_out(id_col: str = "doc_id") -> Column:
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % FOLDS == HELD_OUT, F.lit(False))


def zip_bytes(data: bytes) -> bytes:
    return len(data).to_bytes(8, "little") + pa.Codec("zstd", _ZSTD).compress(data, asbytes=True)


def unzip_bytes(data: bytes) -> bytes:
    return pa.decompress(data[8:], int.from_bytes(data[:8], "little"), "zstd", asbytes=True)


def pack(values: np.ndarray) -> bytes:
    """Byte planes, which compress well: the high bytes of counts and differences are nearly all zero."""
    values = np.ascontiguousarray(values)
    return zip_bytes(values.view(np.uint8).reshape(len(values), values.itemsize).T.tobytes())


def unpack(data: bytes, kind: type) -> np.ndarray:
    planes = np.frombuffer(unzip_bytes(data), np.uint8)
    size = np.dtype(kind).itemsize
    return np.ascontiguousarray(planes.reshape(size, len(planes) // size).T).view(kind).ravel()


def pack_sorted(keys: np.ndarray) -> bytes:
    return pack(np.diff(keys, prepend=np.uint64(0)))


def unpack_sorted(data: bytes) -> np.ndarray:
    return np.cumsum(unpack(data, np.uint64), dtype=np.uint64)


def bucket_of(keys: np.ndarray, buckets: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        return ((keys * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(33)).astype(np.int64) % buckets


def _chunks(texts: list[bytes]) -> Iterator[list[bytes]]:
    part, size = [], 0
    for t in texts:
        part.append(t)
        size += len(t) + 1
        if size >= CHUNK_BYTES or len(part) == CHUNK_TEXTS:
            yield part
            part, size = [], 0
    if part:
        yield part


def words_of(text: bytes) -> list[bytes]:
    """bytes.lower and bytes.split follow ASCII alone, as asked."""
    return text.lower().split()


def merged(parts: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    return counted(np.concatenate([k for k, _ in parts]), np.concatenate([n for _, n in parts]))


def _window_counts(texts: list[bytes], learn: list[bool], depth: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct windows of all texts and how often those to learn from have each."""
    held: list[tuple[np.ndarray, np.ndarray]] = []
    size = 0
    for wanted in (True, False):
        for chunk in _chunks([t for t, x in zip(texts, learn) if x == wanted]):
            keys, n = counted(windows(chunk, depth)[0])
            held.append((keys, n if wanted else np.zeros(len(n), np.int64)))
            size += len(keys)
            if size > HOLD:
                held = [merged(held)]
                size = 0
    return merged(held)


def _distinct_windows(texts: list[bytes], depth: int) -> np.ndarray:
    found = np.empty(0, np.uint64)
    for chunk in _chunks(texts):
        found = counted(np.concatenate([found, counted(windows(chunk, depth)[0])[0]]))[0]
    return found


class Vocabulary:
    """Words of a block's normalised texts: distinct ones by hash bucket and in order, and each token's place among them."""

    def __init__(self, texts: list[bytes], buckets: int):
        # a space after the last word leaves an empty word there, which is the end
        split = pc.split_pattern(pa.array([t + b" " if t else b"" for t in texts], pa.large_binary()), " ")
        self.n_tokens = np.diff(split.offsets.to_numpy()).astype(np.int64)
        coded = split.flatten().dictionary_encode()
        bucket = np.fromiter(map(zlib.crc32, coded.dictionary.to_pylist()), np.int64, len(coded.dictionary)) % buckets
        rank = np.empty(len(bucket), np.int64)
        rank[pc.sort_indices(coded.dictionary).to_numpy()] = np.arange(len(bucket))
        order = np.lexsort((rank, bucket))
        place = np.empty(len(order), np.int32)
        place[order] = np.arange(len(order), dtype=np.int32)
        self.words = coded.dictionary.take(pa.array(order))
        self.tokens = place[coded.indices.to_numpy()]
        self.buckets, starts = np.unique(bucket[order], return_index=True)
        self.cuts = list(zip(starts.tolist(), [*starts[1:].tolist(), len(order)]))


def _ask(block: int, docs: list[tuple], buckets: int, depth: int) -> Iterator[pa.RecordBatch]:
    """A block's rows: its texts in pieces, and per bucket its distinct windows and words with their training counts."""

    def rows(kind: int, bucket: list, keys: list, counts: list) -> pa.RecordBatch:
        n = len(keys)
        return pa.record_batch(
            [pa.array([kind] * n, pa.int32()), pa.array([block] * n, pa.int64()), pa.array(bucket, pa.int32()), pa.array(keys, pa.binary()), pa.array(counts, pa.binary())],
            ["kind", "block", "bucket", "keys", "counts"],
        )

    texts, learn = [b" ".join(words_of(t)) for _, t, _ in docs], [not out for *_, out in docs]
    first = number = 0
    while first < len(docs):
        end = first
        size = 0
        while end < len(docs) and (end == first or size + len(texts[end]) <= PIECE_BYTES):
            size += len(texts[end])
            end += 1
        data = zip_bytes(pickle.dumps(([d for d, *_ in docs[first:end]], learn[first:end], texts[first:end]), protocol=5))
        yield rows(TEXTS, [number], [data], [None])
        first, number = end, number + 1
    keys, n = _window_counts(texts, learn, depth)
    of = bucket_of(keys, buckets)
    order = np.argsort(of, kind="stable")
    keys, n = keys[order], n[order]
    own, starts = np.unique(of[order], return_index=True)
    cuts = list(zip(starts.tolist(), [*starts[1:].tolist(), len(keys)]))
    yield rows(WINDOWS, own.tolist(), [pack_sorted(keys[a:b]) for a, b in cuts], [pack(n[a:b]) for a, b in cuts])
    del keys, n, of, order
    known = Vocabulary(texts, buckets)
    times = np.bincount(known.tokens[np.repeat(np.array(learn), known.n_tokens)], minlength=len(known.words)).astype(np.int64)
    yield rows(WORDS, known.buckets.tolist(), [zip_bytes(b"\n".join(known.words[a:b].to_pylist())) for a, b in known.cuts], [pack(times[a:b]) for a, b in known.cuts])


def questions(docs: DataFrame, buckets: int, depth: int) -> DataFrame:
    """Rows of all blocks. ``docs``: doc_id, text, held_out.

    Blocks are runs of rows of a partition, numbered by partition and place, so a task that
    is run again makes the same ones.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        block = TaskContext.get().partitionId() << 32
        held: list[tuple] = []
        size = 0
        for batch in batches:
            texts = pc.fill_null(batch.column(1), "").cast(pa.binary())
            for doc, text, out in zip(batch.column(0), texts, batch.column(2)):
                held.append((doc.as_py(), text.as_py(), out.as_py()))
                size += len(held[-1][1]) + 1
                if size >= BLOCK_BYTES:
                    yield from _ask(block, held, buckets, depth)
                    held, size, block = [], 0, block + 1
        if held:
            yield from _ask(block, held, buckets, depth)

    return docs.mapInArrow(run, _ASKED)


def window_counts(asked: DataFrame, buckets: int) -> DataFrame:
    """(window, n): every distinct window of all texts and how often the training part has it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []
        size = 0
        for batch in batches:
            for keys, counts in zip(batch.column("keys"), batch.column("counts")):
                held.append((unpack_sorted(keys.as_py()), unpack(counts.as_py(), np.int64)))
                size += len(held[-1][0])
                if size > HOLD:
                    held = [merged(held)]
                    size = 0
        if held:
            keys, n = merged(held)
            for at in range(0, len(keys), 100_000):
                yield pa.record_batch([pa.array(keys[at : at + 100_000].view(np.int64)), pa.array(n[at : at + 100_000])], ["window", "n"])

    rows = asked.where(F.col("kind") == WINDOWS).select("bucket", "keys", "counts")
    return rows.repartition(buckets, "bucket").mapInArrow(run, "window bigint, n bigint")


def _by_subtree(counts: DataFrame, buckets: int) -> DataFrame:
    nearest = F.shiftrightunsigned("window", BITS).bitwiseAND(F.lit((1 << (BITS * SPLIT)) - 1))
    return counts.repartition(buckets, nearest)


def _whole(batches: Iterator[pa.RecordBatch]) -> tuple[np.ndarray, np.ndarray]:
    parts = [(b.column("window").to_numpy().view(np.uint64), b.column("n").to_numpy()) for b in batches]
    if not parts:
        return np.empty(0, np.uint64), np.empty(0, np.int64)
    return np.concatenate([k for k, _ in parts]), np.concatenate([n for _, n in parts])


def upper_tree(counts: DataFrame, buckets: int, depth: int):
    """Nodes of fewer than ``SPLIT`` bytes of context, made of sums that the subtrees send up.

    At most 256 ** (SPLIT - 1) contexts of 255 nodes, whatever the input's size.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, n = _whole(batches)
        if len(keys):
            for j, (number, total, ones, rest) in lower_levels(keys, n, depth, SPLIT)[1].items():
                yield pa.record_batch(
                    [pa.array(np.full(len(number), j, np.int32)), pa.array(number.view(np.int64)), pa.array(total), pa.array(ones), pa.array(rest)], ["j", "number", "total", "ones", "rest"]
                )

    sent = _by_subtree(counts.where("n > 0"), buckets).mapInArrow(run, "j int, number bigint, total bigint, ones bigint, rest double")
    table = sent.groupBy("j", "number").agg(F.sum("total").alias("total"), F.sum("ones").alias("ones"), F.sum("rest").alias("rest")).toArrow()
    bit = table["j"].to_numpy()
    columns = [table["number"].to_numpy().view(np.uint64), *(table[c].to_numpy() for c in ("total", "ones", "rest"))]
    sums = {}
    for j in range(BITS):
        own = np.flatnonzero(bit == j)
        own = own[np.argsort(columns[0][own], kind="stable")]
        sums[j] = tuple(c[own] for c in columns)
    return upper_levels(sums, SPLIT)


def window_scores(counts: DataFrame, buckets: int, depth: int) -> DataFrame:
    """(bucket, window, score): log10 of the chance of each distinct window's byte after its context."""
    shared = counts.sparkSession.sparkContext.broadcast(upper_tree(counts, buckets, depth))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, n = _whole(batches)
        if not len(keys):
            return
        levels = shared.value | lower_levels(keys, n, depth, SPLIT)[0]
        for at in range(0, len(keys), 100_000):
            part = keys[at : at + 100_000]
            yield pa.record_batch(
                [pa.array(bucket_of(part, buckets).astype(np.int32)), pa.array(part.view(np.int64)), pa.array(log10_chances(levels, depth, part).astype(np.float32))], ["bucket", "window", "score"]
            )

    return _by_subtree(counts, buckets).mapInArrow(run, "bucket int, window bigint, score float")


def window_answers(asked: DataFrame, scores: DataFrame) -> DataFrame:
    """(kind, block, bucket, keys): the scores of each block's windows, bucket by bucket in the order asked."""

    def run(asked: pa.Table, known: pa.Table) -> pa.Table:
        window, score = known["window"].to_numpy().view(np.uint64), known["score"].to_numpy()
        order = np.argsort(window)
        window, score = window[order], score[order]
        said = [pack(score[np.searchsorted(window, unpack_sorted(k.as_py()))]) for k in asked["keys"]]
        return pa.table({"kind": asked["kind"], "block": asked["block"], "bucket": asked["bucket"], "keys": pa.array(said, pa.binary())})

    rows = asked.where(F.col("kind") == WINDOWS).select("kind", "block", "bucket", "keys")
    return rows.groupBy("bucket").cogroup(scores.groupBy("bucket")).applyInArrow(run, "kind int, block bigint, bucket int, keys binary")


def word_answers(asked: DataFrame) -> DataFrame:
    """(kind, block, bucket, keys, total, kinds): training counts of each block's words in the order asked,
    and, in one row a bucket, the bucket's share of the training tokens and of their distinct words."""

    def run(asked: pa.Table) -> pa.Table:
        counts: dict[bytes, int] = {}
        lists = [unzip_bytes(k.as_py()).split(b"\n") for k in asked["keys"]]
        for words, n in zip(lists, asked["counts"]):
            for w, x in zip(words, unpack(n.as_py(), np.int64).tolist()):
                counts[w] = counts.get(w, 0) + x
        said = [pack(np.array([counts[w] for w in words], np.int64)) for words in lists]
        first = [sum(counts.values())] + [0] * (len(lists) - 1)
        kinds = [sum(x > 0 for x in counts.values())] + [0] * (len(lists) - 1)
        return pa.table({
            "kind": asked["kind"], "block": asked["block"], "bucket": asked["bucket"], "keys": pa.array(said, pa.binary()),
            "total": pa.array(first, pa.int64()), "kinds": pa.array(kinds, pa.int64()),
        })

    rows = asked.where(F.col("kind") == WORDS)
    return rows.groupBy("bucket").applyInArrow(run, "kind int, block bigint, bucket int, keys binary, total bigint, kinds bigint")


def _chunk_scores(texts: list[bytes], keys: np.ndarray, value: np.ndarray, depth: int) -> np.ndarray:
    """The sum of each text's window values; windows are sorted with their text's number beside them where 64 bits hold both."""
    own, starts = windows(texts, depth)
    text = np.repeat(np.arange(len(texts), dtype=np.uint64), np.diff(starts))
    if BITS * (depth + 1) + 16 <= 64:
        own = np.sort((own << np.uint64(16)) | text)
        own, text = own >> np.uint64(16), own & np.uint64(0xFFFF)
    else:
        order = np.argsort(own)
        own, text = own[order], text[order]
    here, times = counted(own)
    return np.bincount(text.astype(np.int64), np.repeat(value[np.searchsorted(keys, here)], times), len(texts))


def _score_block(part: pa.Table, buckets: int, depth: int, total: int, kinds: int) -> pa.Table:
    """The rows of a block's texts from its pieces and the answers to it."""
    rows: dict[int, dict[int, bytes]] = {TEXTS: {}, WINDOWS: {}, WORDS: {}}
    for kind, bucket, keys in zip(part["kind"].to_pylist(), part["bucket"].to_pylist(), part["keys"]):
        rows[kind][bucket] = keys
    pieces = [pickle.loads(unzip_bytes(d.as_py())) for _, d in sorted(rows[TEXTS].items())]
    texts = [t for p in pieces for t in p[2]]
    keys = _distinct_windows(texts, depth)
    order = np.argsort(bucket_of(keys, buckets), kind="stable")
    value = np.empty(len(keys), np.float64)
    value[order] = np.concatenate([unpack(d.as_py(), np.float32) for _, d in sorted(rows[WINDOWS].items())])
    score = np.concatenate([_chunk_scores(chunk, keys, value, depth) for chunk in _chunks(texts)])
    del keys, value, order
    known = Vocabulary(texts, buckets)
    count = np.concatenate([unpack(d.as_py(), np.int64) for _, d in sorted(rows[WORDS].items())])
    n_tokens = known.n_tokens
    starts = np.concatenate([[0], np.cumsum(n_tokens)[:-1]])
    base = np.add.reduceat(np.log10(count + 0.5)[known.tokens], starts) - n_tokens * math.log10(total + 0.5 * (kinds + 1))
    known = np.add.reduceat((count > 0).astype(np.int64)[known.tokens], starts)
    size = np.array([len(t) + 1 for t in texts], np.int64)
    return pa.table({
        "doc_id": pa.array([d for p in pieces for d in p[0]], pa.int64()), "held_out": pa.array([not x for p in pieces for x in p[1]]),
        "n_tokens": pa.array(n_tokens), "n_known": pa.array(known), "train_tokens": pa.array(np.full(len(texts), total, np.int64)), "base_score": pa.array(base),
        "score": pa.array(score), "n_bytes": pa.array(size), "bits_per_byte": pa.array(-score / math.log10(2) / size),
    })


def score_texts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", out: Column | None = None, depth: int = DEPTH) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score, n_bytes, bits_per_byte of every row.

    ``out`` marks rows that are scored but not learned from. ``bits_per_byte`` is the code
    length by the trees; the end counts as a byte.
    """
    spark = docs.sparkSession
    buckets = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 1)
    rows = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias("text"), (held_out(id_col) if out is None else out).alias("held_out"))
    asked = common.stored(questions(rows, buckets, depth), "lm-blocks")
    words = common.stored(word_answers(asked), "lm-words")
    size = words.agg(F.sum("total").alias("n"), F.sum("kinds").alias("v")).first()
    total, kinds = size["n"] or 0, size["v"] or 0
    counts = common.stored(window_counts(asked, buckets), "lm-windows")
    columns = ["kind", "block", "bucket", "keys"]
    answers = window_answers(asked, window_scores(counts, buckets, depth)).unionByName(words.select(*columns))
    blocks = asked.where(F.col("kind") == TEXTS).select(*columns).unionByName(answers)
    return blocks.groupBy("block").applyInArrow(
        lambda part: _score_block(part, buckets, depth, total, kinds),
        "doc_id bigint, held_out boolean, n_tokens bigint, n_known bigint, train_tokens bigint, base_score double, score double, n_bytes bigint, bits_per_byte double",
    )


def op4_lm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score_texts(common.table(spark, sf_dir, "documents"))
