"""SentencePiece encoding and decoding by suffix-array matching.

A group of documents is cut where no piece can cross; the distinct units are laid end
to end and a suffix array over them, sorted as deep as the longest piece, is searched
by all pieces at once. Every occurrence is an edge from its start to its end. Edges are
sorted by end and relaxed in that order.

The vocabulary is of the byte-pair kind, where the best path is not the one of the
largest sum of scores, so relaxation uses the property that decides it: a sequence is
the byte-pair encoding of its text exactly if every two neighbours would be encoded as
themselves. Of the edges that end at a position, one follows the token that ends at its
start in this way; that one is kept. Whether two pieces may be neighbours is worked out
once for each pair by merging their characters.

Defined cases: a null or empty text has no piece; characters outside the vocabulary
become byte pieces; U+2581 in a text decodes as a space, as in the public library;
repeated rows encode alike; an empty table gives an empty result; other columns pass
through, those named as an added one as ``input_<name>``.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fragmap.llm import common

MODEL = "piece_bpe_32k.model"
GROUP_CHARS = 4_000_000
INDEX_CHARS = 400_000
CACHE_UNITS = 200_000
#: Fixed value: the mark that stands for a space.
SPACE = "▁"
_UNIT = re.compile(f"{SPACE}+[^{SPACE}\n]*|\n|[^{SPACE}\n]+")


class _PairTable:
    """Open addressing from a pair number to 0 or 1, for arrays of numbers at once."""

    def __init__(self, bits: int = 18):
        self._room(bits)

    def _room(self, bits: int) -> None:
        self.bits, self.used = bits, 0
        self.keys, self.values = np.full(1 << bits, -1, np.int64), np.zeros(1 << bits, bool)

    def _home(self, keys: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            return ((keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)).astype(np.int64)

    def get(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Values, and the places of keys that are not held."""
        at = self._home(keys)
        held = self.keys[at]
        out = self.values[at]
        live, lost = np.flatnonzero(held != keys), []
        at = at[live]
        while len(live):
            held = self.keys[at]
            hit, none = held == keys[live], held == -1
            out[live[hit]] = self.values[at[hit]]
            lost.append(live[none])
            on = ~(hit | none)
            live, at = live[on], (at[on] + 1) & (len(self.keys) - 1)
        return out, np.concatenate(lost) if lost else np.empty(0, np.int64)

    def put(self, keys: np.ndarray, values: np.ndarray) -> None:
        if 2 * (self.used + len(keys)) > len(self.keys):
            old = self.keys != -1
            keys, values = np.concatenate([self.keys[old], keys]), np.concatenate([self.values[old], values])
            self._room(max(self.bits + 1, int(4 * len(keys)).bit_length()))
        self.used += len(keys)
        at = self._home(keys)
        while len(keys):
            free = self.keys[at] == -1
            self.keys[at[free]] = keys[free]
            placed = self.keys[at] == keys
            self.values[at[placed]] = values[placed]
            keys, values, at = keys[~placed], values[~placed], (at[~placed] + 1) & (len(self.keys) - 1)


class PieceCodec:
    def __init__(self, path: str):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        n = model.get_piece_size()
        self.pieces = [model.id_to_piece(i) for i in range(n)]
        plain = [not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i) or model.is_unused(i)) for i in range(n)]
        self.ids = {p: i for i, p in enumerate(self.pieces) if plain[i]}
        self.scores = {p: model.get_score(i) for p, i in self.ids.items()}
        self.byte_ids = [model.piece_to_id(f"<0x{b:02X}>") for b in range(256)]
        self.outside = n  # stands for any character without a piece
        for p in self.ids:
            if "\n" in p and len(p) > 1 or SPACE in p.lstrip(SPACE):
                raise ValueError(f"units can't be cut where the piece {p!r} may cross")
        self.usable = [p for p in self.ids if self.merge(p) == [p]]
        self.longest = max(map(len, self.usable), default=1)
        self.size = np.array([len(p) for p in self.usable], np.int32)
        self.number = np.array([self.ids[p] for p in self.usable], np.int32)
        self.codes = np.zeros((len(self.usable), self.longest), np.int64)
        for i, p in enumerate(self.usable):
            self.codes[i, : len(p)] = np.frombuffer(p.encode("utf-32-le"), np.uint32)
        self.single = np.unique(self.codes[self.size == 1, 0])
        self.raw = [p.encode() for p in self.pieces]
        for b, i in enumerate(self.byte_ids):
            self.raw[i] = bytes([b])
        self.width = np.array([len(r) for r in self.raw], np.int64)
        self.exact = True  # every unit so far is what its pieces decode to
        self.pairs = _PairTable()
        self.cache: dict[str, bytes] = {}

    def merge(self, text: str) -> list[str]:
        """Byte-pair merging of a short text: the best-scored neighbours first, the leftmost of equals."""
        parts, scores = list(text), self.scores
        while len(parts) > 1:
            found = [(-scores[m], i) for i in range(len(parts) - 1) if (m := parts[i] + parts[i + 1]) in scores]
            if not found:
                break
            i = min(found)[1]
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
        return parts

    def _neighbours(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        ok = (left == self.outside) | (right == self.outside)
        at = np.flatnonzero(~ok)
        keys = left[at].astype(np.int64) * (self.outside + 1) + right[at]
        known, lost = self.pairs.get(keys)
        if len(lost):
            new = np.unique(keys[lost])
            pieces = self.pieces
            a, b = (new // (self.outside + 1)).tolist(), (new % (self.outside + 1)).tolist()
            values = np.array([self.merge(pieces[x] + pieces[y]) == [pieces[x], pieces[y]] for x, y in zip(a, b)], bool)
            self.pairs.put(new, values)
            known[lost] = values[np.searchsorted(new, keys[lost])]
        ok[at] = known
        return ok

    def _suffixes(self, text: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray, int]:
        """Starts of suffixes sorted by their first ``longest`` characters, by doubling the sorted depth; the sorted
        keys of the first round, which hold as many characters of ``bits`` bits as a number takes, and that number of characters."""
        n = len(text)
        first = depth = max(1, min(63 // bits, self.longest))
        padded = np.concatenate([text, np.zeros(depth, np.int64)])
        key = np.zeros(n, np.int64)
        for d in range(depth):
            key = (key << bits) | padded[d : d + n]
        order = np.argsort(key, kind="stable")
        ordered = begun = key[order]
        while depth < self.longest:
            rank = np.empty(n, np.int64)
            rank[order] = np.cumsum(np.concatenate([[1], ordered[1:] != ordered[:-1]]))
            further = np.zeros(n, np.int64)
            further[: max(n - depth, 0)] = rank[depth:]
            key = (rank << 32) | further
            order = np.argsort(key, kind="stable")
            ordered = key[order]
            depth *= 2
        return order, begun, first

    def _ranges(self, text: np.ndarray, order: np.ndarray, codes: np.ndarray, bits: int, begun: np.ndarray, first: int) -> tuple[np.ndarray, np.ndarray]:
        """The suffixes that begin with each piece: both bounds by its first characters' key, then narrowed a character at a time."""
        low, high = np.zeros(len(self.size), np.int64), np.zeros(len(self.size), np.int64)
        inside = np.flatnonzero((codes >= 0).all(axis=1))  # its characters occur
        key = np.zeros(len(inside), np.int64)
        for d in range(first):
            key = (key << bits) | codes[inside, d]
        open_bits = bits * np.maximum(first - self.size[inside].astype(np.int64), 0)
        low[inside] = np.searchsorted(begun, key, "left")
        high[inside] = np.searchsorted(begun, key | ((np.int64(1) << open_bits) - 1), "right")
        padded = np.concatenate([text, np.full(self.longest, -1, np.int64)])
        for d in range(first, self.longest):
            live = np.flatnonzero((self.size > d) & (low < high))
            want = codes[live, d]
            bounds = []
            for above in (False, True):
                a, b = low[live].copy(), high[live].copy()
                while True:
                    open_ = np.flatnonzero(a < b)
                    if not len(open_):
                        break
                    mid = (a[open_] + b[open_]) >> 1
                    got = padded[order[mid] + d]
                    right = got <= want[open_] if above else got < want[open_]
                    a[open_[right]] = mid[right] + 1
                    b[open_[~right]] = mid[~right]
                bounds.append(a)
            low[live], high[live] = bounds
        return low, high

    def encode_units(self, units: list[str]) -> list[bytes]:
        """Piece numbers (int32) of each distinct unit, all from one suffix array."""
        sizes = np.array([len(u) for u in units], np.int64)
        text = np.frombuffer(("\0" + "\0".join(units) + "\0").encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)
        begins = 1 + np.concatenate([[0], np.cumsum(sizes + 1)[:-1]])
        offset = np.zeros(len(text) + 1, np.int32)  # of a boundary in its unit
        offset[1 : len(text)] = np.arange(1, len(text)) - np.repeat(begins, sizes + 1)
        present = np.zeros(max(int(text.max()), int(self.codes.max(initial=0))) + 1, bool)
        present[text] = True
        place = np.where(present, np.cumsum(present) - 1, -1)  # characters numbered in order, 0 for the separator
        dense, bits = place[text], max(1, (int(present.sum()) - 1).bit_length())
        order, begun, first = self._suffixes(dense, bits)
        low, high = self._ranges(dense, order, place[self.codes], bits, begun, first)
        del begun
        count = high - low
        found = np.repeat(low - (np.cumsum(count) - count), count) + np.arange(int(count.sum()))
        start = order[found].astype(np.int32)
        size, token = np.repeat(self.size, count), np.repeat(self.number, count)
        held = np.isin(np.flatnonzero(present), self.single)
        held[0] = True
        lone = np.flatnonzero(~held[dense]).astype(np.int32)
        start = np.concatenate([start, lone])
        size, token = np.concatenate([size, np.ones(len(lone), np.int32)]), np.concatenate([token, np.full(len(lone), self.outside, np.int32)])
        del found, order
        end = start + size
        steps = offset[start] + size
        sort = np.argsort(steps.astype(np.uint16) if len(steps) and steps.max() < 1 << 16 else steps, kind="stable")  # two bytes are sorted by radix
        start, end, token = start[sort], end[sort], token[sort]
        steps = (offset[start] + (end - start)).astype(np.int64)
        last, back = np.full(len(text) + 1, -1, np.int32), np.zeros(len(text) + 1, np.int32)
        bounds = np.flatnonzero(np.concatenate([[True], steps[1:] != steps[:-1], [True]])) if len(steps) else [0]
        for a, b in zip(bounds[:-1], bounds[1:]):
            s, t = start[a:b], token[a:b]
            before = last[s]
            ok = offset[s] == 0
            rest = np.flatnonzero(~ok)
            ok[rest] = self._neighbours(before[rest], t[rest])
            to = end[a:b][ok]
            last[to], back[to] = t[ok], s[ok]
        used = np.zeros(len(text) + 1, bool)
        at = begins + sizes
        floor = begins.copy()
        while len(at):
            used[at] = True
            at = back[at].astype(np.int64)
            on = at > floor
            at, floor = at[on], floor[on]
        places = np.flatnonzero(used)
        tokens = last[places]
        if (tokens < 0).any():
            raise AssertionError("a unit has no encoding")
        cuts = np.searchsorted(places, begins + sizes, "right")
        data, bounds = tokens.astype(np.int32).tobytes(), [0, *(4 * cuts).tolist()]
        out = [data[a:b] for a, b in zip(bounds[:-1], bounds[1:])]
        for i in np.unique(np.searchsorted(cuts, np.flatnonzero(tokens == self.outside), "right")).tolist():
            own = slice(bounds[i] // 4, bounds[i + 1] // 4)
            out[i] = self._with_bytes(tokens[own], text, places[own]).tobytes()
        self.exact = self.exact and self._return(units, out)
        return out

    def _return(self, units: list[str], out: list[bytes]) -> bool:
        """Whether every unit is what its pieces decode to; texts of such units are too, as units are whole characters."""
        try:
            want = [u.encode() for u in units]
        except UnicodeEncodeError:
            return False
        ids, ends = np.frombuffer(b"".join(out), np.int32), np.cumsum([len(o) // 4 for o in out])
        width = np.concatenate([[0], np.cumsum(self.width[ids])])[ends]
        return bool((width == np.cumsum([len(w) for w in want])).all()) and b"".join(map(self.raw.__getitem__, ids.tolist())) == b"".join(want)

    def _with_bytes(self, tokens: np.ndarray, text: np.ndarray, ends: np.ndarray) -> np.ndarray:
        out: list[int] = []
        for t, end in zip(tokens.tolist(), ends.tolist()):
            if t == self.outside:
                out += [self.byte_ids[b] for b in chr(int(text[end - 1])).encode("utf-8", "surrogatepass")]
            else:
                out.append(t)
        return np.array(out, np.int32)

    def encode(self, texts: list[str | None]) -> list[np.ndarray]:
        """Piece numbers of each text of one group."""
        new: dict[str, str] = {}  # one string for each distinct unit
        cut = []
        for t in texts:
            units = _UNIT.findall(SPACE + t.replace(" ", SPACE)) if t else []
            cut.append(list(map(new.setdefault, units, units)))
        if len(self.cache) + len(new) > CACHE_UNITS:
            self.cache = {u: self.cache[u] for u in new if u in self.cache}
        new = [u for u in new if u not in self.cache]
        part, chars = [], 0
        for i, u in enumerate(new):
            if "\0" in u:  # the separator of the index; such a unit is encoded around it
                self.cache[u] = self._around_zero(u)
                self.exact = False  # such texts are decoded whole
                continue
            part.append(u)
            chars += len(u) + 1
            if chars >= INDEX_CHARS:
                self.cache.update(zip(part, self.encode_units(part)))
                part, chars = [], 0
        if part:
            self.cache.update(zip(part, self.encode_units(part)))
        known = self.cache
        return [np.frombuffer(b"".join(map(known.__getitem__, units)), np.int32) for units in cut]

    def _around_zero(self, unit: str) -> bytes:
        parts = unit.split("\0")
        codes = iter(self.encode_units([p for p in parts if p])) if any(parts) else iter(())
        zero = np.array([self.byte_ids[0]], np.int32).tobytes()
        return zero.join(next(codes) if p else b"" for p in parts)

    def decode(self, ids: np.ndarray) -> str:
        text = b"".join(map(self.raw.__getitem__, ids.tolist())).decode("utf-8", "replace").replace(SPACE, " ")
        return text[1:] if text.startswith(" ") else text


@lru_cache(maxsize=2)
def codec(model: str) -> PieceCodec:
    """By path, or by name among the public vocabulary files."""
    if "/" not in model:
        import public_tokenizers

        model = public_tokenizers.path(model)
    common.keep("pieces", codec.cache_clear)
    return PieceCodec(model)


def _groups(batches: Iterator[pa.RecordBatch], at: int) -> Iterator[pa.Table]:
    """The rows in tables of just over ``GROUP_CHARS`` characters in column ``at``."""
    held, size = [], 0
    for batch in batches:
        first = 0
        for i, n in enumerate(pc.utf8_length(batch.column(at)).to_pylist()):
            size += n or 0
            if size >= GROUP_CHARS:
                yield pa.Table.from_batches([*held, batch.slice(first, i + 1 - first)]).combine_chunks()
                held, size, first = [], 0, i + 1
        if first < batch.num_rows:
            held.append(batch.slice(first))
    if held:
        yield pa.Table.from_batches(held).combine_chunks()


def encode_documents(docs: DataFrame, text_col: str = "text", model: str = MODEL, ids: bool = True) -> DataFrame:
    """All columns of ``docs`` and ``n_pieces``, ``pieces_crc32`` (of the numbers as little-endian int32), ``round_trip`` and, if asked, ``pieces``.

    Input columns of these names are returned as ``input_<name>``.
    """
    added = ["n_pieces", "pieces_crc32", "round_trip", *["pieces"] * ids]
    docs = common.set_aside(docs, added)
    names = docs.columns
    at = names.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zlib

        common.begin("pieces")
        own = codec(model)
        for part in _groups(batches, at):
            texts = part.column(at).to_pylist()
            codes = own.encode(texts)
            more = [
                pa.array([len(c) for c in codes], pa.int64()),
                pa.array([zlib.crc32(c.astype("<i4").tobytes()) for c in codes], pa.int64()),
                pa.array([own.exact or own.decode(c) == (t or "").replace(SPACE, " ") for c, t in zip(codes, texts)], pa.bool_()),
            ]
            if ids:
                more.append(pa.array(codes, pa.list_(pa.int32())))
            yield from pa.Table.from_arrays([*part.columns, *more], [*names, *added]).combine_chunks().to_batches(max_chunksize=2000)

    kinds = [f"`{n}` {k}" for n, k in docs.dtypes]
    schema = ", ".join([*kinds, "n_pieces bigint, pieces_crc32 bigint, round_trip boolean", *["pieces array<int>"] * ids])
    return docs.mapInArrow(run, schema)


def decode_documents(docs: DataFrame, pieces_col: str = "pieces", model: str = MODEL) -> DataFrame:
    """All columns of ``docs`` (one named so as ``input_decoded``) and ``decoded``."""
    docs = common.set_aside(docs, ["decoded"])
    names = docs.columns
    at = names.index(pieces_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.begin("pieces")
        own = codec(model)
        for batch in batches:
            texts = [own.decode(np.array(p.as_py() or [], np.int32)) for p in batch.column(at)]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(texts, pa.string())], [*names, "decoded"])

    kinds = [f"`{n}` {k}" for n, k in docs.dtypes]
    return docs.mapInArrow(run, ", ".join([*kinds, "decoded string"]))


def op2_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents").select("doc_id", "text")
    return encode_documents(docs, ids=False).drop("text")
