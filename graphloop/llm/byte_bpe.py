"""Byte-level BPE encoding and decoding.

Pre-tokenisation uses no regular expression. Every code point gets a class from a table; the
class, with what can be seen of its neighbours by shifted comparisons, is a transition
function on the eight states of a small automaton. These functions form a finite monoid, so
their composition is a table look-up, and all states of a batch come from a blocked
associative scan. Where a state meets a class that starts a slice there is a boundary.

Equal slices of a stretch are found by hash and confirmed byte by byte, and the distinct ones feed a cache of merged
pairs. Short slices that it lacks are merged together, a matrix of
parts with one merge in every row at a time; a long one is merged by a heap in O(n log n), so
a slice of any length is handled whole. Token ids keep the byte offset of each token, with
which any stretch of a text can be decoded by itself.
"""

from __future__ import annotations

import base64
import heapq
import unicodedata
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from graphloop.llm.shingles import BYTE_CODES, STEP, mix

# Code points with the White_Space property.
WHITE_SPACE = [0x09, 0x0A, 0x0B, 0x0C, 0x0D, 0x20, 0x85, 0xA0, 0x1680, 0x2000, 0x2001, 0x2002, 0x2003, 0x2004, 0x2005, 0x2006,
               0x2007, 0x2008, 0x2009, 0x200A, 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]
# Endings split off after an apostrophe.
SHORT_ENDINGS = "stmd"
LONG_ENDINGS = ("re", "ve", "ll")

LETTER, NUMBER, OTHER, SPACE_RUN, SPACE_BEFORE, SPACE_ALONE, APOSTROPHE_1, APOSTROPHE_2, RESET = range(9)
_ENDED, _IN_LETTERS, _IN_NUMBERS, _IN_OTHERS, _IN_SPACES, _AFTER_SPACE, _TAKE_1, _TAKE_2 = range(8)

CHUNK_CHARS = 500_000
CACHE_SLICES = 80_000
CACHE_BYTES = 64
MATRIX_BYTES = (6, 9, 12, 16, 32)
NO_PAIR = np.int32(2**31 - 1)
_WIDTH = [next(w for w in MATRIX_BYTES if n <= w) for n in range(MATRIX_BYTES[-1] + 1)]


def _step(state: int, kind: int) -> tuple[int, bool]:
    """(next state, whether a slice starts at this code point)."""
    runs = {LETTER: _IN_LETTERS, NUMBER: _IN_NUMBERS, OTHER: _IN_OTHERS}
    if kind == RESET:
        return _ENDED, True
    if kind == LETTER and state in (_TAKE_1, _TAKE_2):
        return (_ENDED if state == _TAKE_1 else _TAKE_1), False
    if kind in runs:
        return runs[kind], state not in (runs[kind], _AFTER_SPACE)
    if kind in (APOSTROPHE_1, APOSTROPHE_2):
        if state in (_IN_OTHERS, _AFTER_SPACE):
            return _IN_OTHERS, False
        return (_TAKE_1 if kind == APOSTROPHE_1 else _TAKE_2), True
    if kind == SPACE_RUN:
        return _IN_SPACES, state != _IN_SPACES
    return (_AFTER_SPACE if kind == SPACE_BEFORE else _ENDED), True


def _monoid() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(element of each class, product table, image of the start state for each element)."""
    generators = [tuple(_step(s, k)[0] for s in range(8)) for k in range(9)]
    elements = list(dict.fromkeys(generators))
    known = {e: i for i, e in enumerate(elements)}
    for first in elements:  # grows while it is walked, until closed
        for then in generators:
            product = tuple(then[s] for s in first)
            if product not in known:
                known[product] = len(elements)
                elements.append(product)
    size = len(elements)
    table = np.empty((size, size), dtype=np.int16)
    for i, first in enumerate(elements):
        for j, then in enumerate(elements):
            table[i, j] = known[tuple(then[s] for s in first)]
    return np.array([known[g] for g in generators], dtype=np.int16), table, np.array([e[_ENDED] for e in elements], dtype=np.int8)


_ELEMENT, _PRODUCT, _FROM_START = _monoid()
_FLAT, _SIZE = _PRODUCT.ravel(), _PRODUCT.shape[0]
_STARTS = np.array([[_step(s, k)[1] for k in range(9)] for s in range(8)])
_KINDS: np.ndarray | None = None


def _kinds() -> np.ndarray:
    """Class of every code point: 0 letter, 1 number, 2 other, 3 white space."""
    global _KINDS
    if _KINDS is None:
        table = np.full(0x110000, OTHER, dtype=np.uint8)
        for cp in range(0x110000):
            major = unicodedata.category(chr(cp))[0]
            if major == "L":
                table[cp] = LETTER
            elif major == "N":
                table[cp] = NUMBER
        table[WHITE_SPACE] = SPACE_RUN
        _KINDS = table
    return _KINDS


def _scan(elements: np.ndarray) -> np.ndarray:
    """Inclusive products of all prefixes, block by block."""
    n = len(elements)
    if n <= 64:
        out = elements.copy()
        for i in range(1, n):
            out[i] = _PRODUCT[out[i - 1], out[i]]
        return out
    width = max(16, int(n**0.5) // 2)
    rows = -(-n // width)
    padded = np.full(rows * width, elements[-1], dtype=np.int64)
    padded[:n] = elements
    block = np.ascontiguousarray(padded.reshape(rows, width).T)
    for k in range(1, width):
        block[k] = _FLAT[block[k - 1] * _SIZE + block[k]]
    totals = _scan(block[-1].astype(np.int16)).astype(np.int64)
    block[:, 1:] = _FLAT[totals[None, :-1] * _SIZE + block[:, 1:]]
    return block.T.ravel()[:n].astype(np.int16)


def boundaries(joined: str, resets: np.ndarray) -> np.ndarray:
    """Sorted positions at which a slice starts; ``resets`` are separators between texts."""
    cps = np.frombuffer(joined.encode("utf-32-le"), dtype=np.uint32)
    n = len(cps)
    if not n:
        return np.empty(0, dtype=np.int64)
    kind = _kinds()[cps]
    space = kind == SPACE_RUN
    last = np.empty(n, dtype=bool)  # white space before something that is none
    last[:-1] = space[:-1] & ~space[1:]
    last[-1] = False
    kind[last] = np.where(cps[last] == 0x20, SPACE_BEFORE, SPACE_ALONE)
    marks = np.flatnonzero(cps == 0x27)
    if len(marks):
        follow = np.zeros((3, len(marks)), dtype=np.uint32)
        for d in (1, 2):
            inside = marks + d < n
            follow[d, inside] = cps[marks[inside] + d]
        short = np.isin(follow[1], [ord(c) for c in SHORT_ENDINGS])
        long = np.zeros(len(marks), dtype=bool)
        for ending in LONG_ENDINGS:
            long |= (follow[1] == ord(ending[0])) & (follow[2] == ord(ending[1]))
        kind[marks[short]] = APOSTROPHE_1
        kind[marks[long]] = APOSTROPHE_2
    kind[resets] = RESET
    states = np.empty(n, dtype=np.int8)
    states[0] = _ENDED
    states[1:] = _FROM_START[_scan(_ELEMENT[kind])[:-1]]
    return np.flatnonzero(_STARTS[states, kind])


def _distinct(raw: bytes, data: np.ndarray, starts: np.ndarray, spans: np.ndarray, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(first slice of each kind, kind of each slice); slices of one hash are one kind only if all their bytes agree."""
    _, first, same = np.unique(hashes, return_index=True, return_inverse=True)
    like = first[same]
    if (spans == spans[like]).all():
        inside = np.arange(int(spans.sum())) - np.repeat(np.cumsum(spans) - spans, spans)
        if (data[np.repeat(starts, spans) + inside] == data[np.repeat(starts[like], spans) + inside]).all():
            return first, same
    known: dict[bytes, int] = {}
    kinds = [known.setdefault(raw[a : a + n], len(known)) for a, n in zip(starts.tolist(), spans.tolist(), strict=True)]
    same = np.array(kinds)
    return np.unique(same, return_index=True)[1], same


class Vocabulary:
    """Ranks of byte strings; encodes slices and holds tables for decoding."""

    def __init__(self, ranks: dict[bytes, int]):
        self.ranks = ranks
        size = max(ranks.values()) + 1
        tokens = [b""] * size
        for token, rank in ranks.items():
            tokens[rank] = token
        self.lengths = np.array([len(t) for t in tokens], dtype=np.int64)
        self.starts = np.cumsum(self.lengths) - self.lengths
        self.bytes = np.frombuffer(b"".join(tokens), dtype=np.uint8)
        self.single = np.array([ranks.get(bytes([b]), -1) for b in range(256)], dtype=np.int32)
        self._build_pairs()

    def _build_pairs(self) -> None:
        """An open-addressing table from two adjacent tokens to the token they make."""
        left, right, made = [], [], []
        for token, rank in self.ranks.items():
            for k in range(1, len(token)):
                a, b = self.ranks.get(token[:k]), self.ranks.get(token[k:])
                if a is not None and b is not None:
                    left.append(a), right.append(b), made.append(rank)
        self.bits = max(4, (4 * len(made)).bit_length())
        self.keys = np.full(1 << self.bits, -1, dtype=np.int64)
        self.made = np.full(1 << self.bits, NO_PAIR, dtype=np.int32)
        key = (np.array(left, dtype=np.int64) << 32) | np.array(right, dtype=np.int64)
        value = np.array(made, dtype=np.int32)
        slot = self._slot(key)
        while len(key):
            free = self.keys[slot] == -1
            self.keys[slot[free]] = key[free]
            placed = self.keys[slot] == key
            self.made[slot[placed]] = value[placed]
            key, value, slot = key[~placed], value[~placed], (slot[~placed] + 1) & ((1 << self.bits) - 1)

    def _slot(self, key: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            return (key.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(64 - self.bits)).astype(np.int64)

    def pair_ranks(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Rank of the token that two tokens make, ``NO_PAIR`` where they make none."""
        key = (left.astype(np.int64) << 32) | right.astype(np.int64)
        slot = self._slot(key)
        at = self.keys[slot]
        out = np.where(at == key, self.made[slot], NO_PAIR)
        rest = np.flatnonzero((at != key) & (at != -1))
        while len(rest):
            slot[rest] = (slot[rest] + 1) & ((1 << self.bits) - 1)
            at = self.keys[slot[rest]]
            hit = at == key[rest]
            out[rest[hit]] = self.made[slot[rest[hit]]]
            rest = rest[~hit & (at != -1)]
        return out

    @classmethod
    def load(cls, path: str) -> Vocabulary:
        """Reads a file of base64 token and rank per line."""
        with open(path, "rb") as lines:
            pairs = (line.split() for line in lines if line.strip())
            return cls({base64.b64decode(token): int(rank) for token, rank in pairs})

    def merge(self, slice_bytes: bytes) -> tuple[int, ...]:
        """Token ids of one slice: lowest rank first, leftmost on ties."""
        ranks = self.ranks
        if slice_bytes in ranks:
            return (ranks[slice_bytes],)
        n = len(slice_bytes)
        end = list(range(1, n + 1))  # end of the part that starts here
        before = list(range(-1, n - 1))
        alive = [True] * n
        heap = []
        for i in range(n - 1):
            rank = ranks.get(slice_bytes[i : i + 2])
            if rank is not None:
                heap.append((rank, i, i + 2))
        heapq.heapify(heap)
        while heap:
            _, i, stop = heapq.heappop(heap)
            if not alive[i] or end[i] >= n or end[end[i]] != stop:
                continue
            j = end[i]
            alive[j] = False
            end[i] = stop
            if stop < n:
                before[stop] = i
                rank = ranks.get(slice_bytes[i : end[stop]])
                if rank is not None:
                    heapq.heappush(heap, (rank, i, end[stop]))
            if before[i] >= 0:
                rank = ranks.get(slice_bytes[before[i] : stop])
                if rank is not None:
                    heapq.heappush(heap, (rank, before[i], stop))
        out, i = [], 0
        while i < n:
            out.append(ranks[slice_bytes[i : end[i]]])
            i = end[i]
        return tuple(out)

    def merge_many(self, slices: list[bytes]) -> list[tuple[int, ...]]:
        """``merge`` for many slices at once."""
        out: list = [None] * len(slices)
        groups: dict[int, list[int]] = {width: [] for width in MATRIX_BYTES}
        for i, (piece, rank) in enumerate(zip(slices, map(self.ranks.get, slices), strict=True)):
            if rank is not None:
                out[i] = (rank,)
            elif len(piece) > MATRIX_BYTES[-1]:
                out[i] = self.merge(piece)
            else:
                groups[_WIDTH[len(piece)]].append(i)
        for width, rows in groups.items():
            for at in range(0, len(rows), 20_000):
                part = rows[at : at + 20_000]
                for i, ids in zip(part, self._merge_matrix([slices[i] for i in part], width), strict=True):
                    out[i] = ids
        return out

    def _merge_matrix(self, slices: list[bytes], width: int) -> list[tuple[int, ...]]:
        n = len(slices)
        sizes = np.fromiter(map(len, slices), dtype=np.int64, count=n)
        columns = np.arange(width)
        parts = np.full((n, width + 1), -1, dtype=np.int32)
        parts[:, :width][columns < sizes[:, None]] = self.single[np.frombuffer(b"".join(slices), dtype=np.uint8)]
        ranks = np.full((n, width + 1), NO_PAIR, dtype=np.int32)
        paired = np.flatnonzero((columns + 1 < sizes[:, None]).ravel())
        row, column = paired // width, paired % width
        ranks[row, column] = self.pair_ranks(parts[row, column], parts[row, column + 1])
        active = np.arange(n)
        while len(active):
            r = ranks[active]
            spot = r.argmin(axis=1)
            least = r[np.arange(len(active)), spot]
            go = least != NO_PAIR
            active, spot, least, r = active[go], spot[go], least[go], r[go]
            p = parts[active]
            index = np.arange(len(active))
            shifted = columns + (columns > spot[:, None])
            p[:, :width] = np.take_along_axis(p, shifted, axis=1)
            p[index, spot] = least
            r[:, :width] = np.take_along_axis(r, columns + (columns >= spot[:, None]), axis=1)
            follow = p[index, spot + 1]
            r[index, spot] = NO_PAIR
            some = np.flatnonzero(follow >= 0)
            r[some, spot[some]] = self.pair_ranks(least[some], follow[some])
            some = np.flatnonzero(spot > 0)
            r[some, spot[some] - 1] = self.pair_ranks(p[some, spot[some] - 1], least[some])
            parts[active], ranks[active] = p, r
        used = parts >= 0
        ends = np.cumsum(used.sum(axis=1)).tolist()
        flat = parts[used].tolist()
        return [tuple(flat[a:b]) for a, b in zip([0, *ends[:-1]], ends, strict=True)]

    def decode(self, ids: np.ndarray) -> np.ndarray:
        """Bytes of a run of token ids."""
        lengths = self.lengths[ids]
        total = np.cumsum(lengths)
        if not len(ids):
            return np.empty(0, dtype=np.uint8)
        shift = np.repeat(self.starts[ids] - (total - lengths), lengths)
        return self.bytes[shift + np.arange(total[-1])]


def stretches(text: str, size: int) -> Iterator[str]:
    """A text in parts of about ``size`` characters, cut only before white space that follows something else.

    A slice starts there whatever stands before, and classes look ahead only, so the parts have
    the slices of the whole. A run without such a place is one part.
    """
    spaces, at = frozenset(map(chr, WHITE_SPACE)), 0
    while len(text) - at > size:
        cut = at + size
        while cut < len(text) and not (text[cut] in spaces and text[cut - 1] not in spaces):
            cut += 1
        yield text[at:cut]
        at = cut
    if at < len(text) or not text:
        yield text[at:]


class Encoder:
    """Encodes lists of texts, a bounded number of characters at a time, also of one text."""

    def __init__(self, vocabulary: Vocabulary):
        self.vocabulary = vocabulary
        self.merged: dict[bytes, tuple[int, ...]] = {}
        self.older: dict[bytes, tuple[int, ...]] = {}

    def _merge(self, pieces: list[bytes]) -> list[tuple[int, ...]]:
        """Token ids of distinct pieces.

        Short pieces stay in a cache of two generations: when the younger is full it becomes
        the older, and what is still in use moves over.
        """
        if len(self.merged) > CACHE_SLICES:
            self.merged, self.older = {}, self.merged
        found = list(map(self.merged.get, pieces))
        lost = [i for i, ids in enumerate(found) if ids is None]
        missing = []
        for i in lost:
            ids = self.older.get(pieces[i])
            if ids is None:
                missing.append(i)
            else:
                found[i] = self.merged[pieces[i]] = ids
        for i, ids in zip(missing, self.vocabulary.merge_many([pieces[i] for i in missing]), strict=True):
            found[i] = ids
            if len(pieces[i]) <= CACHE_BYTES:
                self.merged[pieces[i]] = ids
        return found

    def encode(self, texts: list[str]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(ids, tokens of each text) for consecutive stretches of ``texts``."""
        start = 0
        while start < len(texts):
            if len(texts[start]) > CHUNK_CHARS:
                parts = [self._stretch([part])[0] for part in stretches(texts[start], CHUNK_CHARS)]
                ids = np.concatenate(parts)
                yield ids, np.array([len(ids)])
                start += 1
                continue
            stop, chars = start, 0
            while stop < len(texts) and (stop == start or chars + len(texts[stop]) <= CHUNK_CHARS):
                chars += len(texts[stop])
                stop += 1
            yield self._stretch(texts[start:stop])
            start = stop

    def _stretch(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        joined = "\n".join(texts)
        lengths = np.fromiter(map(len, texts), dtype=np.int64, count=len(texts))
        firsts = np.cumsum(lengths + 1) - (lengths + 1)
        resets = firsts[1:] - 1
        cuts = boundaries(joined, resets)
        raw = joined.encode()
        data = np.frombuffer(raw, dtype=np.uint8)
        starts, seams = cuts, resets
        if len(raw) > len(joined):  # places in code points become places in bytes
            cps = np.frombuffer(joined.encode("utf-32-le"), dtype=np.uint32)
            widths = 1 + (cps >= 0x80).astype(np.int64) + (cps >= 0x800) + (cps >= 0x10000)
            places = np.cumsum(widths) - widths
            starts, seams = places[cuts], places[resets]
        spans = np.diff(np.append(starts, len(raw)))
        if len(resets):
            keep = ~np.isin(cuts, resets, assume_unique=True)
            cuts = cuts[keep]
        else:
            keep = slice(None)
        if not len(cuts):
            return np.empty(0, dtype=np.int32), np.zeros(len(texts), dtype=np.int64)
        with np.errstate(over="ignore"):
            powers = np.multiply.accumulate(np.full(int(spans.max()), STEP, dtype=np.uint64))
            codes = BYTE_CODES[data] * powers[np.arange(len(raw)) - np.repeat(starts, spans)]
            codes[seams] = 0
            hashes = mix(np.add.reduceat(codes, starts) + spans.astype(np.uint64))[keep]
        starts, spans = starts[keep], spans[keep]
        first, same = _distinct(raw, data, starts, spans, hashes)
        begin = starts[first]
        found = self._merge([raw[a:b] for a, b in zip(begin.tolist(), (begin + spans[first]).tolist(), strict=True)])
        sizes = np.fromiter(map(len, found), dtype=np.int64, count=len(found))
        flat = np.fromiter(chain.from_iterable(found), dtype=np.int32, count=int(sizes.sum()))
        offset = (np.cumsum(sizes) - sizes)[same]
        sizes = sizes[same]
        upto = np.append(0, np.cumsum(sizes))
        ids = flat[np.repeat(offset - upto[:-1], sizes) + np.arange(upto[-1])]
        bounds = np.append(np.searchsorted(cuts, firsts), len(cuts))
        return ids, upto[bounds[1:]] - upto[bounds[:-1]]


def _without(df: DataFrame, names: tuple[str, ...]) -> DataFrame:
    return df.select(*(F.col(f"`{c}`") for c in df.columns if c not in names))


def _lists(values: np.ndarray, counts: np.ndarray) -> pa.Array:
    ends = np.append(0, np.cumsum(counts)).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(values))


def encode_texts(df: DataFrame, path: str, text_col: str = "text", with_offsets: bool = True, with_decoded: bool = False, keep_text: bool = True) -> DataFrame:
    """Adds ``ids`` (array of token ids) and ``offsets`` (byte offset of each token) to ``df``.

    The vocabulary is read by the driver from ``path`` and broadcast; its size is that of the
    file. ``with_decoded`` adds the bytes that the ids stand for, decoded from the ids in the
    same pass; without ``keep_text`` the text itself is not sent back. Null texts count as
    empty and give empty arrays. Rows are encoded one by one, whole and in bounded stretches;
    repeats give equal results, an empty table stays empty, and columns of ``df`` named
    like a result are replaced.
    """
    vocabulary = df.sparkSession.sparkContext.broadcast(Vocabulary.load(path))
    wanted = {"ids": True, "offsets": with_offsets, "decoded": with_decoded}
    base = _without(df, tuple(wanted))
    place = base.columns.index(text_col)
    passed = [k for k, c in enumerate(base.columns) if keep_text or k != place]
    numbers = T.ArrayType(T.IntegerType())
    fields = [base.schema.fields[k] for k in passed]
    fields += [T.StructField(name, T.BinaryType() if name == "decoded" else numbers) for name, want in wanted.items() if want]
    names = [f.name for f in fields]

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = Encoder(vocabulary.value)
        lengths = vocabulary.value.lengths
        for batch in batches:
            done = 0
            for at in range(0, batch.num_rows, 256):
                texts = [t or "" for t in batch.column(place).slice(at, 256).to_pylist()]
                for ids, counts in encoder.encode(texts):
                    rows = batch.slice(done, len(counts))
                    done += len(counts)
                    columns = [rows.column(k) for k in passed]
                    columns.append(_lists(ids, counts))
                    ends = np.append(0, np.cumsum(lengths[ids]))
                    upto = np.append(0, np.cumsum(counts))
                    if with_offsets:
                        columns.append(_lists((ends[:-1] - np.repeat(ends[upto[:-1]], counts)).astype(np.int32), counts))
                    if with_decoded:
                        raw, cuts = vocabulary.value.decode(ids).tobytes(), ends[upto].tolist()
                        columns.append(pa.array([raw[a:b] for a, b in zip(cuts[:-1], cuts[1:], strict=True)], pa.binary()))
                    yield pa.RecordBatch.from_arrays(columns, names=names)

    return base.mapInArrow(encode, T.StructType(fields))


def decode_ids(df: DataFrame, path: str, ids_col: str = "ids", text_col: str = "decoded") -> DataFrame:
    """Adds the bytes that the token ids stand for as the binary column ``text_col``.

    Null arrays give null; an id outside the vocabulary raises. A part of a text is decoded by
    slicing ``ids`` where ``offsets`` says.
    """
    vocabulary = df.sparkSession.sparkContext.broadcast(Vocabulary.load(path))
    base = _without(df, (text_col,))
    place = base.columns.index(ids_col)
    schema = T.StructType(base.schema.fields + [T.StructField(text_col, T.BinaryType())])

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = vocabulary.value
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                lists = part.column(place)
                ids = lists.flatten().to_numpy(zero_copy_only=False)
                counts = lists.value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
                raw = table.decode(ids).tobytes()
                ends = np.append(0, np.cumsum(table.lengths[ids]))[np.cumsum(counts)].tolist()
                valid = lists.is_valid().to_pylist()
                texts = [raw[a:b] if ok else None for a, b, ok in zip([0, *ends], ends, valid, strict=False)]
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(texts, type=pa.binary())], names=schema.names)

    return base.mapInArrow(decode, schema)


def digest(df: DataFrame, path: str) -> DataFrame:
    """The contract's columns for rows (doc_id, text)."""
    coded = encode_texts(df.select("doc_id", "text"), path, with_offsets=False, with_decoded=True, keep_text=False)
    joined = F.array_join(F.transform("ids", lambda i: i.cast("string")), ",")
    return coded.select(
        "doc_id", F.size("ids").cast("long").alias("n_tokens"), F.sha2(joined.cast("binary"), 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256")
    )
