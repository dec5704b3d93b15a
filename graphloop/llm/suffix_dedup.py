"""Repeated passages by a common-prefix-aware distributed merge sort of suffixes.

A byte goes when a string of ``length`` bytes over it also starts elsewhere. Sorting all
suffixes would move every byte many times over, so a filter first finds the suffixes that can
matter: in every window of ``length`` bytes the smallest hash of its ``gram``-byte strings is
an anchor, equal windows have equal anchors, and an anchor whose hash is met once in the
corpus rules out all windows that it owns. What is left is settled by suffix order alone:

1. For every anchor met twice, the suffix at the first window it owns is cut to the bytes its
   windows cover. Tasks sort these suffixes into runs, collapse equal ones, front-code the rest
   (length of the prefix shared with the one before, then the other bytes) and exchange the
   pieces of runs by ranges of the alphabetical order.
2. A loser tree merges the runs of a range. Every head carries the length of the prefix it
   shares with the last winner, so a known prefix is never compared again, and the merge
   yields the longest common prefix of neighbours. A suffix that shares ``length`` bytes or
   more with a neighbour settles its leading windows as repeated.
3. Where windows stay open, the suffix from the anchor on, and the bytes before it read
   backwards, are sorted the same way, beside those of one settled suffix for each distinct
   string with the same anchor. Their longest common prefixes bound how far a repeat can
   reach to either side, so only windows within both bounds stay open.
4. Two suffixes with one anchor part, going backwards, at one of the depths at which neighbours
   part. From each such depth on, the suffixes of open windows, and of settled ones
   with that anchor, are sorted, exchanged and merged once more. Whatever two of them share is
   then the longest common prefix of neighbours, and settles the windows within it.

Equal texts, by 96 bits of hashes, are sorted once and known to repeat throughout; equal
suffixes collapse before the exchange. So neither a text nor a passage that a third of
all documents share costs more than one entry for each run.
"""

from __future__ import annotations

from array import array
from bisect import bisect_left
from collections.abc import Iterator
from hashlib import blake2b

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphloop.llm.shingles import mix
from graphloop.materialize import release, stored

LENGTH, GRAM = 200, 40
SEGMENT = 4_000_000
CHUNK = 2_000_000
RUN_BYTES = 12_000_000
SAMPLE, SAMPLE_BYTES = 12_000, 240
INTERVAL, OPEN, SETTLED = 0, 1, 2

_RNG = np.random.Generator(np.random.PCG64(9))
_BYTE = _RNG.integers(1, 2**63, 256, dtype=np.uint64)
_P = 0xD1342543DE82EF95
_P_INVERSE = pow(_P, -1, 2**64)
_LOW = np.uint64(2**24 - 1)
_powers: tuple[np.ndarray, np.ndarray] = (np.ones(0, np.uint64), np.ones(0, np.uint64))


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    global _powers
    if len(_powers[0]) < n:
        made = []
        for p in (_P, _P_INVERSE):
            steps = np.full(n, np.uint64(p))
            steps[0] = 1
            made.append(np.multiply.accumulate(steps))
        _powers = (made[0], made[1])
    return _powers


def anchors(segments: list[bytes], length: int = LENGTH, gram: int = GRAM) -> tuple[np.ndarray, ...]:
    """(segment, anchor, first window, last window, hash) of every anchor; places within segments."""
    data = np.frombuffer(b"".join(segments), dtype=np.uint8)
    n, width = len(data), length - gram + 1
    sizes = np.fromiter(map(len, segments), dtype=np.int64, count=len(segments))
    firsts = np.cumsum(sizes) - sizes
    none = np.empty(0, dtype=np.int64)
    if not (sizes >= length).any():
        return none, none, none, none, none
    up, down = _power_tables(n + 1)
    with np.errstate(over="ignore"):
        sums = np.zeros(n + 1, dtype=np.uint64)
        np.cumsum(_BYTE[data] * up[:n], out=sums[1:])
        hashes = mix((sums[gram:] - sums[:-gram]) * down[: n - gram + 1])
    packed = (hashes & ~_LOW) | np.arange(len(hashes), dtype=np.uint64)
    rows = -(-len(packed) // width)
    block = np.full(rows * width, np.iinfo(np.uint64).max, dtype=np.uint64)
    block[: len(packed)] = packed
    block = block.reshape(rows, width)
    ahead = np.minimum.accumulate(block, axis=1).ravel()
    behind = np.minimum.accumulate(block[:, ::-1], axis=1)[:, ::-1].ravel()
    least = np.minimum(behind[: n - length + 1], ahead[width - 1 : width - 1 + n - length + 1])
    # Windows that would leave their segment are none.
    lost = np.zeros(n + 1, dtype=np.int32)
    np.add.at(lost, firsts + np.maximum(sizes - length + 1, 0), 1)
    np.add.at(lost, firsts + sizes, -1)
    windows = np.flatnonzero(np.cumsum(lost[: n - length + 1]) == 0)
    owner = (least[windows] & _LOW).astype(np.int64)
    change = np.flatnonzero(np.diff(owner)) + 1
    begin, end = np.append(0, change), np.append(change, len(owner)) - 1
    place = owner[begin]
    segment = np.searchsorted(firsts, place, side="right") - 1
    base = firsts[segment]
    return segment, place - base, windows[begin] - base, windows[end] - base, hashes[place].view(np.int64)


def _segments(texts: list[bytes], length: int) -> Iterator[tuple[list[bytes], list[int], list[int]]]:
    """Lists of (segments, text of each, offset of each), cut so that every window lies in one."""
    parts, whose, offsets, size = [], [], [], 0
    for i, text in enumerate(texts):
        if len(text) < length:
            continue
        for at in range(0, max(1, len(text) - length + 1), SEGMENT):
            parts.append(text[at : at + SEGMENT + length - 1])
            whose.append(i), offsets.append(at)
            size += len(parts[-1])
            if size >= CHUNK:
                yield parts, whose, offsets
                parts, whose, offsets, size = [], [], [], 0
    if parts:
        yield parts, whose, offsets


def _pack(place: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """Anchor's place with the distances to its first and last window."""
    return (place << 16) | ((place - low) << 8) | (place - high)


def find_anchors(docs: DataFrame, length: int, gram: int) -> DataFrame:
    """(hash, dk, chk, pack) for rows (dk, chk, text); the last two bits of ``pack`` are flags.

    Bit 0: the anchor is known to repeat, within its chunk. Bit 1: it is not the first of its
    chunk, so it need not meet others of its hash.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            dk, chk = batch.column("dk").to_numpy(), batch.column("chk").to_numpy()
            texts = [t.encode() for t in batch.column("text").to_pylist()]
            for parts, whose, offsets in _segments(texts, length):
                segment, place, low, high, hashes = anchors(parts, length, gram)
                shift = np.array(offsets, dtype=np.int64)[segment]
                own = np.array(whose)[segment]
                _, first, inverse, counts = np.unique(hashes, return_index=True, return_inverse=True, return_counts=True)
                known = counts[inverse] > 1
                extra = known.copy()
                extra[first] = False
                pack = _pack(place + shift, low + shift, high + shift) << 2 | extra.astype(np.int64) << 1 | known
                columns = [hashes, dk[own], chk[own], pack]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["hash", "dk", "chk", "pack"])

    return docs.select("dk", "chk", "text").mapInArrow(run, "hash long, dk long, chk int, pack long")


def repeated_anchors(found: DataFrame) -> DataFrame:
    """(dk, chk, pack) of anchors whose hash is met twice or more; streams, whatever the number."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: pa.RecordBatch | None = None
        before: int | None = None

        def keep(batch: pa.RecordBatch, following: int | None) -> pa.RecordBatch:
            hashes = batch.column("hash").to_numpy()
            same = hashes[1:] == hashes[:-1]
            pack = batch.column("pack").to_numpy()
            twice = (pack & 1) > 0
            twice[1:] |= same
            twice[:-1] |= same
            twice[0] |= before is not None and before == hashes[0]
            twice[-1] |= following is not None and following == hashes[-1]
            kept = batch.filter(pa.array(twice))
            return pa.RecordBatch.from_arrays([kept.column("dk"), kept.column("chk"), pa.array(pack[twice] >> 2)], names=["dk", "chk", "pack"])

        for batch in batches:
            if not batch.num_rows:
                continue
            if held is not None:
                yield keep(held, batch.column("hash")[0].as_py())
                before = held.column("hash")[held.num_rows - 1].as_py()
            held = batch
        if held is not None:
            yield keep(held, None)

    route = F.when(F.col("pack").bitwiseAND(F.lit(2)) == 0, F.col("hash")).otherwise(F.col("dk"))
    return found.repartition(route).sortWithinPartitions("hash").mapInArrow(run, "dk long, chk int, pack long")


def splitters(docs: DataFrame, found: DataFrame, n_found: int, gram: int) -> dict[str, list[bytes]]:
    """Sorted leading bytes of about ``SAMPLE`` of the suffixes that are sorted, by the kind of suffix.

    They are drawn from the suffixes themselves and are longer than a window, so a range is cut
    wherever different suffixes part, however many share their first bytes. Kinds: 'suffix' from the
    first window on, 'right' from the anchor on, 'left' the anchor and the bytes before it read backwards.
    """
    share = min(1.0, SAMPLE / max(1, n_found))
    drawn = F.pmod(F.xxhash64(F.lit("sample"), "dk", "chk", "pack"), F.lit(2**30)) < int(share * 2**30)
    picked = found.where(drawn).groupBy("dk", "chk").agg(F.collect_set("pack").alias("packs"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            kinds, heads = [], []
            for text, packs in zip(batch.column("text").to_pylist(), batch.column("packs").to_pylist(), strict=True):
                raw = text.encode()
                for pack in packs:
                    place = pack >> 16
                    low = place - (pack >> 8 & 255)
                    kinds += ["suffix", "right", "left"]
                    heads += [raw[low : low + SAMPLE_BYTES], raw[place : place + SAMPLE_BYTES], raw[place : place + gram] + raw[low:place][::-1]]
            yield pa.RecordBatch.from_arrays([pa.array(kinds, pa.string()), pa.array(heads, pa.binary())], names=["kind", "head"])

    # The sample's size is fixed, whatever the corpus.
    texts = docs.join(F.broadcast(picked), ["dk", "chk"]).groupBy("dk", "chk").agg(F.first("text").alias("text"), F.first("packs").alias("packs"))
    rows = texts.select("text", "packs").mapInArrow(run, "kind string, head binary").collect()
    out: dict[str, list[bytes]] = {"suffix": [], "right": [], "left": []}
    for row in rows:
        out[row.kind].append(bytes(row.head))
    return {kind: sorted(heads) for kind, heads in out.items()}


def cut_ranges(sample: list[bytes], ranges: int) -> list[bytes]:
    """At most ``ranges`` - 1 distinct splitters at even steps of the sample."""
    return sorted({sample[len(sample) * k // ranges] for k in range(1, ranges)}) if sample else []


PIECE = "dest int, kind int, dk long, chk int, low int, high int, n int, hash binary, dks binary, chks binary, lows binary, places binary, windows binary, known binary, shared binary, sizes binary, rest binary"
_NAMES = [part.split()[0] for part in PIECE.split(", ")]


def _table(**columns) -> pa.RecordBatch:
    """A batch of ``PIECE`` rows; columns that are not given are null."""
    n = len(next(iter(columns.values())))
    kinds = {"int": pa.int32(), "long": pa.int64(), "binary": pa.binary()}
    types = dict(part.split() for part in PIECE.split(", "))
    arrays = [pa.array(columns[c], type=kinds[types[c]]) if c in columns else pa.nulls(n, kinds[types[c]]) for c in _NAMES]
    return pa.RecordBatch.from_arrays(arrays, names=_NAMES)


def _shared_prefixes(strings: list[bytes], sizes: np.ndarray) -> np.ndarray:
    """Common prefix of each sorted string with the one before."""
    out = np.zeros(len(strings), dtype=np.int64)
    step = 50_000
    for at in range(1, len(strings), step):
        part = strings[at - 1 : at + step]
        lengths = sizes[at - 1 : at + step]
        grid = np.zeros((len(part), int(lengths.max()) + 1), dtype=np.uint8)
        place = np.arange(int(lengths.sum())) - np.repeat(np.cumsum(lengths) - lengths, lengths)
        grid[np.repeat(np.arange(len(part)), lengths), place] = np.frombuffer(b"".join(part), dtype=np.uint8)
        differs = grid[1:] != grid[:-1]
        differs[:, -1] = True
        out[at : at + step] = np.minimum(differs.argmax(axis=1), np.minimum(lengths[1:], lengths[:-1]))
    return out


class _Run:
    """Collects suffixes, sorts and front-codes them, and cuts the run into ranges."""

    def __init__(self, cuts: list[bytes], tell_known: bool = False):
        self.cuts, self.tell_known = cuts, tell_known
        self.clear()

    def clear(self) -> None:
        self.strings: list[bytes] = []
        self.meta = array("q")  # dk, chk, low, place, windows, hash, known
        self.bytes = 0

    def add(self, string: bytes, *meta: int) -> None:
        self.strings.append(string)
        self.meta.extend(meta)
        self.bytes += len(string)

    def flush(self) -> Iterator[pa.RecordBatch]:
        if not self.strings:
            return
        strings = self.strings
        order = sorted(range(len(strings)), key=strings.__getitem__)
        strings = [strings[i] for i in order]
        dk, chk, low, place, windows, hashes, known = np.array(self.meta, dtype=np.int64).reshape(-1, 7)[order].T
        sizes = np.fromiter(map(len, strings), dtype=np.int64, count=len(strings))
        shared = _shared_prefixes(strings, sizes)
        equal = np.zeros(len(strings), dtype=bool)
        equal[1:] = (shared[1:] == sizes[1:]) & (sizes[1:] == sizes[:-1])
        known = known.astype(bool)
        twice = equal.copy()
        twice[:-1] |= equal[1:]
        told = twice if self.tell_known else twice & ~known
        if told.any():
            yield _table(dest=-1 - (dk[told] & 0x3FFF), kind=np.zeros(told.sum(), dtype=np.int32), dk=dk[told], chk=chk[told], low=low[told], high=low[told] + sizes[told])
        heads = np.flatnonzero(~equal)
        known = known | twice
        # Between two heads of classes stand only equals of the first, so its prefix with the second holds.
        lead = shared[heads]
        heads_list = heads.tolist()
        names = [strings[i] for i in heads_list]
        edges = [0, *(bisect_left(names, c) for c in self.cuts), len(names)]
        for dest, (a, b) in enumerate(zip(edges[:-1], edges[1:], strict=True)):
            if a == b:
                continue
            at = heads[a:b]
            cover = lead[a:b].copy()
            cover[0] = 0
            rest = b"".join(s[c:] for s, c in zip(names[a:b], cover.tolist(), strict=True))
            packed = {"hash": hashes[at], "dks": dk[at], "chks": chk[at].astype(np.int32), "lows": low[at].astype(np.int32), "places": place[at].astype(np.int16), "windows": windows[at].astype(np.int16),
                      "known": known[at].astype(np.int8), "shared": cover.astype(np.int16), "sizes": sizes[at].astype(np.int16)}
            yield _table(dest=[dest], kind=[OPEN], n=[b - a], rest=[rest], **{k: [v.tobytes()] for k, v in packed.items()})
        self.clear()


def suffix_runs(rows: DataFrame, cuts: list[bytes], length: int, gram: int) -> DataFrame:
    """Front-coded pieces of sorted runs for rows (dk, chk, copies, text, packs)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        made = _Run(cuts)
        for batch in batches:
            for dk, chk, copies, text, packs in zip(*(batch.column(c).to_pylist() for c in ("dk", "chk", "copies", "text", "packs")), strict=True):
                raw = text.encode()
                for pack in packs:
                    place = pack >> 16
                    low, high = place - (pack >> 8 & 255), place - (pack & 255)
                    name = int.from_bytes(blake2b(raw[place : place + gram], digest_size=8).digest(), "little", signed=True)
                    made.add(raw[low : high + length], dk, chk, low, place - low, high - low + 1, name, int(copies > 1))
                if made.bytes >= RUN_BYTES:
                    yield from made.flush()
        yield from made.flush()

    return rows.select("dk", "chk", "copies", "text", "packs").mapInArrow(run, PIECE)


def side_runs(items: DataFrame, left: list[bytes], right: list[bytes], gram: int) -> DataFrame:
    """The same for both sides of the anchors of rows (kind, dk, chk, low, place, rest).

    A side is told by a first byte and by the last bit of what stands for ``low``.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        made = _Run([b"L" + c for c in left] + [b"R"] + [b"R" + c for c in right], tell_known=True)
        for batch in batches:
            for kind, dk, chk, low, place, item in zip(*(batch.column(c).to_pylist() for c in ("kind", "dk", "chk", "low", "place", "rest")), strict=True):
                known = int(kind == SETTLED)
                made.add(b"R" + item[place:], dk, chk, 2 * low + 1, 0, 0, 0, known)
                made.add(b"L" + item[place : place + gram] + item[:place][::-1], dk, chk, 2 * low, 0, 0, 0, known)
                if made.bytes >= RUN_BYTES:
                    yield from made.flush()
        yield from made.flush()

    return items.select("kind", "dk", "chk", "low", "place", "rest").mapInArrow(run, PIECE)


def window_runs(items: DataFrame, cuts: list[bytes], length: int) -> DataFrame:
    """The same for the suffixes at ``starts`` of rows (kind, dk, chk, low, starts, rest)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        made = _Run(cuts)
        for batch in batches:
            columns = (batch.column(c).to_pylist() for c in ("kind", "dk", "chk", "low", "starts", "rest"))
            for kind, dk, chk, low, starts, item in zip(*columns, strict=True):
                for j in starts:
                    made.add(item[j:], dk, chk, low + j, 0, len(item) - j - length + 1, 0, int(kind == SETTLED))
                if made.bytes >= RUN_BYTES:
                    yield from made.flush()
        yield from made.flush()

    return items.select("kind", "dk", "chk", "low", "starts", "rest").mapInArrow(run, PIECE)


def _common(a: bytes, b: bytes, known: int) -> int:
    """Length of the common prefix, of which ``known`` bytes are known."""
    n = min(len(a), len(b))
    while known < n:
        stop = min(n, known + 32)
        x, y = a[known:stop], b[known:stop]
        if x != y:
            differ = int.from_bytes(x, "big") ^ int.from_bytes(y, "big")
            return known + (8 * (stop - known) - differ.bit_length()) // 8
        known = stop
    return n


def _unfold(shared: list[int], sizes: list[int], rest: bytes) -> Iterator[tuple[bytes, int]]:
    string, at = b"", 0
    for common, size in zip(shared, sizes, strict=True):
        stop = at + size - common
        string = string[:common] + rest[at:stop]
        at = stop
        yield string, common


def merge_runs(runs: list[Iterator[tuple[bytes, int]]]) -> Iterator[tuple[int, bytes, int]]:
    """(run, string, prefix shared with the one before) in order, by a loser tree.

    ``prefix[r]`` is what the head of run r shares with the last winner. The head with more
    is the smaller one, and the other's prefix stays right; only heads that share equally
    much are compared, from there on, and the loser learns its prefix with the winner.
    """
    n = len(runs)
    size = 1
    while size < n:
        size *= 2
    head: list[bytes | None] = [next(run, (None, 0))[0] for run in runs] + [None] * (size - n)
    prefix = [0] * size

    def play(a: int, b: int) -> tuple[int, int]:
        x, y = head[a], head[b]
        if y is None:
            return a, b
        if x is None:
            return b, a
        if prefix[a] != prefix[b]:
            return (a, b) if prefix[a] > prefix[b] else (b, a)
        common = _common(x, y, prefix[a])
        if common == len(x) or (common < len(y) and x[common] < y[common]):
            prefix[b] = common
            return a, b
        prefix[a] = common
        return b, a

    losers = [0] * size
    winners = list(range(size))
    level = size
    at = {k: k - size for k in range(size, 2 * size)}
    while level > 1:
        for node in range(level // 2, level):
            at[node], losers[node] = play(at.pop(2 * node), at.pop(2 * node + 1))
        level //= 2
    winner = at.get(1, winners[0])
    while (string := head[winner]) is not None:
        yield winner, string, prefix[winner]
        head[winner], prefix[winner] = next(runs[winner], (None, 0))
        node = (winner + size) // 2
        while node:
            winner, losers[node] = play(winner, losers[node])
            node //= 2


def merged(pieces: DataFrame, least: int, suffixes: bool = False, sides: bool = False) -> DataFrame:
    """(kind, dk, chk, low, high, hash, place, windows, done, rest) from the merge of all runs.

    Intervals are the most that a suffix shares with a neighbour, from ``least`` bytes on, unless
    it is known to repeat; with ``sides`` what it shares with either neighbour. With
    ``suffixes`` there are also open and settled suffixes, and the number of windows ``done``.
    """
    schema = "kind int, dk long, chk int, low int, high int, hash long, place int, windows int, done int, rest binary"
    kinds = {"int": pa.int32(), "long": pa.int64(), "binary": pa.binary()}
    fields = [part.split() for part in schema.split(", ")]
    dtypes = {"hash": np.int64, "dks": np.int64, "chks": np.int32, "lows": np.int32, "places": np.int16, "windows": np.int16, "known": np.int8}

    def out(**columns) -> pa.RecordBatch:
        n = len(columns["dk"])
        arrays = [columns[c] if isinstance(columns.get(c), pa.Array) else pa.array(columns[c], kinds[t]) if c in columns else pa.nulls(n, kinds[t]) for c, t in fields]
        return pa.RecordBatch.from_arrays(arrays, names=[c for c, _ in fields])

    def one_range(rows: list[dict]) -> Iterator[pa.RecordBatch]:
        columns = {k: np.concatenate([np.frombuffer(r[k], dtype=t) for r in rows]) for k, t in dtypes.items()}
        starts = np.cumsum([0, *(r["n"] for r in rows)]).tolist()
        runs = [_unfold(np.frombuffer(r["shared"], np.int16).tolist(), np.frombuffer(r["sizes"], np.int16).tolist(), r["rest"]) for r in rows]
        place = starts[:-1]
        order, strings, shared = [], [], []
        for r, string, common in merge_runs(runs):
            order.append(place[r])
            place[r] += 1
            strings.append(string)
            shared.append(common)
        at = np.array(order)
        dk, chk, low, places, windows, known, hashes = (columns[c][at] for c in ("dks", "chks", "lows", "places", "windows", "known", "hash"))
        sizes = np.fromiter(map(len, strings), dtype=np.int64, count=len(strings))
        before = np.array(shared, dtype=np.int64)
        behind = np.append(before[1:], 0)
        if sides:
            for common in (before, behind):
                hit = np.flatnonzero(common >= least)
                yield out(kind=np.full(len(hit), INTERVAL), dk=dk[hit], chk=chk[hit], low=low[hit], high=low[hit] + common[hit])
            return
        most = np.maximum(before, behind)
        hit = np.flatnonzero((most >= least) & (known == 0))
        if len(hit):
            yield out(kind=np.full(len(hit), INTERVAL), dk=dk[hit], chk=chk[hit], low=low[hit], high=low[hit] + most[hit])
        if not suffixes:
            return
        settled = np.where(known != 0, windows, np.clip(most - least + 1, 0, windows))
        done = settled == windows
        same = np.append(False, (before[1:] == sizes[1:]) & (sizes[1:] == sizes[:-1]))
        passed = ~done | ~same
        index = np.flatnonzero(passed)
        for k in range(0, len(index), 20_000):
            i = index[k : k + 20_000]
            yield out(
                kind=np.where(done[i], SETTLED, OPEN), dk=dk[i], chk=chk[i], low=low[i], hash=hashes[i], place=places[i], windows=windows[i],
                done=settled[i], rest=[strings[j] for j in i.tolist()],
            )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        dest, rows = None, []
        for batch in batches:
            told = batch.filter(pa.array(batch.column("kind").to_numpy() == INTERVAL))
            if told.num_rows:
                yield out(**{c: told.column(c) for c in ("kind", "dk", "chk", "low", "high")})
            for row in batch.filter(pa.array(batch.column("kind").to_numpy() != INTERVAL)).to_pylist():
                if row["dest"] != dest and rows:
                    yield from one_range(rows)
                    rows = []
                dest = row["dest"]
                rows.append(row)
        if rows:
            yield from one_range(rows)

    return pieces.repartition("dest").sortWithinPartitions("dest").mapInArrow(run, schema)


def _open_windows(first: DataFrame, sample: dict[str, list[bytes]], length: int, gram: int) -> DataFrame:
    """(kind, dk, chk, low, starts, rest): where suffixes of open windows, and of settled ones that may equal them, start."""
    opened = first.where(F.col("kind") == OPEN)
    settled = first.where(F.col("kind") == SETTLED).join(opened.select("hash").distinct(), "hash", "left_semi").select(opened.columns)
    items = opened.unionByName(settled)
    ranges = max(1, items.count() * 2 * length // RUN_BYTES)
    sides = merged(side_runs(items, cut_ranges(sample["left"], ranges), cut_ranges(sample["right"], ranges), gram), gram + 1, sides=True)
    shared = F.col("high") - F.col("low")
    right = F.col("low").bitwiseAND(F.lit(1)) == 1
    reach = sides.groupBy("dk", "chk", F.shiftright("low", 1).alias("low")).agg(
        F.max(F.when(right, shared - 1)).alias("after"), F.collect_set(F.when(~right, shared - 1 - gram)).alias("depths")
    )
    reach = stored(items.join(reach, ["dk", "chk", "low"]).where(F.col("after").isNotNull() & (F.size("depths") > 0)))
    farthest = F.col("place") - F.greatest("done", F.col("place") - F.array_max("depths"))
    nearest = F.greatest(length - F.col("after"), F.col("place") - F.col("windows") + 1)
    reach = reach.withColumn("near", nearest).withColumn("asks", (F.col("kind") == OPEN) & (nearest <= farthest))
    depths = reach.select("hash", "asks", F.explode("depths").alias("depth")).groupBy("hash").agg(F.max("asks").alias("asked"), F.collect_set("depth").alias("all"))
    held = reach.join(depths.where("asked"), "hash").where(F.col("asks") | (F.col("done") > 0))
    # Open and settled windows of one suffix alike: what is settled stands in as what others may equal.
    fits = F.filter("all", lambda d: (d <= F.col("place")) & (d >= F.when(F.col("asks"), F.col("near")).otherwise(F.lit(0))))
    starts = F.transform(fits, lambda d: (F.col("place") - d).cast("int"))
    starts = F.filter(starts, lambda j: j < F.col("windows"))
    return held.select("kind", "dk", "chk", "low", starts.alias("starts"), "rest").where(F.size("starts") > 0)


def _cut(rows: DataFrame) -> DataFrame:
    """(id, n_bytes, spans, kept) for rows (id, text, found)."""
    schema = f"id {dict(rows.dtypes)['id']}, n_bytes long, spans array<struct<start:long,stop:long>>, kept binary"
    spans_type = pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes, spans, kept = [], [], []
            for text, found in zip(batch.column("text").to_pylist(), batch.column("found").to_pylist(), strict=True):
                raw = text.encode()
                joined: list[list[int]] = []
                for low, high in sorted((f["low"], f["high"]) for f in found or ()):
                    if joined and low <= joined[-1][1]:
                        joined[-1][1] = max(joined[-1][1], high)
                    else:
                        joined.append([low, high])
                edges = [0, *(x for span in joined for x in span), len(raw)]
                sizes.append(len(raw))
                spans.append([{"start": a, "stop": b} for a, b in joined])
                kept.append(b"".join(raw[a:b] for a, b in zip(edges[::2], edges[1::2], strict=True)))
            arrays = [batch.column("id"), pa.array(sizes, pa.int64()), pa.array(spans, spans_type), pa.array(kept, pa.binary())]
            yield pa.RecordBatch.from_arrays(arrays, names=["id", "n_bytes", "spans", "kept"])

    return rows.select("id", "text", "found").mapInArrow(run, schema)


def dedup_passages(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """(id, n_bytes, spans, kept): the byte spans that repeat elsewhere, and what is left.

    Null texts count as empty; texts shorter than ``length`` bytes cannot repeat. Repeated
    rows are occurrences of their own, so both lose what they share. An empty table gives an
    empty result; other columns of ``df`` do not matter. ``kept`` is binary, since a cut may
    fall within a character.
    """
    if not gram < length <= gram + 255:
        raise ValueError("length must exceed gram, by 255 at most")
    spark = df.sparkSession
    text = F.coalesce(F.col(text_col), F.lit("")).alias("text")
    docs = df.select(F.col(id_col).alias("id"), text)
    docs = docs.withColumn("dk", F.xxhash64("text")).withColumn("chk", F.hash("text"))
    texts = docs.where(F.octet_length("text") >= length).groupBy("dk", "chk").agg(F.first("text").alias("text"), F.count(F.lit(1)).alias("copies"))
    found = stored(repeated_anchors(find_anchors(texts, length, gram)))
    release(spark)
    n_found = found.count()
    sample = splitters(docs, found, n_found, gram)
    spots = found.groupBy("dk", "chk").agg(F.collect_set("pack").alias("packs"))

    ranges = max(1, n_found * (length + length // 2) // RUN_BYTES)
    pieces = suffix_runs(texts.join(spots, ["dk", "chk"]), cut_ranges(sample["suffix"], ranges), length, gram)
    first = stored(merged(pieces, length, suffixes=True))
    release(spark)
    windows = stored(_open_windows(first, sample, length, gram))
    release(spark)
    total = windows.agg(F.coalesce(F.sum(F.size("starts") * F.length("rest")), F.lit(0))).first()[0]
    second = merged(window_runs(windows, cut_ranges(sample["suffix"], max(1, total // RUN_BYTES)), length), length)

    ends = docs.select("dk", "chk", F.lit(0).alias("low"), F.octet_length("text").alias("high")).where(F.col("high") >= length)
    copied = ends.groupBy("dk", "chk", "low", "high").agg(F.count(F.lit(1)).alias("copies")).where("copies > 1")
    columns = ["dk", "chk", "low", "high"]
    spans = first.where(F.col("kind") == INTERVAL).select(columns).unionByName(second.select(columns)).unionByName(copied.select(columns))
    spans = spans.groupBy("dk", "chk")
    spans = spans.agg(F.collect_set(F.struct("low", "high")).alias("found"))
    return _cut(docs.join(spans, ["dk", "chk"], "left"))


def digest(cut: DataFrame) -> DataFrame:
    """The contract's columns."""
    removed = F.aggregate("spans", F.lit(0).cast("long"), lambda total, span: total + span["stop"] - span["start"])
    return cut.select(
        F.col("id").alias("doc_id"), "n_bytes", removed.alias("n_removed"), F.size("spans").cast("long").alias("n_spans"), F.sha2("kept", 256).alias("kept_sha256")
    )
