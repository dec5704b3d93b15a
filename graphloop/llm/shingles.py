"""Vectorised hashes of words and shingles of many texts at once."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

CHUNK_BYTES = 2_000_000
_RNG = np.random.Generator(np.random.PCG64(20))
BYTE_CODES = _RNG.integers(1, 2**63, 256, dtype=np.uint64)
STEP = np.uint64(0x9E3779B97F4A7C15)
_FOLD = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
_IS_SPACE = np.zeros(256, dtype=bool)
_IS_SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finisher."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def word_hashes(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(hash of every word, number of words before each text and in all)."""
    joined = np.frombuffer(b"\n".join(texts), dtype=np.uint8)
    lengths = np.fromiter(map(len, texts), dtype=np.int64, count=len(texts))
    firsts = np.cumsum(lengths + 1) - (lengths + 1)
    inside = ~_IS_SPACE[joined]
    edge = np.diff(inside.astype(np.int8), prepend=0, append=0)
    starts, stops = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
    if not len(starts):
        return np.empty(0, dtype=np.uint64), np.zeros(len(texts) + 1, dtype=np.int64)
    sizes = stops - starts
    begins = np.cumsum(sizes) - sizes
    place = np.arange(int(sizes.sum())) - np.repeat(begins, sizes)
    with np.errstate(over="ignore"):
        powers = np.multiply.accumulate(np.full(int(sizes.max()), STEP, dtype=np.uint64))
        hashes = np.add.reduceat(BYTE_CODES[joined[inside]] * powers[place], begins)
        hashes = mix(hashes + sizes.astype(np.uint64))
    return hashes, np.append(np.searchsorted(starts, firsts), len(starts))


def shingle_sets(texts: list[str | None], width: int) -> Iterator[np.ndarray]:
    """The sorted distinct shingle hashes of each text; A-Z are folded.

    A text of fewer words than ``width`` has its whole sequence as one shingle; one without
    words has none.
    """
    start = 0
    while start < len(texts):
        part, size = [], 0
        while start < len(texts) and (not part or size < CHUNK_BYTES):
            part.append((texts[start] or "").encode().translate(_FOLD))
            size += len(part[-1])
            start += 1
        words, upto = word_hashes(part)
        with np.errstate(over="ignore"):
            n = max(0, len(words) - width + 1)
            grams = np.zeros(n, dtype=np.uint64)
            for k in range(width):
                grams = grams * STEP + words[k : k + n]
            grams = mix(grams)
            for a, b in zip(upto[:-1].tolist(), upto[1:].tolist(), strict=True):
                if b - a >= width:
                    yield np.unique(grams[a : b - width + 1])
                elif b > a:
                    whole = np.uint64(b - a)
                    for w in words[a:b]:
                        whole = whole * STEP + w
                    yield mix(np.array([whole ^ np.uint64(0xA5A5A5A5)], dtype=np.uint64))
                else:
                    yield np.empty(0, dtype=np.uint64)
