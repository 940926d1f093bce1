"""Vectorised reading of words from Arrow string columns.

A word is a maximal run of bytes outside space and 0x09-0x0D, with A-Z lower-cased. Texts are taken
whole; null counts as empty. Work goes in slices of bounded size, and a text longer than a slice is
cut at white space, so memory doesn't follow the longest text by more than eight bytes a word.
"""

from __future__ import annotations

import sys
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

ENCODERS = "_word_encoders"  # where a worker keeps the encoders of `tokens`
SLICE = 1 << 20
SPACE = np.zeros(256, bool)
SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
MULTIPLIER = 0x9E3779B97F4A7C15 | 1
MASK = (1 << 64) - 1


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser on unsigned 64-bit integers."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


@lru_cache(1)
def _tables(n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    codes = mix64(np.arange(1, 257, dtype=np.uint64) * np.uint64(0xD6E8FEB86659FD93))[LOWER]
    inverse = pow(MULTIPLIER, -1, 1 << 64)
    powers = np.full(n + 1, MULTIPLIER, np.uint64)
    powers[0] = 1
    back = np.full(n + 1, inverse, np.uint64)
    back[0] = 1
    return codes, np.cumprod(powers), np.cumprod(back)


def drop_tables() -> None:
    """For a worker that goes on to tokenize."""
    _tables.cache_clear()


def bytes_and_offsets(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes and int64 offsets of a string column; null is empty. A worker that comes here has done its tokenizing: its caches go."""
    sys.modules.pop(ENCODERS, None)
    column = pc.fill_null(column, "")
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    wide = pa.types.is_large_string(column.type)
    _, off, data = column.buffers()
    n, o = len(column), column.offset
    if n == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offsets = np.frombuffer(off, np.int64 if wide else np.int32)[o : o + n + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def slices(raw: np.ndarray, offsets: np.ndarray, size: int = SLICE) -> Iterator[tuple[int, int, int, int]]:
    """(first text, past last text, first byte, past last byte); a long text comes in several slices cut at white space."""
    i, n = 0, len(offsets) - 1
    while i < n:
        j = int(np.searchsorted(offsets, offsets[i] + size, "right")) - 1
        if j > i:
            yield i, min(j, n), int(offsets[i]), int(offsets[min(j, n)])
            i = min(j, n)
            continue
        at, end = int(offsets[i]), int(offsets[i + 1])
        while at < end:
            stop = min(at + size, end)
            while stop < end and not SPACE[raw[stop]]:
                stop += 1
            yield i, i + 1, at, stop
            at = stop
        i += 1


def word_spans(part: np.ndarray, cuts: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of the words of a slice, and the number of its first word for each cut (text border)."""
    inside = ~SPACE[part]
    first, last = inside.copy(), inside.copy()
    first[1:] &= ~inside[:-1]
    last[:-1] &= ~inside[1:]
    some = cuts[:-1][np.diff(cuts) > 0]
    first[some] = inside[some]
    ends = cuts[1:][np.diff(cuts) > 0] - 1
    last[ends] = inside[ends]
    starts = np.flatnonzero(first)
    return starts, np.flatnonzero(last) + 1, np.searchsorted(starts, cuts)


def span_sums(part: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Polynomials over the lower-cased bytes of spans, wherever they stand."""
    size = max(len(part), SLICE + 4096)
    codes, powers, back = _tables(1 << int(size - 1).bit_length())
    sums = np.zeros(len(part) + 1, np.uint64)
    np.cumsum(codes[part] * powers[: len(part)], out=sums[1:])
    return (sums[ends] - sums[starts]) * back[starts]


def joined_sum(sum_a: np.uint64, size_a: int, sum_b: np.uint64, size_b: int) -> tuple[np.uint64, int]:
    """Polynomial and size of a span from those of its two parts."""
    return np.uint64((int(sum_a) + pow(MULTIPLIER, int(size_a), 1 << 64) * int(sum_b)) & MASK), int(size_a) + int(size_b)


def span_hashes(part: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hashes of byte spans, equal for equal lower-cased bytes wherever they stand."""
    return mix64(span_sums(part, starts, ends) + (ends - starts).astype(np.uint64))


def hashed_spans(column: pa.Array, prefixes: tuple[int, ...] = ()) -> Iterator[tuple[int, int, np.ndarray, list[np.ndarray]]]:
    """(first text, past last text, word borders of these texts, hashes of the words and of their first n (negative: last -n) bytes), each text whole."""
    raw, offsets = bytes_and_offsets(column)
    held: list[list[np.ndarray]] = []
    for i, j, a, b in slices(raw, offsets):
        part = raw[a:b]
        cuts = np.clip(offsets[i : j + 1], a, b) - a
        starts, ends, borders = word_spans(part, cuts)
        hashes = [span_hashes(part, starts, ends)]
        for n in prefixes:
            hashes.append(span_hashes(part, starts, np.minimum(ends, starts + n)) if n > 0 else span_hashes(part, np.maximum(starts, ends + n), ends))
        if j == i + 1 and (b < offsets[j] or held):  # a piece of a long text
            held.append(hashes)
            if b < offsets[j]:
                continue
            hashes, held = [np.concatenate(x) for x in zip(*held, strict=True)], []
            borders = np.array([0, len(hashes[0])])
        yield i, j, borders, hashes


def hashed_words(column: pa.Array) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first text, past last text, word borders of these texts, word hashes), each text whole."""
    for i, j, borders, hashes in hashed_spans(column):
        yield i, j, borders, hashes[0]


COMBINE = (
    np.uint64(0x9FB21C651E98DF25), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(0x165667B19E3779F9),
    np.uint64(0xD1B54A32D192ED03), np.uint64(0x8CB92BA72F3D8DD7), np.uint64(0xAAAAAAAB5EEDBEEF),
)


def shingle_hashes(borders: np.ndarray, words: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(text number, hash) of every k-word shingle; a text with 1 to k-1 words gives its whole sequence as one."""
    n = np.diff(borders)
    total = len(words)
    grams = np.zeros(max(0, total - k + 1), np.uint64)
    for t in range(k):
        grams += words[t : t + len(grams)] * COMBINE[t % len(COMBINE)] * np.uint64(2 * (t // len(COMBINE)) + 1)
    owner = np.repeat(np.arange(len(n)), n)
    whole = owner[: len(grams)] == owner[k - 1 :] if len(grams) else np.zeros(0, bool)
    texts, hashes = owner[: len(grams)][whole], mix64(grams[whole])
    short = np.flatnonzero((n > 0) & (n < k))
    if len(short):
        extra = []
        for d in short:
            own = words[borders[d] : borders[d + 1]]
            value = len(own)
            for w in own.tolist():
                value = ((value ^ w) * MULTIPLIER + len(own)) & MASK
            extra.append(value)
        texts = np.concatenate([texts, short])
        hashes = np.concatenate([hashes, mix64(np.array(extra, np.uint64))])
    return texts, hashes
