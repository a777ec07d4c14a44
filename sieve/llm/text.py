"""Vectorised word and shingle hashing shared by the text operators.

A word is a maximal run of bytes outside 0x20 and 0x09-0x0D of the UTF-8 text. Its
hash is the sum, modulo 2**64, of one random number for each (byte, offset inside
the word); a sum over a stretch is the difference of two running sums, so no Python
loop runs over words. Numbers of different offsets are unrelated, so words that
repeat a structure (powers, Thue-Morse words) collide no more often than others.
Hashes of n words are combined pairwise through a finaliser for the same reason.
A second, independent lane gives 128 bits where windows are compared across a corpus.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import IntegralType

from sieve.plans.names import fresh

__all__ = ["as_bytes", "fresh", "lists", "mix", "ngrams", "release", "shingles", "signed", "slices", "starts", "whole", "word_hashes"]

#: Bytes of text hashed at once; longer texts are cut at white space.
PIECE = 1 << 20
_WHITE = np.zeros(256, bool)
_WHITE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser (splitmix64)."""
    x = x + np.uint64(0x9E3779B97F4A7C15)
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


#: Offsets inside a word whose numbers are tabulated; those beyond are computed.
NEAR = 32
_LANES = (np.uint64(0xD6E8FEB86659FD93), np.uint64(0xA24BAED4963EE407))


def _numbers(byte: np.ndarray, offset: np.ndarray, lane: int) -> np.ndarray:
    """The random number of a byte at an offset."""
    return mix(mix((offset.astype(np.uint64) << np.uint64(8) | byte.astype(np.uint64)) + _LANES[lane]) ^ _LANES[lane])


_TABLES = [_numbers(np.tile(np.arange(256), NEAR), np.repeat(np.arange(NEAR), 256), lane) for lane in range(2)]
_TRIM = getattr(ctypes.CDLL(None), "malloc_trim", None)


def as_bytes(column: pa.Array, lower: bool = False) -> list[bytes]:
    """UTF-8 bytes of a string column; null is empty. ``lower`` maps A-Z only."""
    kind = pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()
    out = [x or b"" for x in column.cast(kind).to_pylist()]
    return [x.lower() for x in out] if lower else out


def _pieces(texts: list[bytes]) -> Iterator[tuple[list[bytes], list[int]]]:
    """Groups of about PIECE bytes with the text each part belongs to."""
    parts: list[bytes] = []
    owners: list[int] = []
    held = 0
    for k, t in enumerate(texts):
        at = 0
        while True:
            end = len(t)
            if end - at > PIECE:
                end = at + PIECE
                while end < len(t) and not _WHITE[t[end]]:
                    end += 1
            parts.append(t[at:end] if at or end < len(t) else t)
            owners.append(k)
            held += end - at + 1
            at = end
            if held >= PIECE:
                yield parts, owners
                parts, owners, held = [], [], 0
            if at >= len(t):
                break
    if parts:
        yield parts, owners


def word_hashes(texts: list[bytes], lane: int | tuple[int, ...] = 0) -> tuple[np.ndarray, np.ndarray]:
    """(hash of every word in order, words of each text); several lanes give rows of hashes."""
    lanes = (lane,) if isinstance(lane, int) else lane
    hashes: list[list[np.ndarray]] = [[] for _ in lanes]
    counts = np.zeros(len(texts), np.int64)
    for parts, owners in _pieces(texts):
        buf = np.frombuffer(b" ".join(parts) + b" ", np.uint8)
        white = _WHITE[buf]
        edge = np.flatnonzero(white[1:] != white[:-1]) + 1
        if not white[0]:
            edge = np.concatenate(([0], edge))
        if not len(edge):
            continue
        s, e = edge[0::2], edge[1::2]
        length = e - s
        offset = np.arange(len(buf), dtype=np.int32)
        gap = np.zeros(len(buf), np.int32)  # from the start of the word before to this word's start
        gap[s] = np.diff(s, prepend=0)
        offset -= np.cumsum(gap, dtype=np.int32)
        offset[white] = 0
        far = np.flatnonzero(offset >= NEAR) if length.max() > NEAR else None
        at = np.minimum(offset, NEAR - 1) * np.int32(256) + buf
        for out, k in zip(hashes, lanes, strict=True):
            numbers = _TABLES[k][at]
            if far is not None:
                numbers[far] = _numbers(buf[far], offset[far], k)
            total = np.zeros(len(buf) + 1, np.uint64)
            np.cumsum(numbers, out=total[1:])
            out.append(mix(total[e] - total[s] + length.astype(np.uint64)))
        ends = np.cumsum([len(p) + 1 for p in parts])
        per_part = np.bincount(np.searchsorted(ends, s, "right"), minlength=len(parts))
        np.add.at(counts, owners, per_part)
    made = [np.concatenate(h) if h else np.zeros(0, np.uint64) for h in hashes]
    return (made[0] if isinstance(lane, int) else np.stack(made)), counts


def ngrams(w: np.ndarray, n: int) -> np.ndarray:
    """Hash of the n words from every position (len(w) - n + 1 values), order-sensitive.

    Stretches of 1, 2, 4, ... words are made by joining two of half the length; the
    stretches whose lengths add up to n are joined in the end. Every join is mixed.
    """
    if len(w) < n:
        return np.zeros(0, np.uint64)
    join = lambda a, b: mix(a * np.uint64(0xC2B2AE3D27D4EB4F) + b)
    have, width, out, done = w, 1, None, 0
    while True:
        if n & width:
            part = have[done : done + len(w) - n + 1]
            out = part if out is None else join(out, part)
            done += width
        if width * 2 > n:
            return mix(out)
        have = join(have[:-width], have[width:])
        width *= 2


def starts(counts: np.ndarray) -> np.ndarray:
    """Offsets of each text's words, with the end as last value."""
    return np.concatenate(([0], np.cumsum(counts)))


def shingles(w: np.ndarray, counts: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct n-word shingle hashes of each text, sorted, and their number.

    A text with 1 to n-1 words has its whole sequence as its only shingle.
    """
    at = starts(counts)
    grams = ngrams(w, n)
    out, sizes = [], np.zeros(len(counts), np.int64)
    for k in range(len(counts)):
        a, b = at[k], at[k + 1]
        if b - a >= n:
            u = np.unique(grams[a : b - n + 1])
        elif b > a:
            u = mix(ngrams(w[a:b], int(b - a)) + np.uint64(b - a))
        else:
            continue
        sizes[k] = len(u)
        out.append(u)
    return (np.concatenate(out) if out else np.zeros(0, np.uint64)), sizes


def slices(batch: pa.RecordBatch, text: int, limit: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """Parts of a batch with about ``limit`` bytes of text each, one row at least."""
    if not batch.num_rows:
        return
    sizes = np.asarray(pc.fill_null(pc.binary_length(batch.column(text)), 0)).astype(np.int64)
    group = np.cumsum(sizes) // limit
    cuts = np.concatenate(([0], np.flatnonzero(group[1:] != group[:-1]) + 1, [batch.num_rows]))
    for a, b in zip(cuts[:-1], cuts[1:], strict=True):
        yield batch.slice(a, b - a)
    release()


def release() -> None:
    """Gives freed memory back to the system: a worker lives as long as its executor."""
    pa.default_memory_pool().release_unused()
    if _TRIM:
        _TRIM(0)


def signed(x: np.ndarray) -> pa.Array:
    return pa.array(x.view(np.int64))


def lists(values: pa.Array, sizes: np.ndarray) -> pa.Array:
    """A list column from concatenated values."""
    return pa.ListArray.from_arrays(pa.array(starts(sizes).astype(np.int32)), values)


def whole(df: DataFrame, key: str) -> Column:
    """The id column as a 64-bit number; other than whole numbers are refused when the plan is made."""
    kind = df.schema[key].dataType
    if not isinstance(kind, IntegralType):
        raise TypeError(f"column {key} holds ids and must be of a whole-number type, not {kind.simpleString()}")
    return F.col(f"`{key}`").cast("long")
