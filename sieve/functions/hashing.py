"""The same 64-bit words in numpy (builder) and in Catalyst (probe).

Word A of a key is ``xxhash64(seed, key64)`` and word B is ``xxhash64(seed, A)``, as
Spark chains them from its own start value 42. The numpy mirror below gives the same
bits, so a filter built in an Arrow worker is probed by generated JVM code.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import cache
from importlib import import_module
from typing import NamedTuple

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

#: The five 64-bit primes of XXH64.
P1, P2, P3, P4, P5 = (np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))
#: The finaliser constants of the 64-bit murmur mixer.
M1, M2 = np.uint64(0xFF51AFD7ED558CCD), np.uint64(0xC4CEB9FE1A85EC53)
_START = 42
LOW32 = 0xFFFFFFFF


def _rotate(x: np.ndarray, by: int) -> np.ndarray:
    return (x << np.uint64(by)) | (x >> np.uint64(64 - by))


def xx_long(x: np.ndarray, seed: np.ndarray | int) -> np.ndarray:
    """XXH64 of 8-byte integers (uint64) under a seed."""
    with np.errstate(over="ignore"):
        h = np.asarray(seed, np.uint64) + P5 + np.uint64(8)
        h = h ^ (_rotate(x * P2, 31) * P1)
        h = _rotate(h, 27) * P1 + P4
        h = (h ^ (h >> np.uint64(33))) * P2
        h = (h ^ (h >> np.uint64(29))) * P3
        return h ^ (h >> np.uint64(32))


def seeded(seed: int, x: np.ndarray) -> np.ndarray:
    """``xxhash64(seed, x)`` of Spark, for uint64 ``x``."""
    start = xx_long(np.array([seed & 0xFFFFFFFFFFFFFFFF], np.uint64), _START)[0]
    return xx_long(x, start)


def murmur(x: np.ndarray, seed: int) -> np.ndarray:
    """The seeded murmur finaliser (ablation: another hash family)."""
    with np.errstate(over="ignore"):
        h = x + np.uint64(seed & 0xFFFFFFFFFFFFFFFF)
        h = (h ^ (h >> np.uint64(33))) * M1
        h = (h ^ (h >> np.uint64(33))) * M2
        return h ^ (h >> np.uint64(33))


def words(key64: np.ndarray, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """Words A and B of keys (int64 in, uint64 out)."""
    a = seeded(seed, key64.view(np.uint64))
    return a, seeded(seed, a)


def reduce32(x: np.ndarray, size: int) -> np.ndarray:
    """Multiply-shift of 32-bit values to 0..size-1 (int64)."""
    return ((x * np.uint64(size)) >> np.uint64(32)).astype(np.int64)


def high(x: np.ndarray) -> np.ndarray:
    return x >> np.uint64(32)


def low(x: np.ndarray) -> np.ndarray:
    return x & np.uint64(LOW32)


def first_segment(a: np.ndarray, seg_len: int, seg_count: int, arity: int, layout: str) -> np.ndarray:
    """The segment a key's first cell is about in: what keys are put in order by."""
    if layout == "overlap":
        return reduce32(high(a), (seg_count - arity) * seg_len + 1) // seg_len
    return reduce32(high(a), seg_count - arity + 1)


def locations(a: np.ndarray, b: np.ndarray, seg_len: int, seg_count: int, arity: int, layout: str) -> np.ndarray:
    """Cells of every key, one column a cell (int64)."""
    out = np.empty((len(a), arity), np.int64)
    if layout == "blocks":  # one cell in each of three large blocks
        for j, x in enumerate((high(a), high(b), low(b))):
            out[:, j] = reduce32(x, seg_len) + j * seg_len
        return out
    if layout == "overlap":  # the windows start at any cell
        base = reduce32(high(a), (seg_count - arity) * seg_len + 1)
    else:
        base = reduce32(high(a), seg_count - arity + 1) * seg_len
    width = 64 // arity if layout == "plain" else seg_len.bit_length() - 1
    for j in range(arity):
        piece = b >> np.uint64(j * width)
        if layout == "plain":
            piece = piece & np.uint64((1 << width) - 1)
            offset = ((piece * np.uint64(seg_len)) >> np.uint64(width)).astype(np.int64)
        else:
            offset = (piece & np.uint64(seg_len - 1)).astype(np.int64)
        out[:, j] = base + j * seg_len + offset
    return out


class Fingerprints(NamedTuple):
    """A fingerprint function: 64 bits from a key's word A in numpy (uint64) and in Catalyst (bigint), bit for bit alike.

    The low bits of what it gives are stored; they must be spread as evenly as word A's.
    """

    array: Callable[[np.ndarray], np.ndarray]
    column: Callable[[Column], Column]


#: Both halves of word A, folded.
FOLDED = Fingerprints(lambda a: a ^ high(a), lambda a: a.bitwiseXOR(high_column(a)))


@cache
def fingerprint_function(path: str) -> Fingerprints:
    """The function named ``module:attribute``; the workers import it as well. Empty: word A itself.

    A saved filter keeps the name, so load filters only from where you would import code.
    """
    if not path:
        return Fingerprints(lambda a: a, lambda a: a)
    module, _, name = path.partition(":")
    found = getattr(import_module(module), name)
    if not isinstance(found, Fingerprints):
        raise TypeError(f"{path} is no fingerprint function")
    return found


def fingerprint(a: np.ndarray, bits: int, function: str = "") -> np.ndarray:
    a = fingerprint_function(function).array(a)
    return (a & np.uint64((1 << bits) - 1)).astype({8: np.uint8, 16: np.uint16}.get(bits, np.uint32))


# --- Column twins ---------------------------------------------------------------


def shift_right(x: Column, by: Column | int) -> Column:
    return F.call_function("shiftrightunsigned", x, F.lit(by) if isinstance(by, int) else by)


def shift_left(x: Column, by: Column | int) -> Column:
    return F.call_function("shiftleft", x, F.lit(by) if isinstance(by, int) else by)


def word_columns(key64: Column, seed: Column) -> tuple[Column, Column]:
    a = F.xxhash64(seed, key64)
    return a, F.xxhash64(seed, a)


def reduce_column(x32: Column, size: Column) -> Column:
    """ANSI-safe: both factors are below 2**32 and 2**31."""
    return shift_right(x32 * size.cast("long"), 32)


def high_column(x: Column) -> Column:
    return shift_right(x, 32)


def low_column(x: Column) -> Column:
    return x.bitwiseAND(F.lit(LOW32))


def location_columns(a: Column, b: Column, seg_len: Column, seg_count: Column, arity: int, layout: str) -> list[Column]:
    """Column twins of ``locations`` (bigint)."""
    seg_len = seg_len.cast("long")
    if layout == "blocks":
        return [reduce_column(x, seg_len) + F.lit(j) * seg_len for j, x in enumerate((high_column(a), high_column(b), low_column(b)))]
    if layout == "overlap":
        base = reduce_column(high_column(a), (seg_count - arity) * seg_len + 1)
    else:
        base = reduce_column(high_column(a), seg_count - (arity - 1)) * seg_len
    out = []
    for j in range(arity):
        if layout == "plain":
            width = 64 // arity
            piece = shift_right(b, j * width).bitwiseAND(F.lit((1 << width) - 1))
            offset = shift_right(piece * seg_len, width)
        else:
            width = F.bit_count(seg_len - 1).cast("int")
            offset = shift_right(b, F.lit(j) * width).bitwiseAND(seg_len - 1)
        out.append(base + F.lit(j) * seg_len + offset)
    return out
