"""Structures over the md5 hash, which any SQL engine can recompute bit for bit."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sieve.functions import sizing
from sieve.functions.hashing import shift_right
from sieve.functions.keys import portable

BLOOM_HASHES, BLOOM_BITS = 8, 12


def _halves(key: Column) -> tuple[Column, Column]:
    """32 and 28 bits of the first portable word."""
    h = portable("k", key)
    return shift_right(h, 28), h.bitwiseAND(F.lit((1 << 28) - 1))


def bloom_places(key: Column, bits: int | Column, hashes: int = BLOOM_HASHES) -> Column:
    """Array of bit numbers by double hashing."""
    h1, h2 = _halves(key)
    m = F.lit(bits) if isinstance(bits, int) else bits
    return F.transform(F.sequence(F.lit(0), F.lit(hashes - 1)), lambda i: shift_right((h1 + i * h2).bitwiseAND(F.lit(0xFFFFFFFF)) * m.cast("bigint"), 32))


def bloom_size(n: int) -> int:
    """Bits, a multiple of 32."""
    return -(-n * BLOOM_BITS // 32) * 32


def bit_words(places: DataFrame, by: str = "bit") -> DataFrame:
    """(word, mask) of 32-bit words from rows of bit numbers."""
    mask = F.call_function("shiftleft", F.lit(1).cast("bigint"), F.col(by).bitwiseAND(F.lit(31)).cast("int"))
    return places.select(shift_right(F.col(by), 5).alias("word"), mask.alias("mask")).groupBy("word").agg(F.bit_or("mask").alias("mask"))


def blocked_places(key: Column, blocks: int) -> Column:
    """Array of eight bit numbers inside one 256-bit block, one in each 32-bit lane."""
    h1, _ = _halves(key)
    second = portable("k", key, 16)
    block = shift_right(h1 * F.lit(blocks).cast("bigint"), 32)
    return F.transform(F.sequence(F.lit(0), F.lit(7)), lambda i: block * 256 + i * 32 + F.call_function("shiftrightunsigned", second, i * 5).bitwiseAND(F.lit(31)))


def fuse_places(key: Column, seg_len: int, seg_count: int, arity: int) -> Column:
    """Array of ``arity`` cells in consecutive segments."""
    h1, _ = _halves(key)
    second = portable("k", key, 16)
    start = shift_right(h1 * F.lit(seg_count - arity + 1).cast("bigint"), 32)
    width = seg_len.bit_length() - 1
    return F.array(*[(start + j) * seg_len + shift_right(second, j * width).bitwiseAND(F.lit(seg_len - 1)) for j in range(arity)])


def xor_places(key: Column, block: int) -> Column:
    """Array of three cells, one in each block."""
    h1, _ = _halves(key)
    second = portable("k", key, 16)
    parts = (h1, shift_right(second, 28), portable("x", key).bitwiseAND(F.lit(0xFFFFFFFF)))
    return F.array(*[shift_right(x * F.lit(block).cast("bigint"), 32) + j * block for j, x in enumerate(parts)])


def fuse_keyed(df: DataFrame, key: str, arity: int) -> tuple[DataFrame, int, int]:
    """(key, locs) of a table's distinct keys, with the segment length and count."""
    keys = df.select(F.col(key).alias("key")).filter("key IS NOT NULL").distinct()
    _, length, count = sizing.fuse(keys.count(), arity)
    return keys.select("key", fuse_places(F.col("key"), length, count, arity).alias("locs")), length, count


def xor_keyed(df: DataFrame, key: str) -> tuple[DataFrame, int]:
    keys = df.select(F.col(key).alias("key")).filter("key IS NOT NULL").distinct()
    block = sizing.xor(keys.count())
    return keys.select("key", xor_places(F.col("key"), block).alias("locs")), block
