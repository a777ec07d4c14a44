"""Array sizes of every kind, in Python and, for the formula queries, as Columns."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Fixed values, by arity: (base, slope, knee) of the array size n * (base + slope * max(1, ln knee / ln n))
#: and (log base, shift) of the segment size 2 ** floor(log_base n + shift).
FUSE = {3: ((0.875, 0.25, 1e6), (3.33, 2.25)), 4: ((0.77, 0.305, 6e5), (2.91, -0.5))}
#: Xor: cells per key and spare cells. Vector quotient: tags and buckets of a block, load.
XOR = (1.23, 32)
VQF_TAGS, VQF_BUCKETS, VQF_LOAD = 48, 80, 0.93
CUCKOO_SLOTS = 4


def segment(n: int, arity: int) -> int:
    base, shift = FUSE[min(arity, 4)][1]
    n = max(2, n)
    return 1 << max(0, math.floor(math.log(n) / math.log(base) + shift))


def fuse(n: int, arity: int, size_factor: float = 0.0) -> tuple[int, int, int]:
    """(cells before padding, segment length, segment count): at least ``arity`` segments."""
    n = max(2, n)
    length = min(segment(n, arity), 1 << (64 // arity))
    if size_factor:
        cells = math.floor(n * size_factor)
    else:
        base, slope, knee = FUSE[min(arity, 4)][0]
        cells = math.floor(n * (base + slope * max(1.0, math.log(knee) / math.log(n))))
    return cells, length, max(arity, -(-cells // length))


def xor(n: int) -> int:
    """Length of each of the three blocks."""
    return -(-(math.floor(XOR[0] * n) + XOR[1]) // 3)


def bloom_hashes(bits_per_key: float) -> int:
    return max(1, round(bits_per_key * math.log(2)))


def bloom_bits_for(eps: float) -> float:
    """Bits per key of a Bloom filter for a target false-positive probability."""
    return math.log2(1 / eps) / math.log(2)


def bloom_bits(n: int, bits_per_key: float) -> int:
    return max(64, -(-math.ceil(n * bits_per_key) // 64) * 64)


def blocked_blocks(n: int, bits_per_key: float) -> int:
    return max(1, math.ceil(n * bits_per_key / 256))


def cuckoo_buckets(n: int, max_load: float, power_of_two: bool = False) -> int:
    m = max(2, math.ceil(n / (CUCKOO_SLOTS * max_load)))
    return 1 << (m - 1).bit_length() if power_of_two else m


def ribbon_slots(n: int, attempt: int = 0) -> int:
    return math.ceil(n * 1.10 * 1.05**attempt) + 64


def vqf_blocks(n: int) -> int:
    return max(2, math.ceil(n / (VQF_TAGS * VQF_LOAD)))


def shard_bits(n: int, per_shard_log2: int = 20) -> int:
    """2**20 to 2**21 keys in a shard once there are that many."""
    return max(0, math.floor(math.log2(max(1, n))) - per_shard_log2)


# --- Column twins ---------------------------------------------------------------


def fuse_columns(n: Column, arity: int) -> tuple[Column, Column, Column]:
    (base, slope, knee), (log_base, shift) = FUSE[arity]
    n = F.greatest(n, F.lit(2)).cast("double")
    cells = F.floor(n * (F.lit(base) + F.lit(slope) * F.greatest(F.lit(1.0), F.lit(math.log(knee)) / F.log(n)))).cast("bigint")
    length = F.pow(F.lit(2.0), F.greatest(F.lit(0.0), F.floor(F.log(n) / F.lit(math.log(log_base)) + F.lit(shift)).cast("double"))).cast("bigint")
    count = F.greatest(F.lit(arity).cast("bigint"), F.ceil(cells / length).cast("bigint"))
    return cells, length, count


def xor_column(n: Column) -> Column:
    return F.ceil((F.floor(F.lit(XOR[0]) * n) + XOR[1]) / 3).cast("bigint")
