"""Space bounds and costs as formulas, in Columns."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sieve.functions import sizing

#: Bits per key at false-positive probability 2**-k, as (factor, constant) of k.
CURVES = {"bound": (1.0, 0.0), "bloom": (1 / math.log(2), 0.0), "xor": (1.23, 0.0), "xorplus": (1.0824, 0.5125), "fuse3": (1.125, 0.0), "fuse4": (1.075, 0.0)}
CUCKOO_CAPACITY = 0.955


def bound(eps: Column) -> Column:
    return -F.log2(eps)


def bits_for(curve: str, k: Column, capacity: float = CUCKOO_CAPACITY) -> Column:
    """Bits per key of a structure at false-positive probability 2**-k."""
    if curve == "cuckoo":  # k + 3 fingerprint bits: eight slots are compared
        return (k + 3) / F.lit(capacity)
    factor, constant = CURVES[curve]
    return k * F.lit(factor) + F.lit(constant)


def set_bits(curve: str, k: Column, n: Column) -> Column:
    """Bits that a structure over ``n`` keys takes at error 2**-k, its array padded as it is built; whole numbers.

    Xor+ keeps 0.64 of its third block's cells and 1.25 bits a cell of it: 1.0824k + 0.5125 a key in the limit.
    """
    n, k = n.cast("bigint"), k.cast("bigint")
    if curve == "bound":
        return n * k
    if curve == "bloom":
        return F.greatest(F.lit(64).cast("bigint"), F.ceil(F.ceil(n * k * F.lit(1 / math.log(2))) / 64) * 64)
    if curve == "cuckoo":
        return F.greatest(F.lit(2).cast("bigint"), F.ceil(n * 1000 / F.lit(round(4000 * CUCKOO_CAPACITY)))) * 4 * (k + 3)
    if curve == "xor":
        return 3 * sizing.xor_column(n) * k
    if curve == "xorplus":
        return F.ceil(sizing.xor_column(n) * (264 * k + 125) / 100)
    _, length, count = sizing.fuse_columns(n, int(curve.removeprefix("fuse")))
    return length * count * k


def curves_of(sets: DataFrame, low: int = 8, high: int = 16) -> DataFrame:
    """(source, n, k, curve, bits, set_bits): the curves, and what each structure takes for the sets (source, n)."""
    sized = sets.select("source", "n", F.explode(F.sequence(F.lit(low).cast("bigint"), F.lit(high).cast("bigint"))).alias("k"))
    k = F.col("k").cast("double")
    parts = [F.struct(F.lit(c).alias("curve"), F.round(bits_for(c, k), 6).alias("bits"), set_bits(c, F.col("k"), F.col("n")).alias("set_bits")) for c in (*CURVES, "cuckoo")]
    return sized.select("source", "n", "k", F.explode(F.array(*parts)).alias("x")).select("source", "n", "k", "x.curve", "x.bits", "x.set_bits")


def match_cuckoo(width: int = 64, capacity: float = 0.95) -> dict[str, int]:
    """Bits per key at which fuse filters have the false-positive probability of a cuckoo filter.

    ``width``: bits per key of the cuckoo filter; its fingerprints lose 3 bits to the slots.
    """
    k = width * capacity - 3
    return {"fuse3": math.floor(1.125 * k), "fuse4": math.floor(1.075 * k)}


def match_cuckoo_cells(cells: Column, n: Column, width: int = 64, capacity: float = 0.95) -> Column:
    """``match_cuckoo`` for an array of ``cells`` cells, padding included, over ``n`` keys."""
    return F.floor(cells * F.lit(round(1000 * (width * capacity - 3))) / (1000 * n)).cast("bigint")


def accesses(kind: str, eps: float = 0.01) -> int:
    """Cells or cache lines a positive probe touches."""
    return {"fuse3": 3, "xor": 3, "fuse4": 4, "cuckoo": 2, "blocked": 1, "vqf": 2, "ribbon": 2}.get(kind) or math.ceil(-math.log2(eps))


def collision_term(n: Column) -> Column:
    """What 64-bit hashing adds to the false-positive probability."""
    return n.cast("double") / F.lit(2.0**64)


def bloom_fpr(hashes: int, bits: float) -> float:
    return (1 - math.exp(-hashes / bits)) ** hashes


def blocked_fpr(bits: float, slots: int = 256) -> float:
    """Poisson mixture over the keys of a block."""
    mean, out, p = slots / bits, 0.0, math.exp(-slots / bits)
    for i in range(int(mean + 12 * math.sqrt(mean)) + 20):
        out += p * (1 - (31 / 32) ** i) ** 8
        p *= mean / (i + 1)
    return out


def expected_fpr(kind: str, fp_bits: int = 8, bits_per_key: float = 12.0, hashes: int = 8, load: float = 0.94) -> float:
    """The model of a kind's false-positive probability."""
    if kind == "bloom":
        return bloom_fpr(hashes, bits_per_key)
    if kind == "blocked":
        return blocked_fpr(bits_per_key)
    if kind == "cuckoo":
        return 8 * load / (2**fp_bits - 1)
    if kind == "vqf":
        return 2 * load * 48 / 80 / 256
    return 2.0**-fp_bits
