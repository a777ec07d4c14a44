"""Static schemas of the engine's tables."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import types as T

#: One row a filter and shard. Exactly one of the payload groups is filled, by kind.
FILTERS = T.StructType(
    [
        T.StructField("filter_id", T.StringType()),
        T.StructField("kind", T.StringType()),
        T.StructField("shard", T.IntegerType()),
        T.StructField("shard_bits", T.IntegerType()),
        T.StructField("n", T.LongType()),
        T.StructField("arity", T.IntegerType()),
        T.StructField("fp_bits", T.IntegerType()),
        T.StructField("seed", T.LongType()),
        T.StructField("attempts", T.IntegerType()),
        T.StructField("seg_len", T.IntegerType()),
        T.StructField("seg_count", T.IntegerType()),
        T.StructField("array_len", T.IntegerType()),
        T.StructField("params", T.MapType(T.StringType(), T.StringType())),
        T.StructField("cells8", T.ArrayType(T.ByteType())),
        T.StructField("cells16", T.ArrayType(T.ShortType())),
        T.StructField("cells32", T.ArrayType(T.IntegerType())),
        T.StructField("words", T.ArrayType(T.LongType())),
        T.StructField("payload_bits", T.LongType()),
        T.StructField("build_ns", T.LongType()),
    ]
)

MEASUREMENTS = T.StructType(
    [
        T.StructField("workload", T.StringType()),
        T.StructField("filter", T.StringType()),
        T.StructField("param", T.StringType()),
        T.StructField("n", T.LongType()),
        T.StructField("n_probe", T.LongType()),
        T.StructField("hit_share", T.DoubleType()),
        T.StructField("bits_per_key", T.DoubleType()),
        T.StructField("fpr", T.DoubleType()),
        T.StructField("overhead", T.DoubleType()),
        T.StructField("build_ns_per_key", T.DoubleType()),
        T.StructField("probe_ns_per_key", T.DoubleType()),
        T.StructField("build_spread", T.DoubleType()),
        T.StructField("build_query_ratio", T.DoubleType()),
        T.StructField("attempts", T.IntegerType()),
        T.StructField("repeat", T.IntegerType()),
        T.StructField("note", T.StringType()),
    ]
)


@dataclass(frozen=True)
class Spec:
    """What a probe must know of a filter before it sees a row of it."""

    kind: str
    fp_bits: int = 8
    arity: int = 3
    family: str = "xxhash64"
    layout: str = "fuse"  # fuse, overlap, plain (segments of any length), blocks (xor)
    bits_per_key: float = 12.0
    hashes: int = 8
    homogeneous: bool = False
    size_factor: float = 0.0  # 0: the sizing tables
    max_load: float = 0.94
    power_of_two: bool = False
    presort: bool = True
    buffered: bool = False  # xor: keys pass through buffers by region of the array
    fingerprint: str = ""  # "module:attribute" of a fingerprint function of the caller's
    order: str = "layer"
    max_attempts: int = 100

    @property
    def cells(self) -> str:
        return f"cells{8 if self.fp_bits <= 8 else 16 if self.fp_bits <= 16 else 32}"


def spec(kind: str, **how) -> Spec:
    """A Spec by name: fuse3, fuse4, fuse5.., xor, xorplus, bloom, blocked, cuckoo, ribbon, vqf."""
    if kind.startswith("fuse"):
        how.setdefault("arity", int(kind[4:]))
        if not 3 <= how["arity"] <= 8:
            raise ValueError("arity must be 3 to 8")
    elif kind in ("xor", "xorplus"):
        how.update(arity=3, layout="blocks")
    elif kind == "bloom":
        from sieve.functions.sizing import bloom_hashes

        how.setdefault("bits_per_key", 12.0)
        how.setdefault("hashes", bloom_hashes(how["bits_per_key"]))
    elif kind == "cuckoo":
        how.setdefault("fp_bits", 12)
    elif kind not in ("blocked", "ribbon", "vqf"):
        raise ValueError(f"unknown kind {kind}")
    allowed = {"cuckoo": range(4, 17), "ribbon": range(1, 33), "vqf": (8,)}.get(kind, (8, 16, 32))
    if how.get("fp_bits", 8) not in allowed:
        raise ValueError(f"{kind} takes fingerprints of {list(allowed)} bits")
    made = Spec(kind, **how)
    if made.fingerprint and not made.kind.startswith(("fuse", "xor")):
        raise ValueError(f"{kind} takes no fingerprint function")
    if made.buffered and kind not in ("xor", "xorplus"):
        raise ValueError("only xor and xorplus are built through buffers")
    return made
