"""Space, accuracy and time measures over filters and probes."""

from __future__ import annotations

import time
from statistics import median

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from sieve.functions.hashing import locations, words
from sieve.functions.keys import with_key
from sieve.operators import probe
from sieve.operators.build import Filter, build_keys
from sieve.operators.contains import Loaded, places
from sieve.operators.kinds import fuse_shape
from sieve.schema import Spec


def bits_per_key(filters: DataFrame) -> DataFrame:
    """Payload bits over keys, padding included."""
    return filters.groupBy("filter_id", "kind").agg((F.sum("payload_bits") / F.sum("n")).alias("bits_per_key"))


def fpr(probed: DataFrame, flag: str = "maybe_member", truth: str = "is_member") -> Column | DataFrame:
    """Share of positives among probes known to be outside."""
    outside = ~F.col(truth)
    return probed.agg(F.avg(F.when(outside, F.col(flag).cast("double"))).alias("fpr"), F.count_if(outside).alias("outside"))


def false_negatives(probed: DataFrame, flag: str = "maybe_member", truth: str = "is_member") -> DataFrame:
    return probed.agg(F.count_if(F.col(truth) & ~F.col(flag)).alias("false_negatives"))


def relative_space(bits: Column, eps: Column) -> Column:
    """Bits per key over the information bound at the measured probability."""
    return bits / -F.log2(eps)


def overhead_pct(bits: Column, eps: Column) -> Column:
    return (relative_space(bits, eps) - 1) * 100


def failure_rate(filters: DataFrame) -> DataFrame:
    return filters.agg(F.avg((F.col("attempts") > 1).cast("double")).alias("failure_rate"), F.max("attempts").alias("most"))


def mean_degree(arity: Column, n: Column, cells: Column) -> Column:
    """Keys per cell."""
    return arity * n / cells


def segment_ratio(cells: Column, seg_len: Column) -> Column:
    return cells / seg_len


def pruned_share(df: DataFrame, f: Filter, keys: str) -> DataFrame:
    """Share of rows that the gate spares the exact join."""
    return probe.contains(df, f, keys).agg(F.avg((~F.col("maybe_member")).cast("double")).alias("pruned"))


def locality(loc_rows: DataFrame, order: list[str], loc: str = "loc") -> DataFrame:
    """Mean distance between successive touches in the given order, per shard."""
    step = F.abs(F.col(loc) - F.lag(loc).over(Window.partitionBy("shard").orderBy(*order)))
    return loc_rows.withColumn("step", step).groupBy("shard").agg(F.avg("step").alias("mean_step"))


def locality_of(keys: np.ndarray, s: Spec, seed: int = 1) -> tuple[float, float]:
    """Mean cell distance between keys in hash order and in segment order."""
    length, count = fuse_shape(len(keys), s)
    a, b = words(keys, seed)
    loc = locations(a, b, length, count, s.arity, s.layout)[:, 0]
    return float(np.abs(np.diff(loc)).mean()), float(np.abs(np.diff(loc[np.argsort(loc // length, kind="stable")])).mean())


def median_of(runs: list[float]) -> tuple[float, float]:
    """(median, half spread over the median)."""
    m = median(runs)
    return m, (max(runs) - min(runs)) / 2 / m if m else 0.0


def build_runs(keys: np.ndarray, s: Spec, seed: int = 1, min_s: float = 0.1, repeats: int = 3) -> tuple[list[float], int]:
    """(nanoseconds of the in-task builder, run by run, most seeds tried); short builds are repeated to ``min_s``."""
    runs, most = [], 0
    for r in range(repeats):
        done, began = 0, time.perf_counter()
        while not done or time.perf_counter() - began < min_s:
            most = max(most, build_keys(keys, s, seed + 1000 * r + done)[2])
            done += 1
        runs.append((time.perf_counter() - began) / done * 1e9)
    return runs, most


def loaded(keys: np.ndarray, s: Spec, seed: int = 1) -> tuple[Loaded, int]:
    """A filter in this process, with its logical bits."""
    made, own, _ = build_keys(keys, s, seed)
    row = {"seed": own, "seg_len": made.seg_len, "seg_count": made.seg_count, "array_len": made.array_len}
    if made.cells is not None:
        row[{1: "cells8", 2: "cells16", 4: "cells32"}[made.cells.itemsize]] = made.cells.view({1: np.int8, 2: np.int16, 4: np.int32}[made.cells.itemsize])
    if made.words is not None:
        row["words"] = made.words.view(np.int64)
    return Loaded(row, s), made.bits


def probe_runs(f: Loaded, probes: np.ndarray, repeats: int = 3) -> tuple[list[float], int]:
    """Nanoseconds of a numpy probe of all keys, run by run, and the matches counted."""
    runs, hits = [], 0
    for _ in range(repeats):
        began = time.perf_counter()
        hits = int(f.contains(probes).sum())
        runs.append((time.perf_counter() - began) * 1e9)
    return runs, hits


def touches(df: DataFrame, f: Filter, keys: str) -> DataFrame:
    """(touches, probes, cells): what the positive probes of ``df`` look at: of one probe, and of all ``probes`` of them."""
    hits = with_key(probe.semi(df, f, keys), [keys], f.shard_bits, f.spec.family).select("key64", "shard")
    shapes = F.broadcast(f.table.select("shard", "seed", "seg_len", "seg_count", "array_len")).alias("f")  # no payload
    seen = hits.alias("h").join(shapes, F.col("h.shard") == F.col("f.shard")).select(F.size(F.array(*places(F.col("h.key64"), "f", f.spec))).alias("touches"))
    return seen.groupBy("touches").agg(F.count("*").alias("probes"), F.sum("touches").alias("cells"))


def build_query_ratio(build_ns: Column, probe_ns: Column) -> Column:
    return build_ns / probe_ns


def job_seconds(df: DataFrame) -> float:
    """Wall time of a job whose rows go nowhere."""
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began
