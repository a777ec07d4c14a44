"""The experiment workloads: member sets, probe sets and measurement tables."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sieve.functions import measures, sizing, theory
from sieve.functions.keys import key64, shard
from sieve.operators import build
from sieve.plans.scratch import materialize
from sieve.schema import MEASUREMENTS, spec

#: Every kind and setting that is compared.
CATALOGUE: dict[str, tuple[str, dict]] = {
    "fuse3-8": ("fuse3", {}), "fuse3-16": ("fuse3", {"fp_bits": 16}), "fuse4-8": ("fuse4", {}), "fuse4-16": ("fuse4", {"fp_bits": 16}), "xor-8": ("xor", {}), "xor-16": ("xor", {"fp_bits": 16}), "xor-8b": ("xor", {"buffered": True}),
    "xorplus-8": ("xorplus", {}), "bloom-12": ("bloom", {"bits_per_key": 12.0}), "bloom-16": ("bloom", {"bits_per_key": 16.0}), "blocked-12": ("blocked", {}), "cuckoo-12": ("cuckoo", {"fp_bits": 12}), "cuckoo-16": ("cuckoo", {"fp_bits": 16}),
    "ribbon-8": ("ribbon", {"fp_bits": 8}), "ribbon-15": ("ribbon", {"fp_bits": 15}), "ribbon-8h": ("ribbon", {"fp_bits": 8, "homogeneous": True}), "ribbon-15h": ("ribbon", {"fp_bits": 15, "homogeneous": True}), "vqf-8": ("vqf", {"max_load": 0.93}),
}

#: Keys that a driver-side fixture may hold: one shard's worth.
MOST_KEYS = 1 << 21


def key_array(df: DataFrame, column: str | list[str]) -> tuple[np.ndarray, int]:
    """Distinct 64-bit keys of a bounded member set, for single-task timing."""
    columns = [column] if isinstance(column, str) else column
    rows = df.select(key64(*columns).alias("k")).filter("k IS NOT NULL").distinct().limit(MOST_KEYS + 1).toPandas()
    if len(rows) > MOST_KEYS:
        raise ValueError(f"more than {MOST_KEYS} keys: time a shard instead")
    return np.unique(rows["k"].to_numpy(np.int64)), len(rows)


def generated_keys(spark: SparkSession, n: int, start: int = 0, sequential: bool = False) -> DataFrame:
    """(k): n distinct keys, sequential or hashed."""
    ids = spark.range(start, start + n)
    return ids.select(F.col("id").alias("k") if sequential else F.xxhash64("id").alias("k"))


def mixed_probes(members: DataFrame, column: str, n: int, hit: float, seed: int = 7) -> DataFrame:
    """(k, is_member): about ``n`` probes of which a share ``hit`` are members, shuffled."""
    count = max(1, members.count())
    inside = members.select(F.col(column).cast("bigint").alias("k"), F.lit(True).alias("is_member"))
    copies = max(1, round(n * hit / count)) if hit else 0
    inside = inside.withColumn("c", F.explode(F.sequence(F.lit(1), F.lit(max(1, copies))))).drop("c") if copies else inside.limit(0)
    outside = members.sparkSession.range(10**12, 10**12 + round(n * (1 - hit))).select(F.col("id").alias("k"), F.lit(False).alias("is_member"))
    return inside.unionByName(outside).orderBy(F.rand(seed))


def over_shards(sets: dict[str, tuple[DataFrame, list[str]]], run: Callable[[str, int, int, int, int, np.ndarray], Iterator[dict]], schema: str, tasks: int = 1) -> DataFrame:
    """Rows that ``run(name, shard, shards, turn, turns, keys)`` yields for all shards of all key sets, by task.

    The distinct keys of a set are written as a scratch table, counted and cut into shards as
    ``build`` cuts them, so no set is too large and no key reaches the driver. A set of fewer
    shards than ``tasks`` gives each of them to several tasks, as turns 0 to ``turns - 1``.
    """
    parts, places = [], []
    for name, (df, columns) in sets.items():
        own = materialize(df.select(key64(*columns).alias("key64")).filter("key64 IS NOT NULL").distinct(), "keys")
        bits = sizing.shard_bits(own.count(), build.SHARD_LOG2)
        turns = max(1, tasks >> bits)
        first = F.lit(len(places)) + shard(F.col("key64"), bits) * turns
        parts.append(own.select(F.explode(F.sequence(first, first + (turns - 1))).alias("at"), "key64"))
        places += [(name, at, 1 << bits, turn, turns) for at in range(1 << bits) for turn in range(turns)]

    def task(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held = [(x["at"].iloc[0], x["key64"].to_numpy()) for x in batches if len(x)]
        if held:
            yield pd.DataFrame(run(*places[held[0][0]], np.sort(np.concatenate([k for _, k in held]))))

    dealt = reduce(DataFrame.unionByName, parts).repartitionById(len(places), F.col("at"))  # one shard and turn a task
    return dealt.mapInPandas(task, schema)


def _member_probes(keys: np.ndarray, n: int, hit: float, seed: int, at: int = 0, shards: int = 1) -> tuple[np.ndarray, np.ndarray]:
    """Probes that reach this shard: members, and other keys that begin with its bits."""
    rng = np.random.default_rng(seed)
    inside = rng.random(n) < hit
    probes = rng.integers(-(2**63), 2**63 - 1, n, dtype=np.int64)
    if bits := shards.bit_length() - 1:
        probes = ((probes.view(np.uint64) >> np.uint64(bits)) | np.uint64(at << (64 - bits))).view(np.int64)
    probes[inside] = rng.choice(keys, int(inside.sum()))
    return probes, inside


#: What one shard adds to a row of the measurement table. ``build_ns``, ``probe_ns``: of a whole run, one value a run.
TALLY = "filter string, param string, n long, n_probe long, bits long, wrong long, outside long, build_ns array<double>, probe_ns array<double>, attempts int"


def tally(keys: np.ndarray, names: list[str] | None = None, n_probe: int = 400_000, hit: float = 0.25, repeats: int = 3, seed: int = 1, most_probes: int = 10_000_000, at: int = 0, shards: int = 1) -> Iterator[dict]:
    """Counts and times of every kind over one shard, in one thread as in a shard's task.

    Errors below 2**-12 are measured on ``most_probes`` probes of all shards, in parts of ``n_probe``.
    """
    probes, inside = _member_probes(keys, n_probe, hit, seed, at, shards)
    for name in names or list(CATALOGUE):
        kind, how = CATALOGUE[name]
        s = spec(kind, **how)
        load = 0.93 if kind == "vqf" else 0.94
        rare = theory.expected_fpr(kind, s.fp_bits, s.bits_per_key, s.hashes, load) < 2**-12
        build_ns, most = measures.build_runs(keys, s, seed, repeats=repeats)
        f, bits = measures.loaded(keys, s, seed)
        probe_ns, hits = measures.probe_runs(f, probes, repeats)
        wrong, outside = hits - int(inside.sum()), int((~inside).sum())
        for part in range(1, -(-most_probes // (n_probe * shards)) if rare else 1):
            more, own = _member_probes(keys, n_probe, hit, seed + 7919 * part, at, shards)
            wrong, outside = wrong + int(f.contains(more).sum()) - int(own.sum()), outside + int((~own).sum())
        yield {"filter": name, "param": str(s.fp_bits), "n": len(keys), "n_probe": n_probe, "bits": int(bits), "wrong": wrong, "outside": outside, "build_ns": build_ns, "probe_ns": probe_ns, "attempts": most}


def _record(workload: str, hit: float, parts: list[dict]) -> dict:
    """The measurement of one kind over all its shards: sums of counts, and of times run by run."""
    total = lambda c: sum(p[c] for p in parts)
    n, n_probe = total("n"), total("n_probe")
    ns, spread = measures.median_of([sum(r) / max(1, n) for r in zip(*(p["build_ns"] for p in parts), strict=True)])
    probe_ns, _ = measures.median_of([sum(r) / n_probe for r in zip(*(p["probe_ns"] for p in parts), strict=True)])
    eps, per_key = total("wrong") / max(1, total("outside")), total("bits") / max(1, n)
    overhead = float((per_key / -np.log2(eps) - 1) * 100) if eps > 0 else None
    note = "one thread, numpy" if len(parts) == 1 else f"numpy, {len(parts)} shards, a thread each"
    return {"workload": workload, "filter": parts[0]["filter"], "param": parts[0]["param"], "n": n, "n_probe": n_probe, "hit_share": hit, "bits_per_key": per_key, "fpr": eps, "overhead": overhead, "build_ns_per_key": ns, "probe_ns_per_key": probe_ns, "build_spread": spread, "build_query_ratio": ns / probe_ns, "attempts": max(p["attempts"] for p in parts), "repeat": len(parts[0]["build_ns"]), "note": note}


def measure(keys: np.ndarray, names: list[str] | None = None, n_probe: int = 400_000, hit: float = 0.25, repeats: int = 3, workload: str = "families", seed: int = 1, most_probes: int = 10_000_000) -> list[dict]:
    """One record for every kind over the keys of one shard."""
    return [_record(workload, hit, [t]) for t in tally(keys, names, n_probe, hit, repeats, seed, most_probes)]


def _records(spark: SparkSession, tallies: DataFrame, hit: float) -> DataFrame:
    """The measurement table of ``workload, filter, param ...`` rows, one a shard."""

    def combined(rows: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame([_record(rows["workload"].iloc[0], hit, rows.to_dict("records"))])[MEASUREMENTS.fieldNames()]

    return tallies.groupBy("workload", "filter").applyInPandas(combined, MEASUREMENTS)


def measure_sets(spark: SparkSession, sets: dict[str, tuple[DataFrame, list[str]]], names: list[str] | None = None, n_probe: int = 400_000, hit: float = 0.25, repeats: int = 3, generated: list[int] = ()) -> DataFrame:
    """The measurement table of kinds over the whole key sets, and over ``generated`` numbers of random keys.

    Every shard is measured in a task of its own. Measured once: the counts and times are a scratch table.
    """
    schema = f"workload string, {TALLY}"

    def run(name: str, at: int, shards: int, turn: int, turns: int, keys: np.ndarray) -> Iterator[dict]:
        return ({"workload": name, **t} for t in tally(keys, names, n_probe, hit, repeats, at=at, shards=shards))

    def random_sets(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for n in (n for x in batches for n in x["n"]):
            keys = np.unique(np.random.default_rng(n).integers(-(2**63), 2**63 - 1, n, dtype=np.int64))
            yield pd.DataFrame({"workload": f"size {n}", **t} for t in tally(keys, names, n_probe, hit, repeats))

    out = over_shards(sets, run, schema)
    if generated:
        sizes = spark.createDataFrame(list(enumerate(generated)), "at int, n long").repartitionById(len(generated), "at")
        out = out.unionByName(sizes.select("n").mapInPandas(random_sets, schema))
    return _records(spark, materialize(out, "measured"), hit)


def measure_kinds(spark: SparkSession, members: DataFrame, column: str | list[str], names: list[str] | None = None) -> DataFrame:
    """The measurement table of all kinds over a member set."""
    columns = [column] if isinstance(column, str) else column
    return measure_sets(spark, {"families": (members, columns)}, names, n_probe=1_000_000)


def table_key_sets(spark: SparkSession, sf_dir: str) -> dict[str, tuple[DataFrame, list[str]]]:
    """Key sets of the given tables, from the least to the largest."""
    sets = (("nation", ["n_nationkey"]), ("supplier", ["s_suppkey"]), ("part", ["p_partkey"]), ("orders", ["o_orderkey"]), ("lineitem", ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"]))
    return {name: (spark.read.parquet(f"{sf_dir}/{name}.parquet"), columns) for name, columns in sets}


def size_sweep(spark: SparkSession, sets: dict[str, tuple[DataFrame, list[str]]], sizes: list[int], names: tuple[str, ...] = ("fuse3-8", "fuse4-8", "xor-8")) -> DataFrame:
    """Build time and bits per key as the number of keys grows: named key sets, then generated ones."""
    named = {f"size of {name}": s for name, s in sets.items()}
    swept = measure_sets(spark, named, list(names), n_probe=100_000, generated=sizes)
    return swept.withColumn("workload", F.regexp_replace("workload", r"^size \d+$", "size"))
