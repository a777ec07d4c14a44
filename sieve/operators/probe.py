"""Probing filters: gates in front of joins, in generated code wherever possible.

The default gate is a join condition: probe rows left-semi the broadcast filter rows on
the shard, with the membership test as the rest of the condition. Nothing of the
filter reaches the output, and the probe side is not shuffled. Beyond the broadcast
limit the narrow probe rows are shuffled to the filter's shards instead.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from sieve.functions.keys import key64, shard
from sieve.operators.build import Filter
from sieve.operators.contains import Loaded, among, condition, native, received, ship
from sieve.plans.names import fresh
from sieve.schema import FILTERS

#: Payload bytes that are broadcast at most; larger filters are met by a shuffle.
BROADCAST_BYTES = 512 << 20
#: Tasks that share the probes of a shard where filters are met by a shuffle through Arrow.
SALTS = 8


def strategy(f: Filter, limit: int = BROADCAST_BYTES) -> str:
    """broadcast, shuffle or arrow, from the filter's kind and checked size."""
    if f.size_bytes() > limit:
        return "shuffle" if native(f.spec) else "cogroup"
    return "broadcast" if native(f.spec) else "arrow"


def _keyed(df: DataFrame, f: Filter, keys: list[str]) -> tuple[DataFrame, str, str]:
    """``df`` with two more columns, and their names: the key and its shard."""
    key, at = fresh(df.columns, "key", "shard")
    rows = df.withColumn(key, key64(*keys, family=f.spec.family))
    return rows.withColumn(at, shard(F.col(key), f.shard_bits)), key, at


def _payload(f: Filter) -> DataFrame:
    used = ["shard", "seed", "seg_len", "seg_count", "array_len", "words" if f.spec.kind in ("bloom", "blocked", "ribbon") else f.spec.cells]
    if f.spec.kind == "cuckoo":
        used[-1] = "cells16"
    if f.spec.kind == "xorplus":
        used.append("words")
    return f.table.select(*used)


def _joined(df: DataFrame, f: Filter, keys: list[str], how: str, plan: str) -> DataFrame:
    rows, key, at = _keyed(df, f, keys)
    side = _payload(f)
    side = (F.broadcast(side) if plan == "broadcast" else side.hint("shuffle_hash")).alias("f")
    test = (F.col(f"p.`{at}`") == F.col("f.shard")) & condition(F.col(f"p.`{key}`"), "f", f.spec)
    joined = rows.alias("p").join(side, test, how)
    return joined.drop(key, at) if how in ("left_semi", "left_anti") else joined


def contains_arrow(df: DataFrame, f: Filter, keys: list[str], out: str = "maybe_member") -> DataFrame:
    """Adds a flag by numpy gathers over a broadcast payload, whose size is checked."""
    shared, s = df.sparkSession.sparkContext.broadcast(ship(f, BROADCAST_BYTES)), f.spec
    rows, _, _ = _keyed(df, f, keys)
    names = df.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = received(shared.value)
        for batch in batches:
            key, at = batch.column(len(names)), np.asarray(batch.column(len(names) + 1).fill_null(-1))
            there = ~np.asarray(key.is_null())
            flag = among(held, s, np.asarray(key.fill_null(0)).astype(np.int64), at, there)
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(names)], pa.array(flag)], [*names, out])

    return rows.mapInArrow(run, T.StructType([*df.schema, T.StructField(out, T.BooleanType())]))


def contains_cogroup(df: DataFrame, f: Filter, keys: list[str], out: str = "maybe_member", salts: int = SALTS) -> DataFrame:
    """Adds a flag where probe rows meet their shard's filter row, sorted before them.

    Rows stream past one filter at a time; a shard's probes are dealt to ``salts`` tasks
    and no group of them is gathered.
    """
    s, names = f.spec, df.columns
    rows, key, at = _keyed(df, f, keys)
    salt, row, side = fresh(rows.columns, "salt", "row", "side")
    payload = T.StructType([x for x in FILTERS if x.name != "params"])
    spread = F.pmod(F.xxhash64(*[F.col(f"`{c}`") for c in (*keys, at)], F.spark_partition_id()), F.lit(salts)).cast("int")
    probes = rows.select(F.col(f"`{at}`"), spread.alias(salt), F.col(f"`{key}`"), F.struct(*[F.col(f"`{c}`") for c in names]).alias(row), F.lit(None).cast(payload).alias(side))
    filters = f.table.select(F.col("shard").alias(at), F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias(salt), F.lit(None).cast("long").alias(key), F.lit(None).cast(probes.schema[row].dataType).alias(row), F.struct(*payload.names).alias(side))
    both = filters.unionByName(probes).repartition(at, salt).sortWithinPartitions(at, salt, F.col(side).isNull())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: tuple[int, Loaded] | None = None
        for batch in batches:
            shards, values = batch.column(0).fill_null(-1), batch.column(2)
            there = ~np.asarray(values.is_null())
            at_, key_ = np.asarray(shards), np.asarray(values.fill_null(0)).astype(np.int64)
            is_filter, flag = ~np.asarray(batch.column(4).is_null()), np.zeros(len(batch), bool)
            cuts = [0, *np.flatnonzero(is_filter).tolist(), len(batch)]
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                if a < b and is_filter[a]:
                    held = (int(at_[a]), Loaded(batch.column(4)[a].as_py(), s))
                mine = a + np.flatnonzero(there[a:b] & (at_[a:b] == (held[0] if held else -2)))
                if len(mine):
                    flag[mine] = held[1].contains(key_[mine])
            own = np.flatnonzero(~is_filter)
            struct = batch.column(3).take(pa.array(own))
            yield pa.RecordBatch.from_arrays([*(struct.field(i) for i in range(len(names))), pa.array(flag[own])], [*names, out])

    return both.mapInArrow(run, T.StructType([*df.schema, T.StructField(out, T.BooleanType())]))


def contains(df: DataFrame, f: Filter, keys: str | list[str], out: str = "maybe_member", plan: str | None = None) -> DataFrame:
    """``df`` with a flag: true for every member, false for nearly all others; null keys false."""
    keys = [keys] if isinstance(keys, str) else list(keys)
    plan = plan or strategy(f)
    if plan == "arrow":
        return contains_arrow(df, f, keys, out)
    if plan == "cogroup":
        return contains_cogroup(df, f, keys, out)
    joined = _joined(df, f, keys, "left_outer", plan)
    return joined.select(*[F.col(f"p.`{c}`") for c in df.columns], F.col("f.shard").isNotNull().alias(out))


def _flagged(df: DataFrame, f: Filter, keys: list[str], plan: str, wanted: bool) -> DataFrame:
    [flag] = fresh(df.columns, "maybe")
    told = contains(df, f, keys, flag, plan)
    return told.filter(F.col(flag) if wanted else ~F.col(flag)).drop(flag)


def semi(df: DataFrame, f: Filter, keys: str | list[str], plan: str | None = None) -> DataFrame:
    """Rows that may be members; all members are among them."""
    keys = [keys] if isinstance(keys, str) else list(keys)
    plan = plan or strategy(f)
    if plan in ("arrow", "cogroup"):
        return _flagged(df, f, keys, plan, True)
    return _joined(df, f, keys, "left_semi", plan)


def anti(df: DataFrame, f: Filter, keys: str | list[str], plan: str | None = None) -> DataFrame:
    """Rows that are certainly not members (null keys among them)."""
    keys = [keys] if isinstance(keys, str) else list(keys)
    plan = plan or strategy(f)
    if plan in ("arrow", "cogroup"):
        return _flagged(df, f, keys, plan, False)
    return _joined(df, f, keys, "left_anti", plan)


def all_of(df: DataFrame, gates: list[tuple[Filter, str | list[str]]], pass_rates: list[float] | None = None) -> DataFrame:
    """Rows that pass every gate; with pass rates the most selective gate comes first."""
    order = sorted(range(len(gates)), key=lambda i: pass_rates[i]) if pass_rates else range(len(gates))
    for i in order:
        df = semi(df, *gates[i])
    return df


def any_of(df: DataFrame, gates: list[tuple[Filter, str | list[str]]]) -> DataFrame:
    """Rows that pass at least one gate."""
    names = df.columns
    flags = fresh(names, *(f"any{i}" for i in range(len(gates))))
    for flag, (f, keys) in zip(flags, gates, strict=True):
        df = contains(df, f, keys, flag)
    test: Column = F.lit(False)
    for flag in flags:
        test = test | F.col(flag)
    return df.filter(test).select(*[F.col(f"`{c}`") for c in names])


def in_list(df: DataFrame, column: str, values: list, kind: str = "fuse3", **how) -> DataFrame:
    """Rows whose column may be in a long literal list; verify with ``isin`` or a join."""
    from sieve.operators.build import build

    members = df.sparkSession.createDataFrame([(v,) for v in values], f"v {df.schema[column].dataType.simpleString()}")
    return semi(df, build(members, "v", kind, n_hint=max(1, len(values)), **how), column)
