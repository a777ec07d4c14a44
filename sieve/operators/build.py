"""From the key columns of a DataFrame to a table of filters: one shuffle of keys."""

from __future__ import annotations

import json
import time
from collections.abc import Iterator
from dataclasses import asdict, dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema

from sieve.functions import sizing
from sieve.functions.hashing import high_column, low_column, reduce_column, shift_left, shift_right, seeded
from sieve.functions.keys import key64, shard
from sieve.operators.kinds import Payload, build_payload
from sieve.plans.scratch import materialize
from sieve.schema import FILTERS, Spec, spec

#: Keys in a shard: 2**20 to 2**21 of them.
SHARD_LOG2 = 20


@dataclass(frozen=True)
class Filter:
    """A built filter: its table (one row a shard) and what a probe must know of it."""

    table: DataFrame
    spec: Spec
    shard_bits: int
    filter_id: str = "f"

    def size_bytes(self) -> int:
        """Payload as stored, from the sizes alone."""
        return int(self.table.agg(F.coalesce(F.sum("payload_bits"), F.lit(0))).first()[0]) // 8

    def keys(self) -> int:
        return int(self.table.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0])


def attempt_seed(seed: int, at: int, attempt: int) -> int:
    """A shard's seed for one try: the same in every run."""
    x = np.array([((at << 16) + attempt) & 0xFFFFFFFFFFFFFFFF], np.uint64)
    return int(seeded(seed, x).view(np.int64)[0])


def build_keys(keys: np.ndarray, s: Spec, seed: int, at: int = 0) -> tuple[Payload, int, int]:
    """(payload, seed, tries) for distinct keys; raises when every try fails."""
    for attempt in range(s.max_attempts):
        own = attempt_seed(seed, at, attempt)
        made = build_payload(keys, own, s, attempt)
        if made is not None:
            return made, own, attempt + 1
    raise RuntimeError(f"{s.kind}: {s.max_attempts} seeds failed for {len(keys)} keys")


def _row(keys: np.ndarray, at: int, s: Spec, seed: int, filter_id: str, shard_bits: int) -> dict:
    began = time.perf_counter_ns()
    keys = np.unique(keys)
    made, own, tries = build_keys(keys, s, seed, at)
    row = {f.name: None for f in FILTERS} | {
        "filter_id": filter_id, "kind": s.kind, "shard": at, "shard_bits": shard_bits, "n": len(keys), "arity": s.arity, "fp_bits": s.fp_bits, "seed": own, "attempts": tries,
        "seg_len": made.seg_len, "seg_count": made.seg_count, "array_len": made.array_len, "params": list(({"spec": json.dumps(asdict(s))} | made.extra).items()), "payload_bits": made.bits,
    }
    if made.cells is not None:
        name = {1: "cells8", 2: "cells16", 4: "cells32"}[made.cells.itemsize]
        row[name] = made.cells.view({1: np.int8, 2: np.int16, 4: np.int32}[made.cells.itemsize])
    if made.words is not None:
        row["words"] = made.words.view(np.int64)
    row["build_ns"] = time.perf_counter_ns() - began
    return row


def _record(row: dict) -> pa.Table:
    schema = to_arrow_schema(FILTERS)
    return pa.Table.from_arrays([pa.array([row[f.name]], f.type) for f in schema], schema=schema)


def key_table(df: DataFrame, keys: list[str], shard_bits: int, family: str = "xxhash64") -> DataFrame:
    """(shard, key64) of rows whose keys are all there."""
    return df.select(key64(*keys, family=family).alias("key64")).filter("key64 IS NOT NULL").select(shard(F.col("key64"), shard_bits).alias("shard"), "key64")


def _distinct_in_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Every key once a batch: of a key in a third of all rows, one row a batch travels."""
    for batch in batches:
        at, keys = np.asarray(batch.column(0)), np.asarray(batch.column(1))
        u, first = np.unique(keys, return_index=True)
        yield pa.RecordBatch.from_arrays([pa.array(at[first]), pa.array(u)], ["shard", "key64"])


def build(df: DataFrame, keys: str | list[str], kind: str = "fuse3", *, seed: int = 1, n_hint: int | None = None, shard_bits: int | None = None, filter_id: str = "f", engine: str = "arrow", predistinct: bool = True, keep: bool = True, **how) -> Filter:
    """Builds a filter of the given kind over the distinct keys of ``df``.

    n_hint: about how many keys; without it (and without shard_bits) the distinct keys are
    written as a scratch table first, so ``df`` is read once, and their number decides the
    number of shards. Sizes never use it: each shard counts its own.
    engine: "sql" builds bloom and blocked by aggregation alone.
    predistinct: collapse repeated keys in every map batch before the shuffle; after it
    they are collapsed in any case, before a shard's keys are gathered.
    keep: write the filter rows as a scratch table, so that probes do not rebuild.
    Null keys are dropped; repeated keys count once; no key gives no row.
    """
    keys = [keys] if isinstance(keys, str) else list(keys)
    s = spec(kind, **how)
    known = n_hint is not None or shard_bits is not None
    if not known:
        own = df.select(key64(*keys, family=s.family).alias("key64")).filter("key64 IS NOT NULL").distinct()
        own = materialize(own, "keys")
        n_hint = own.count()
    if shard_bits is None:
        shard_bits = sizing.shard_bits(n_hint, SHARD_LOG2)
    rows = key_table(df, keys, shard_bits, s.family) if known else own.select(shard(F.col("key64"), shard_bits).alias("shard"), "key64")
    if engine == "sql":
        table = build_by_aggregation(rows, s, seed, shard_bits, filter_id)
    else:
        if known:
            rows = rows.mapInArrow(_distinct_in_batches, "shard int, key64 bigint") if predistinct else rows
            rows = rows.repartition("shard").distinct()  # behind the one exchange, by streaming aggregation

        def shard_row(table: pa.Table) -> pa.Table:
            at = int(table.column(0)[0].as_py())
            return _record(_row(table.column(1).to_numpy(), at, s, seed, filter_id, shard_bits))

        table = rows.groupBy("shard").applyInArrow(shard_row, FILTERS)
    return Filter(materialize(table, f"filter-{kind}") if keep else table, s, shard_bits, filter_id)


def build_by_aggregation(rows: DataFrame, s: Spec, seed: int, shard_bits: int, filter_id: str) -> DataFrame:
    """Bloom and blocked by ``bit_or`` per word: partial in the map tasks, then final."""
    rows = rows.distinct()
    sizes = rows.groupBy("shard").agg(F.count("*").alias("n"))
    low64 = F.lit(64)
    if s.kind == "bloom":
        m = F.greatest(low64, F.ceil(F.ceil(F.col("n") * F.lit(s.bits_per_key)) / low64) * low64).cast("int")
        n_words = F.col("array_len") / 64
    elif s.kind == "blocked":
        m = F.greatest(F.lit(1), F.ceil(F.col("n") * F.lit(s.bits_per_key) / 256)).cast("int")
        n_words = F.col("array_len") * 4
    else:
        raise ValueError("only bloom and blocked are built by aggregation")
    own = F.xxhash64(F.lit(seed), shift_left(F.col("shard").cast("long"), 16))
    sizes = sizes.withColumn("array_len", m).withColumn("seed", own)
    keyed = rows.join(F.broadcast(sizes), "shard")  # one row a shard
    a = F.xxhash64("seed", "key64")
    one = F.lit(1).cast("long")
    if s.kind == "bloom":
        bit = F.explode(F.transform(F.sequence(F.lit(0), F.lit(s.hashes - 1)), lambda i: reduce_column(low_column(high_column(F.col("a")) + i * low_column(F.col("a"))), F.col("array_len"))))
        bits = keyed.withColumn("a", a).select("shard", bit.alias("bit")).select("shard", shift_right(F.col("bit"), 6).alias("word"), shift_left(one, F.col("bit").bitwiseAND(F.lit(63)).cast("int")).alias("mask"))
    else:
        from sieve.operators.kinds import LANES

        lo = low_column(F.col("a"))
        lane = lambda c: shift_right(low_column(lo.bitwiseAND(F.lit(0xFFFF)) * c + shift_left((shift_right(lo, 16) * c).bitwiseAND(F.lit(0xFFFF)), 16)), 27).cast("int")
        block = reduce_column(high_column(F.col("a")), F.col("array_len")) * 4
        parts = [F.struct((block + w).alias("word"), shift_left(one, lane(LANES[2 * w])).bitwiseOR(shift_left(one, lane(LANES[2 * w + 1]) + 32)).alias("mask")) for w in range(4)]
        bits = keyed.withColumn("a", a).select("shard", F.explode(F.array(*parts)).alias("x")).select("shard", "x.word", "x.mask")
    words = bits.groupBy("shard", "word").agg(F.bit_or("mask").alias("mask"))
    found = words.groupBy("shard").agg(F.map_from_entries(F.collect_list(F.struct("word", "mask"))).alias("held"))
    out = found.join(F.broadcast(sizes), "shard")
    filled = F.transform(F.sequence(F.lit(0).cast("long"), n_words.cast("long") - 1), lambda i: F.coalesce(F.try_element_at(F.col("held"), i), F.lit(0).cast("long")))
    values = {
        "filter_id": F.lit(filter_id), "kind": F.lit(s.kind), "shard": F.col("shard"), "shard_bits": F.lit(shard_bits), "n": F.col("n"), "arity": F.lit(s.arity), "fp_bits": F.lit(s.fp_bits), "seed": F.col("seed"), "attempts": F.lit(1), "seg_len": F.lit(0), "seg_count": F.lit(0),
        "array_len": F.col("array_len"), "params": F.create_map(F.lit("spec"), F.lit(json.dumps(asdict(s)))), "words": filled, "payload_bits": (n_words * 64).cast("long"),
    }
    return out.select(*[values.get(f.name, F.lit(None)).cast(f.dataType).alias(f.name) for f in FILTERS])
