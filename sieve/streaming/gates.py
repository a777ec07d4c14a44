"""Static filters over moving probes, and a filter that grows key by key."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from sieve.functions.hashing import high, low, reduce32, words
from sieve.functions.keys import key64
from sieve.operators import probe
from sieve.operators.build import Filter
from sieve.plans.names import fresh
from sieve.plans.scratch import materialize, scratch_root


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table as a stream of its file; naive timestamps become instants."""
    batch = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    single = spark.readStream.schema(batch.schema).option("pathGlobFilter", "*.parquet").option("maxFilesPerTrigger", 1)
    stream = single.parquet(f"{sf_dir}/{name}.parquet*")
    for f in batch.schema:
        if f.dataType.typeName() == "timestamp_ntz":
            stream = stream.withColumn(f.name, F.col(f.name).cast("timestamp"))
    return stream


def gate_stream(stream: DataFrame, f: Filter, keys: str | list[str]) -> DataFrame:
    """The stream's rows that may be members: a stream-static semi join in generated code."""
    return probe.semi(stream, f, keys, plan="broadcast")


def run(stream: DataFrame, mode: str = "append", batch=None) -> DataFrame:
    """Runs a stream over what is there and returns its result table."""
    spark = stream.sparkSession
    at = f"{scratch_root(spark)}/stream-{uuid.uuid4().hex[:10]}"
    if batch is not None:
        query = stream.writeStream.outputMode(mode).foreachBatch(batch).option("checkpointLocation", f"{at}-log").trigger(availableNow=True).start()
        query.awaitTermination()
        return spark.range(0)
    if mode == "append":
        query = stream.writeStream.outputMode(mode).format("parquet").option("path", at).option("checkpointLocation", f"{at}-log").trigger(availableNow=True).start()
        query.awaitTermination()
        return spark.read.schema(stream.schema).parquet(at)

    def replace(df: DataFrame, number: int) -> None:
        df.write.mode("overwrite").parquet(f"{at}/{number}")
        done.append(number)

    done: list[int] = []
    query = stream.writeStream.outputMode(mode).foreachBatch(replace).option("checkpointLocation", f"{at}-log").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{at}/{max(done)}") if done else spark.createDataFrame([], stream.schema)


def first_seen(stream: DataFrame, key: str, buckets: int = 64, bits: int = 1 << 16, hashes: int = 8) -> DataFrame:
    """The first row of a key in each batch, with ``sure``: true where a growing Bloom filter has not seen the key.

    Keys are dealt to ``buckets`` states by hash. A state holds the words of its filter and
    nothing else, so its size is fixed. Where some bit is missing the key is certainly new;
    other rows may be new and need an exact look (``distinct_keys``). Null keys are left out.
    """
    names = stream.columns
    own, bucket = fresh([*names, "sure"], "key", "bucket")
    keyed = stream.withColumn(own, key64(key)).filter(F.col(own).isNotNull()).withColumn(bucket, F.pmod(own, F.lit(buckets)).cast("int"))

    def step(_, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        filled = np.frombuffer(state.get[0], np.uint64).copy() if state.exists else np.zeros(bits // 64, np.uint64)
        for x in frames:
            x = x.sort_values([own, *names], ignore_index=True).drop_duplicates(own)
            a, _ = words(x[own].to_numpy(np.int64), 1)
            at = np.stack([reduce32((high(a) + np.uint64(i) * low(a)) & np.uint64(0xFFFFFFFF), bits) for i in range(hashes)], 1)
            there = ((filled[at >> 6] >> (at & 63).astype(np.uint64)) & np.uint64(1)) == 1
            np.bitwise_or.at(filled, at >> 6, np.uint64(1) << (at & 63).astype(np.uint64))
            yield x[names].assign(sure=~there.all(axis=1))
        state.update((filled.tobytes(),))

    schema = T.StructType([*stream.schema, T.StructField("sure", T.BooleanType())])
    return keyed.groupBy(bucket).applyInPandasWithState(step, schema, "words binary", "append", "NoTimeout")


def distinct_keys(stream: DataFrame, key: str, **how) -> tuple[DataFrame, DataFrame]:
    """(all keys of a stream, each once; rows a batch: sure ones, and others before and after the exact look).

    The filter spares sure keys the lookup: only the others, repeated keys and false
    positives alike, are looked for in the table of what was seen, batch by batch.
    """
    spark, told = stream.sparkSession, first_seen(stream.select(key), key, **how)
    kind = stream.select(key).schema
    seen = [spark.createDataFrame([], kind)]
    counts: list[tuple[int, int, int, int]] = []

    def take(df: DataFrame, number: int) -> None:
        rows = materialize(df, "first-seen")
        sure = rows.filter("sure").select(key).distinct()
        maybe = rows.filter("NOT sure").select(key).distinct()
        looked = materialize(maybe.join(sure, key, "left_anti").join(seen[0], key, "left_anti"), "first-looked")
        counts.append((number, sure.count(), maybe.count(), looked.count()))
        seen[0] = materialize(seen[0].unionByName(sure).unionByName(looked), "first-keys")

    run(told, batch=take)
    return seen[0], spark.createDataFrame(counts, "batch bigint, sure bigint, looked_up bigint, found_new bigint")


def refresh_by_batch(stream: DataFrame, f: Filter, keys: str, known: DataFrame) -> Filter:
    """Rebuilds, batch by batch, the shards that a stream's new keys fall in.

    ``known``: the keys the filter has; each batch's keys are added to a table beside it.
    """
    from sieve.sources.catalog import refresh

    held = {"filter": f, "keys": known.select(keys)}

    def take(df: DataFrame, number: int) -> None:
        new = materialize(df.select(keys).join(held["keys"], keys, "left_anti").distinct(), "refresh-new")
        held["keys"] = materialize(held["keys"].unionByName(new), "refresh-keys")
        held["filter"] = refresh(held["filter"], held["keys"], new, keys)

    run(stream, batch=take)
    return held["filter"]
