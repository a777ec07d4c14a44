"""SQL surfaces: a registered membership function and a table function."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from sieve.operators.build import Filter
from sieve.operators.contains import among, received, ship


#: Payload bytes of a filter that a function may carry.
MOST_BYTES = 512 << 20


def probe_udf(spark: SparkSession, f: Filter):
    """A vectorised function key64 -> boolean over a broadcast payload; null keys are false.

    The filter's size is checked; it travels as one Arrow stream and is made ready once a worker.
    """
    shared, s, bits = spark.sparkContext.broadcast(ship(f, MOST_BYTES)), f.spec, f.shard_bits

    @F.pandas_udf("boolean")
    def sieve_probe(key: pd.Series) -> pd.Series:
        there = key.notna().to_numpy()
        x = key.fillna(0).to_numpy(np.int64)
        at = ((x.view(np.uint64) >> np.uint64(1)) >> np.uint64(63 - bits)).astype(np.int64)
        return pd.Series(among(received(shared.value), s, x, at, there))

    return sieve_probe


def register_contains(spark: SparkSession, name: str, f: Filter) -> None:
    """Makes ``name(xxhash64(key))`` callable from SQL."""
    spark.udf.register(name, probe_udf(spark, f))


def register_occupancy(spark: SparkSession) -> None:
    """Table function ``sieve_occupancy(cells, seg_len)`` -> (segment, used, empty)."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="segment int, used int, empty int")
    class Occupancy:
        def eval(self, cells: list, seg_len: int):
            for at in range(0, len(cells), seg_len):
                used = sum(1 for c in cells[at : at + seg_len] if c)
                yield at // seg_len, used, seg_len - used

    spark.udtf.register("sieve_occupancy", Occupancy)

