"""Peeling and assignment as DataFrame rounds: a check of the in-task builder, never the default.

Every round is one aggregation by cell and one by key; rounds are as many as peeling has
layers. Rounds are written as scratch tables.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sieve.plans.scratch import materialize


def cell_counts(keyed: DataFrame) -> DataFrame:
    """(loc, cnt, mask) from rows (key, locs): number and xor of the keys of each cell."""
    return keyed.select("key", F.explode("locs").alias("loc")).groupBy("loc").agg(F.count("*").alias("cnt"), F.bit_xor("key").alias("mask"))


def layers(keyed: DataFrame, most: int = 10_000) -> tuple[DataFrame, int]:
    """(key, layer, own, locs) of all peeled keys, and the keys that are left."""
    live = materialize(keyed.select("key", "locs"), "peel-live")
    done: DataFrame | None = None
    for layer in range(1, most):
        single = cell_counts(live).filter("cnt = 1").groupBy(F.col("mask").alias("key")).agg(F.min("loc").alias("own"))
        found = materialize(live.join(single, "key").select("key", F.lit(layer).alias("layer"), "own", "locs"), "peel-layer")
        if not found.limit(1).count():
            break
        done = found if done is None else done.unionByName(found)
        live = materialize(live.join(found.select("key"), "key", "left_anti"), "peel-live")
        if layer % 16 == 0:
            done = materialize(done, "peel-done")
    left = live.count()
    if done is None:
        done = keyed.select("key", F.lit(0).alias("layer"), F.lit(0).cast("bigint").alias("own"), "locs").limit(0)
    return done, left


def assign(done: DataFrame, fingerprint: Column) -> DataFrame:
    """(loc, value) of the owned cells: layers backwards, each from the values so far."""
    rows = materialize(done.withColumn("fp", fingerprint), "assign-rows")
    last = rows.agg(F.max("layer")).first()[0] or 0
    cells = materialize(rows.limit(0).select(F.col("own").alias("loc"), F.col("fp").alias("value")), "assign-cells")
    for layer in range(last, 0, -1):
        mine = rows.filter(F.col("layer") == layer)
        read = mine.select("key", F.explode("locs").alias("loc")).join(cells, "loc").groupBy("key").agg(F.bit_xor("value").alias("x"))
        new = mine.join(read, "key", "left").select(F.col("own").alias("loc"), F.col("fp").bitwiseXOR(F.coalesce("x", F.lit(0).cast("bigint"))).alias("value"))
        cells = materialize(cells.unionByName(new), "assign-cells")
    return cells
