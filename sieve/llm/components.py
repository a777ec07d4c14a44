"""Connected components by alternating large-star and small-star steps.

Every step replaces a node's edges by edges to the least node it sees: an aggregation
(least neighbour, added up in the map tasks first) and a join back on the node. The
nodes with more than one edge in HUBS, of which there are at most 2 * HUBS, are joined
by broadcast, so that no task gets the edges of a hub. Steps are written as scratch
tables until the edge set is stable.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sieve.plans.scratch import materialize

#: A hub has more than one in so many edges, and more edges than a task minds.
HUBS, LEAST_HUB = 2000, 256


def _with_least(edges: DataFrame, of: DataFrame, number: int) -> DataFrame:
    """``edges`` (a, b) with ``m``, the least b of the node a in ``of``; ``number`` edges in all."""
    found = materialize(of.groupBy("a").agg(F.min("b").alias("m"), F.count("*").alias("n")), "components-least")
    hub = F.col("n") > max(LEAST_HUB, number // HUBS)
    hubs = F.broadcast(found.filter(hub).drop("n"))
    rest = edges.join(hubs.select("a"), "a", "left_anti").join(found.filter(~hub).drop("n"), "a")
    return edges.join(hubs, "a").unionByName(rest)


def _large(edges: DataFrame, number: int) -> DataFrame:
    both = edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    told = _with_least(both.filter("b > a"), both, number)
    return told.select(F.col("b").alias("a"), F.least("a", "m").alias("b"))


def _small(edges: DataFrame, number: int) -> DataFrame:
    down = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    told = _with_least(down, down, number)
    return told.select(F.when(F.col("b") == F.col("m"), F.col("a")).otherwise(F.col("b")).alias("a"), F.col("m").alias("b"))


def _state(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(20,0)"))).first())


def components(edges: DataFrame) -> DataFrame:
    """(a, root) for every node that some edge (a, b) touches; root is the least node.

    Self-edges and repeated edges are allowed; nulls are not. Node types need an order.
    """
    e = materialize(edges.filter("a <> b").select("a", "b").distinct(), "components")
    seen = _state(e)
    while seen[0]:
        e = materialize(_large(e, seen[0]).distinct(), "components")
        e = materialize(_small(e, seen[0]).filter("a <> b").distinct(), "components")
        now = _state(e)
        if now == seen:
            break
        seen = now
    # Stable: every edge leads from a node to its root.
    return e.select("a", F.col("b").alias("root")).unionByName(e.select(F.col("b").alias("a"), F.col("b").alias("root")).distinct())
