"""Queries over the given tables with their SQL, by theme."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from sieve.queries import formulas, gates, invariants, portables, relational, streams

MODULES = (gates, formulas, portables, invariants, relational, streams)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {k: v for m in MODULES for k, v in m.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {k: v for m in MODULES for k, v in m.ORACLES.items()}
