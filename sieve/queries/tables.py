"""Reading the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def building_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders of the customers of one market segment."""
    customers = table(spark, sf_dir, "customer").filter("c_mktsegment = 'BUILDING'").select("c_custkey")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderpriority")
    return orders.join(customers, orders.o_custkey == customers.c_custkey, "left_semi")


def money(value, name: str):
    """A rounded sum: the engines add doubles in different orders."""
    return F.round(F.sum(value), 2).alias(name)
