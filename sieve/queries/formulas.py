"""Sizes, curves and costs: the same arithmetic in both engines."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from sieve.functions import sizing, theory
from sieve.functions.measures import mean_degree, segment_ratio, touches
from sieve.operators.build import build
from sieve.queries.tables import table

QUERIES = {}
ORACLES = {}

#: The natural member sets: the key columns of the tables.
KEYS = {"region": ["r_regionkey"], "nation": ["n_nationkey"], "supplier": ["s_suppkey"], "customer": ["c_custkey"], "part": ["p_partkey"], "orders": ["o_orderkey"], "lineitem": ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"]}

_COUNTS = "WITH c AS (" + " UNION ALL ".join(f"SELECT '{t}' AS source, CAST(count(*) AS BIGINT) AS n FROM {t}" for t in ("region", "nation", "supplier", "customer", "part", "orders", "lineitem")) + ")"
_KEY_COUNTS = "WITH c AS (SELECT * FROM (" + " UNION ALL ".join(f"SELECT '{t}' AS source, CAST(count(*) AS BIGINT) AS n FROM (SELECT DISTINCT {', '.join(ks)} FROM {t} WHERE {' AND '.join(k + ' IS NOT NULL' for k in ks)})" for t, ks in KEYS.items()) + ") WHERE n > 0)"
_G = "CAST(greatest(n, 2) AS DOUBLE)"
_CELLS3 = f"CAST(floor({_G} * (0.875 + 0.25 * greatest(1.0, ln(1e6) / ln({_G})))) AS BIGINT)"
_CELLS4 = f"CAST(floor({_G} * (0.77 + 0.305 * greatest(1.0, ln(6e5) / ln({_G})))) AS BIGINT)"
_SEG3 = f"CAST(pow(2, greatest(0, floor(ln({_G}) / ln(3.33) + 2.25))) AS BIGINT)"
_SEG4 = f"CAST(pow(2, greatest(0, floor(ln({_G}) / ln(2.91) - 0.5))) AS BIGINT)"


def _query(sql: str):
    def keep(f):
        QUERIES[f.__name__], ORACLES[f.__name__] = f, sql
        return f

    return keep


def key_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(source, n): the natural member sets, from five keys up."""
    names = ("region", "nation", "supplier", "customer", "part", "orders", "lineitem")
    return reduce(DataFrame.unionByName, [table(spark, sf_dir, t).agg(F.lit(t).alias("source"), F.count("*").alias("n")) for t in names])


def key_set_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(source, n): the distinct keys of every table that has any; null keys are none."""
    counted = [table(spark, sf_dir, t).agg(F.lit(t).alias("source"), F.count_distinct(*ks).alias("n")) for t, ks in KEYS.items()]
    return reduce(DataFrame.unionByName, counted).filter("n > 0")


def _sizes(df: DataFrame) -> DataFrame:
    out = None
    for arity in (3, 4):
        cells, length, count = sizing.fuse_columns(F.col("n"), arity)
        one = df.select("source", "n", F.lit(f"fuse{arity}").alias("kind"), length.alias("seg_len"), count.alias("seg_count"))
        out = one if out is None else out.unionByName(one)
    xor = df.select("source", "n", F.lit("xor").alias("kind"), sizing.xor_column(F.col("n")).alias("seg_len"), F.lit(3).cast("bigint").alias("seg_count"))
    return out.unionByName(xor)


_SIZED = f"""s AS (
  SELECT source, n, 'fuse3' AS kind, {_SEG3} AS seg_len, greatest(3, CAST(ceil({_CELLS3} / CAST({_SEG3} AS DOUBLE)) AS BIGINT)) AS seg_count FROM c
  UNION ALL SELECT source, n, 'fuse4', {_SEG4}, greatest(4, CAST(ceil({_CELLS4} / CAST({_SEG4} AS DOUBLE)) AS BIGINT)) FROM c
  UNION ALL SELECT source, n, 'xor', CAST(ceil((floor(1.23 * n) + 32) / 3) AS BIGINT), 3 FROM c)"""
_SIZES = f"{_COUNTS}, {_SIZED}"


@_query(f"{_SIZES} SELECT source, kind, n, seg_len, seg_count, CAST(floor(8000 * (seg_len * seg_count) / n) AS BIGINT) AS millibits FROM s")
def bits_per_key_fuse_xor(spark, sf_dir):
    """Bits per key of padded 8-bit arrays as the member set grows."""
    sized = _sizes(key_counts(spark, sf_dir))
    return sized.select("source", "kind", "n", "seg_len", "seg_count", F.floor(8000 * F.col("seg_len") * F.col("seg_count") / F.col("n")).cast("bigint").alias("millibits"))


_CURVES = f"""{_KEY_COUNTS}, {_SIZED}, k AS (SELECT CAST(k AS BIGINT) AS k FROM range(8, 17) t(k)),
z AS (SELECT source, n, k, CAST(max(seg_len) FILTER (kind = 'xor') AS BIGINT) AS len, CAST(max(seg_len * seg_count) FILTER (kind = 'fuse3') AS BIGINT) AS cells3, CAST(max(seg_len * seg_count) FILTER (kind = 'fuse4') AS BIGINT) AS cells4 FROM s, k GROUP BY source, n, k),
t AS (SELECT source, n, k, 'bound' AS curve, CAST(k AS DOUBLE) AS bits, n * k AS set_bits FROM z
UNION ALL SELECT source, n, k, 'bloom', k * (1 / ln(2)), greatest(64, CAST(ceil(ceil(n * k * (1 / ln(2))) / 64) AS BIGINT) * 64) FROM z
UNION ALL SELECT source, n, k, 'xor', k * CAST(1.23 AS DOUBLE), 3 * len * k FROM z
UNION ALL SELECT source, n, k, 'xorplus', k * CAST(1.0824 AS DOUBLE) + CAST(0.5125 AS DOUBLE), CAST(ceil(len * (264 * k + 125) / 100) AS BIGINT) FROM z
UNION ALL SELECT source, n, k, 'fuse3', k * CAST(1.125 AS DOUBLE), cells3 * k FROM z
UNION ALL SELECT source, n, k, 'fuse4', k * CAST(1.075 AS DOUBLE), cells4 * k FROM z
UNION ALL SELECT source, n, k, 'cuckoo', (k + 3) / CAST(0.955 AS DOUBLE), greatest(2, CAST(ceil(n * 1000 / 3820) AS BIGINT)) * 4 * (k + 3) FROM z)"""


@_query(f"{_CURVES} SELECT source, n, k, curve, round(bits, 6) AS bits, CAST(set_bits AS BIGINT) AS set_bits FROM t")
def theory_curves(spark, sf_dir):
    """Bits per key of all structures by error, and the bits that the tables' key sets take."""
    return theory.curves_of(key_set_sizes(spark, sf_dir))


@_query(f"{_SIZES} SELECT source, kind, n, CAST(seg_len * seg_count AS BIGINT) AS cells, CAST(seg_count AS BIGINT) AS ratio FROM s WHERE kind <> 'xor'")
def segment_ratio_by_size(spark, sf_dir):
    """Array over segment length: hundreds for large sets."""
    sized = _sizes(key_counts(spark, sf_dir)).filter("kind <> 'xor'").withColumn("cells", F.col("seg_len") * F.col("seg_count"))
    return sized.select("source", "kind", "n", "cells", segment_ratio(F.col("cells"), F.col("seg_len")).cast("bigint").alias("ratio"))


@_query(f"""WITH k AS (SELECT min(l_shipdate) AS first FROM lineitem WHERE l_orderkey IS NOT NULL AND l_partkey IS NOT NULL AND l_suppkey IS NOT NULL AND l_linenumber IS NOT NULL GROUP BY l_orderkey, l_partkey, l_suppkey, l_linenumber),
d AS (SELECT CAST(first AS DATE) AS day, count(*) AS n FROM k WHERE first IS NOT NULL GROUP BY 1), c AS (SELECT day, CAST(sum(n) OVER (ORDER BY day) AS BIGINT) AS n FROM d), s AS (
  SELECT day, n, {_SEG3} * greatest(3, CAST(ceil({_CELLS3} / CAST({_SEG3} AS DOUBLE)) AS BIGINT)) AS fuse3, {_SEG4} * greatest(4, CAST(ceil({_CELLS4} / CAST({_SEG4} AS DOUBLE)) AS BIGINT)) AS fuse4, 3 * CAST(ceil((floor(1.23 * n) + 32) / 3) AS BIGINT) AS xor_cells FROM c)
SELECT CAST(day AS VARCHAR) AS day, n, CAST(fuse3 AS BIGINT) AS fuse3_cells, CAST(fuse4 AS BIGINT) AS fuse4_cells, CAST(xor_cells AS BIGINT) AS xor_cells, fuse3 < xor_cells AS fuse3_smaller, fuse4 < xor_cells AS fuse4_smaller FROM s""")
def crossover(spark, sf_dir):
    """Where padded fuse arrays get smaller than xor's: the set of all lines shipped so far, day by day."""
    lines = table(spark, sf_dir, "lineitem").dropna(subset=KEYS["lineitem"]).groupBy(*KEYS["lineitem"]).agg(F.min("l_shipdate").alias("first"))
    days = lines.filter("first IS NOT NULL").groupBy(F.to_date("first").alias("day")).agg(F.count("*").alias("n"))
    df = days.select("day", F.sum("n").over(Window.orderBy("day")).alias("n"))  # one row a day
    cells = {a: (lambda x: x[1] * x[2])(sizing.fuse_columns(F.col("n"), a)) for a in (3, 4)}
    out = df.select(F.col("day").cast("string").alias("day"), "n", cells[3].alias("fuse3_cells"), cells[4].alias("fuse4_cells"), (3 * sizing.xor_column(F.col("n"))).alias("xor_cells"))
    return out.select("*", (F.col("fuse3_cells") < F.col("xor_cells")).alias("fuse3_smaller"), (F.col("fuse4_cells") < F.col("xor_cells")).alias("fuse4_smaller"))


@_query(f"""{_KEY_COUNTS}, {_SIZED}, b AS (SELECT source, n, kind, CAST(floor(seg_len * seg_count * 57800 / CAST(1000 * n AS DOUBLE)) AS BIGINT) AS bits FROM s)
SELECT source, n, CAST(max(bits) FILTER (kind = 'fuse3') AS BIGINT) AS fuse3_bits, CAST(max(bits) FILTER (kind = 'fuse4') AS BIGINT) AS fuse4_bits FROM b GROUP BY source, n""")
def cuckoo_equal_eps(spark, sf_dir):
    """Bits per key at which fuse filters over the tables' key sets match a 64-bit cuckoo filter."""
    cells = {a: (lambda x: x[1] * x[2])(sizing.fuse_columns(F.col("n"), a)) for a in (3, 4)}
    return key_set_sizes(spark, sf_dir).select("source", "n", *[theory.match_cuckoo_cells(c, F.col("n")).alias(f"fuse{a}_bits") for a, c in cells.items()])


@_query("SELECT kind, touches, count(*) AS probes, CAST(touches * count(*) AS BIGINT) AS cells FROM orders, (VALUES ('fuse3', 3), ('fuse4', 4), ('xor', 3), ('cuckoo', 2), ('blocked', 1), ('bloom', CAST(ceil(log2(100)) AS INTEGER))) t(kind, touches) WHERE o_orderkey IS NOT NULL GROUP BY kind, touches")
def accesses_per_probe(spark, sf_dir):
    """Touches of the positive probes of all orders; the Bloom filter has one false positive in a hundred."""
    orders, out = table(spark, sf_dir, "orders").select("o_orderkey"), None
    for kind in ("fuse3", "fuse4", "xor", "cuckoo", "blocked", "bloom"):
        how = {"bits_per_key": sizing.bloom_bits_for(0.01)} if kind == "bloom" else {}
        one = touches(orders, build(orders, "o_orderkey", kind, **how), "o_orderkey").select(F.lit(kind).alias("kind"), "*")
        out = one if out is None else out.unionByName(one)
    return out


@_query(f"{_SIZES} SELECT source, kind, round((CASE kind WHEN 'fuse4' THEN 4 ELSE 3 END) * n / CAST(seg_len * seg_count AS DOUBLE), 6) AS degree FROM s")
def mean_degree_by_kind(spark, sf_dir):
    """Keys per cell."""
    arity = F.when(F.col("kind") == "fuse4", 4).otherwise(3)
    return _sizes(key_counts(spark, sf_dir)).select("source", "kind", F.round(mean_degree(arity, F.col("n"), F.col("seg_len") * F.col("seg_count")), 6).alias("degree"))


@_query("SELECT source, round(n / pow(2, 64) * 1e18, 6) AS atto FROM (" + _COUNTS + " SELECT * FROM c)")
def collision_terms(spark, sf_dir):
    """What hashing to 64 bits adds to the false-positive probability, in 1e-18."""
    return key_counts(spark, sf_dir).select("source", F.round(theory.collision_term(F.col("n")) * 1e18, 6).alias("atto"))


@_query(f"{_SIZES} SELECT source, CAST(n AS BIGINT) AS n, CAST(seg_count AS INTEGER) AS seg_count, CAST(seg_len * seg_count * 8 AS BIGINT) AS payload_bits FROM s WHERE kind = 'fuse3' AND source IN ('region', 'nation', 'supplier')")
def small_sets(spark, sf_dir):
    """Built filters over tiny sets have the least number of segments."""
    out = None
    for name, key in (("region", "r_regionkey"), ("nation", "n_nationkey"), ("supplier", "s_suppkey")):
        one = build(table(spark, sf_dir, name), key, shard_bits=0).table.select(F.lit(name).alias("source"), "n", "seg_count", "payload_bits")
        out = one if out is None else out.unionByName(one)
    return out


@_query(f"{_CURVES} SELECT source, k, arg_min(curve, (set_bits, curve)) AS smallest FROM t WHERE curve <> 'bound' GROUP BY source, k")
def smallest_curve(spark, sf_dir):
    """The most economical structure for each table's key set at every error from 2**-8 to 2**-16; the first by name of equals."""
    sized = theory.curves_of(key_set_sizes(spark, sf_dir)).filter("curve <> 'bound'")
    return sized.groupBy("source", "k").agg(F.min_by("curve", F.struct("set_bits", "curve")).alias("smallest"))
