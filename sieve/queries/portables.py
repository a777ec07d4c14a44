"""Structures over md5 that SQL recomputes cell by cell."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from sieve.functions import portable, sizing
from sieve.operators import relational
from sieve.queries.tables import table

QUERIES = {}
ORACLES = {}


def _query(sql: str):
    def keep(f):
        QUERIES[f.__name__], ORACLES[f.__name__] = f, sql
        return f

    return keep


def _h(tag: str, x: str, first: int = 1) -> str:
    return f"CAST('0x' || substr(md5('{tag}:' || CAST({x} AS VARCHAR)), {first}, 15) AS BIGINT)"


_H1, _H2 = "(h >> 28)", "(h & 268435455)"
_BLOOM = "(((" + _H1 + " + i * " + _H2 + ") & 4294967295) * m) >> 32"


def _bloom_sql(where: str = "TRUE") -> str:
    return f"""k AS (SELECT p_partkey AS key, {_h('k', 'p_partkey')} AS h FROM part WHERE {where}),
    s AS (SELECT CAST(ceil(count(*) * 12 / 32.0) AS BIGINT) * 32 AS m FROM k),
    b AS (SELECT {_BLOOM} AS bit FROM k, s, (SELECT unnest(range(8)) AS i)),
    w AS (SELECT bit >> 5 AS word, bit_or(1::BIGINT << CAST(bit & 31 AS INTEGER)) AS mask FROM b GROUP BY 1)"""


@_query(f"WITH {_bloom_sql()} SELECT word, mask FROM w")
def bloom_bits_portable(spark, sf_dir):
    """All words of a Bloom filter, by ``bit_or``."""
    part = table(spark, sf_dir, "part")
    places = part.select(F.explode(portable.bloom_places(F.col("p_partkey"), portable.bloom_size(part.count()))).alias("bit"))
    return portable.bit_words(places)


def _probe_bits(keys: DataFrame, words: DataFrame, hashes: int) -> DataFrame:
    """Keys all of whose bits are set: rows (key, bit) against words."""
    bits = keys.select("key", (F.col("bit") / 32).cast("bigint").alias("word"), F.call_function("shiftleft", F.lit(1).cast("bigint"), F.col("bit").bitwiseAND(F.lit(31)).cast("int")).alias("one"))
    hit = bits.join(words, "word", "left").groupBy("key").agg(F.count_if(F.col("mask").bitwiseAND(F.col("one")) != 0).alias("hits"))
    return hit.filter(F.col("hits") == hashes).select("key")


@_query(f"""WITH {_bloom_sql('p_partkey % 4 = 0')},
q AS (SELECT DISTINCT l_partkey AS key, {_h('k', 'l_partkey')} AS h FROM lineitem),
p AS (SELECT key, {_BLOOM} AS bit FROM q, s, (SELECT unnest(range(8)) AS i)),
hit AS (SELECT key FROM p LEFT JOIN w ON word = bit >> 5 GROUP BY key HAVING count(*) FILTER ((mask & (1::BIGINT << CAST(bit & 31 AS INTEGER))) <> 0) = 8)
SELECT count(*) AS positives, count(*) FILTER (key % 4 <> 0) AS false_positives, count(*) FILTER (key % 4 = 0) AS members FROM hit""")
def bloom_probe_portable(spark, sf_dir):
    """The exact number of false positives of a Bloom filter."""
    part = table(spark, sf_dir, "part").filter("p_partkey % 4 = 0")
    m = portable.bloom_size(part.count())
    words = portable.bit_words(part.select(F.explode(portable.bloom_places(F.col("p_partkey"), m)).alias("bit")))
    keys = table(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("key")).distinct()
    hit = _probe_bits(keys.select("key", F.explode(portable.bloom_places(F.col("key"), m)).alias("bit")), words, 8)
    return hit.agg(F.count("*").alias("positives"), F.count_if(F.expr("key % 4 <> 0")).alias("false_positives"), F.count_if(F.expr("key % 4 = 0")).alias("members"))


def _blocked_sql(where: str = "TRUE") -> str:
    return f"""k AS (SELECT p_partkey AS key, {_h('k', 'p_partkey')} AS h, {_h('k', 'p_partkey', 16)} AS g FROM part WHERE {where}),
    s AS (SELECT CAST(ceil(count(*) * 12 / 256.0) AS BIGINT) AS m FROM k),
    b AS (SELECT (({_H1} * m) >> 32) * 256 + i * 32 + ((g >> (i * 5)) & 31) AS bit FROM k, s, (SELECT unnest(range(8)) AS i)),
    w AS (SELECT bit >> 5 AS word, bit_or(1::BIGINT << CAST(bit & 31 AS INTEGER)) AS mask FROM b GROUP BY 1)"""


def _blocks(n: int) -> int:
    return max(1, -(-n * 12 // 256))


@_query(f"WITH {_blocked_sql()} SELECT word, mask FROM w")
def blocked_bits_portable(spark, sf_dir):
    part = table(spark, sf_dir, "part")
    return portable.bit_words(part.select(F.explode(portable.blocked_places(F.col("p_partkey"), _blocks(part.count()))).alias("bit")))


@_query(f"""WITH {_blocked_sql('p_partkey % 4 = 0')},
q AS (SELECT DISTINCT l_partkey AS key, {_h('k', 'l_partkey')} AS h, {_h('k', 'l_partkey', 16)} AS g FROM lineitem),
p AS (SELECT key, (({_H1} * m) >> 32) * 256 + i * 32 + ((g >> (i * 5)) & 31) AS bit FROM q, s, (SELECT unnest(range(8)) AS i)),
hit AS (SELECT key FROM p LEFT JOIN w ON word = bit >> 5 GROUP BY key HAVING count(*) FILTER ((mask & (1::BIGINT << CAST(bit & 31 AS INTEGER))) <> 0) = 8)
SELECT count(*) AS positives, count(*) FILTER (key % 4 <> 0) AS false_positives, count(*) FILTER (key % 4 = 0) AS members FROM hit""")
def blocked_probe_portable(spark, sf_dir):
    part = table(spark, sf_dir, "part").filter("p_partkey % 4 = 0")
    blocks = _blocks(part.count())
    words = portable.bit_words(part.select(F.explode(portable.blocked_places(F.col("p_partkey"), blocks)).alias("bit")))
    keys = table(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("key")).distinct()
    hit = _probe_bits(keys.select("key", F.explode(portable.blocked_places(F.col("key"), blocks)).alias("bit")), words, 8)
    return hit.agg(F.count("*").alias("positives"), F.count_if(F.expr("key % 4 <> 0")).alias("false_positives"), F.count_if(F.expr("key % 4 = 0")).alias("members"))


_ROUND = {3: ("3.33", "2.25", "0.875 + 0.25 * greatest(1.0, ln(1e6) / ln(n))"), 4: ("2.91", "-0.5", "0.77 + 0.305 * greatest(1.0, ln(6e5) / ln(n))")}


def _fuse_sql(t: str, key: str, arity: int) -> str:
    """k: (key, locs) of a table's keys with portable hashes."""
    base, shift, cells = _ROUND[arity]
    locs = ", ".join(f"(start + {j}) * seg + ((g >> CAST({j} * lg AS INTEGER)) & (seg - 1))" for j in range(arity))
    return f"""z AS (SELECT CAST(greatest(2, count(DISTINCT {key})) AS DOUBLE) AS n FROM {t}),
    y AS (SELECT CAST(floor(ln(n) / ln({base}) + ({shift})) AS BIGINT) AS lg, CAST(floor(n * ({cells})) AS BIGINT) AS cells FROM z),
    x AS (SELECT lg, CAST(1 AS BIGINT) << CAST(lg AS INTEGER) AS seg, greatest({arity}, CAST(ceil(cells / pow(2, lg)) AS BIGINT)) AS segs FROM y),
    k0 AS (SELECT DISTINCT {key} AS key FROM {t}),
    k1 AS (SELECT key, seg, lg, (({_h('k', 'key')} >> 28) * (segs - {arity - 1})) >> 32 AS start, {_h('k', 'key', 16)} AS g FROM k0, x),
    k AS (SELECT key, [{locs}] AS locs FROM k1)"""


def _xor_sql(t: str, key: str) -> str:
    return f"""x AS (SELECT CAST(ceil((floor(1.23 * count(DISTINCT {key})) + 32) / 3) AS BIGINT) AS b FROM {t}),
    k0 AS (SELECT DISTINCT {key} AS key FROM {t}),
    k AS (SELECT key, [(({_h('k', 'key')} >> 28) * b) >> 32, ((({_h('k', 'key', 16)} >> 28) * b) >> 32) + b, ((({_h('x', 'key')} & 4294967295) * b) >> 32) + 2 * b] AS locs FROM k0, x)"""


def _peel_sql(keys: str) -> str:
    """Peeling as a recursive query: every round reads the live keys of the round before."""
    return f"""WITH RECURSIVE {keys},
    peel(layer, key, locs, own) AS (
      SELECT 0, key, locs, CAST(NULL AS BIGINT) FROM k
      UNION ALL
      SELECT p.layer + 1, p.key, p.locs, o.own
      FROM peel p LEFT JOIN (
        SELECT key, min(loc) AS own FROM (
          SELECT loc, min(key) AS key FROM (SELECT key, unnest(locs) AS loc FROM peel WHERE own IS NULL) GROUP BY loc HAVING count(*) = 1) GROUP BY key) o ON p.key = o.key
      WHERE p.own IS NULL AND p.layer < 5000
        AND EXISTS (SELECT 1 FROM (SELECT unnest(locs) AS loc FROM peel WHERE own IS NULL) GROUP BY loc HAVING count(*) = 1))
    SELECT key, layer, own FROM peel WHERE own IS NOT NULL"""


@_query(f"WITH {_fuse_sql('part', 'p_partkey', 3)} SELECT key, locs[1] AS loc0, locs[2] AS loc1, locs[3] AS loc2 FROM k")
def fuse3_locations_portable(spark, sf_dir):
    keyed, _, _ = portable.fuse_keyed(table(spark, sf_dir, "part"), "p_partkey", 3)
    return keyed.select("key", *[F.element_at("locs", j + 1).alias(f"loc{j}") for j in range(3)])


@_query(f"WITH {_fuse_sql('part', 'p_partkey', 3)} SELECT loc, count(*) AS cnt, bit_xor(key) AS mask FROM (SELECT key, unnest(locs) AS loc FROM k) GROUP BY loc")
def fuse3_cell_counts_portable(spark, sf_dir):
    """Every cell as a counter and the xor of its keys."""
    keyed, _, _ = portable.fuse_keyed(table(spark, sf_dir, "part"), "p_partkey", 3)
    return relational.cell_counts(keyed)


def _layers(keyed: DataFrame) -> DataFrame:
    return relational.layers(keyed)[0].select("key", "layer", "own")


@_query(_peel_sql(_fuse_sql("supplier", "s_suppkey", 3)))
def fuse3_peel_layers_portable(spark, sf_dir):
    return _layers(portable.fuse_keyed(table(spark, sf_dir, "supplier"), "s_suppkey", 3)[0])


@_query(_peel_sql(_fuse_sql("supplier", "s_suppkey", 4)))
def fuse4_peel_layers_portable(spark, sf_dir):
    return _layers(portable.fuse_keyed(table(spark, sf_dir, "supplier"), "s_suppkey", 4)[0])


@_query(_peel_sql(_xor_sql("supplier", "s_suppkey")))
def xor_peel_layers_portable(spark, sf_dir):
    return _layers(portable.xor_keyed(table(spark, sf_dir, "supplier"), "s_suppkey")[0])


@_query(_peel_sql(_fuse_sql("part", "p_partkey", 3)))
def fuse3_peel_part_portable(spark, sf_dir):
    """The in-task builder's rounds over portable cells, owner by owner."""
    import numpy as np

    from sieve.operators.peel import peel_layers

    keyed, length, count = portable.fuse_keyed(table(spark, sf_dir, "part"), "p_partkey", 3)

    def run(rows):
        x = rows.sort_values("key", ignore_index=True)
        loc = np.array(x["locs"].to_list(), np.int64).reshape(-1, 3)
        import pandas as pd

        found = [(x["key"].to_numpy()[r], np.full(len(r), k + 1), own) for k, (r, own) in enumerate(peel_layers(loc, length * count))]
        return pd.DataFrame({c: np.concatenate([f[i] for f in found]) if found else np.zeros(0, np.int64) for i, c in enumerate(("key", "layer", "own"))})

    return keyed.withColumn("shard", F.lit(0)).groupBy("shard").applyInPandas(lambda rows: run(rows), "key bigint, layer int, own bigint")


@_query(f"""WITH m AS (SELECT * FROM part WHERE p_partkey % 2 = 0), k AS (SELECT p_partkey AS key, {_h('k', 'p_partkey')} AS h, p_partkey % 4 AS side FROM m),
s AS (SELECT CAST(ceil(count(*) * 12 / 32.0) AS BIGINT) * 32 AS m FROM k),
b AS (SELECT {_BLOOM} AS bit FROM k, s, (SELECT unnest(range(8)) AS i)) SELECT bit >> 5 AS word, bit_or(1::BIGINT << CAST(bit & 31 AS INTEGER)) AS mask FROM b GROUP BY 1""")
def bloom_union_equals_or(spark, sf_dir):
    """The union of two Bloom filters of one size is the or of their words."""
    part = table(spark, sf_dir, "part").filter("p_partkey % 2 = 0")
    m = portable.bloom_size(part.count())
    half = lambda r: portable.bit_words(part.filter(f"p_partkey % 4 = {r}").select(F.explode(portable.bloom_places(F.col("p_partkey"), m)).alias("bit")))
    return half(0).unionByName(half(2)).groupBy("word").agg(F.bit_or("mask").alias("mask"))


def _starts(spark: SparkSession, sf_dir: str) -> DataFrame:
    keyed, length, _ = portable.fuse_keyed(table(spark, sf_dir, "part"), "p_partkey", 3)
    return keyed.select("key", (F.element_at("locs", 1) / length).cast("bigint").alias("start_seg"), F.element_at("locs", 1).alias("loc"))


_STARTS = f"{_fuse_sql('part', 'p_partkey', 3)}, st AS (SELECT key, locs[1] // seg AS start_seg, locs[1] AS loc FROM k, x)"


@_query(f"WITH {_STARTS} SELECT key, start_seg, row_number() OVER (PARTITION BY start_seg ORDER BY key) AS place, dense_rank() OVER (ORDER BY start_seg) AS segment_rank FROM st")
def window_rank_keys(spark, sf_dir):
    """A key's place in its starting segment: the counting sort's second half."""
    rows = _starts(spark, sf_dir)
    ranks = rows.select("start_seg").distinct().withColumn("segment_rank", F.dense_rank().over(Window.orderBy("start_seg")).cast("bigint"))  # hundreds of segments
    place = F.row_number().over(Window.partitionBy("start_seg").orderBy("key")).cast("bigint").alias("place")
    return rows.select("key", "start_seg", place).join(ranks, "start_seg").select("key", "start_seg", "place", "segment_rank")


@_query(f"WITH {_STARTS}, c AS (SELECT start_seg, count(*) AS n FROM st GROUP BY start_seg) SELECT start_seg, n, CAST(coalesce(sum(n) OVER (ORDER BY start_seg ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS offs FROM c")
def running_prefix_sums(spark, sf_dir):
    """Where each segment's keys begin in the partially sorted buffer."""
    counts = _starts(spark, sf_dir).groupBy("start_seg").agg(F.count("*").alias("n"))
    w = Window.orderBy("start_seg").rowsBetween(Window.unboundedPreceding, -1)
    return counts.select("start_seg", "n", F.coalesce(F.sum("n").over(w), F.lit(0)).alias("offs"))


@_query(f"""WITH {_STARTS}, d AS (SELECT start_seg // 8 AS zone, abs(loc - lag(loc) OVER (PARTITION BY start_seg // 8 ORDER BY key)) AS by_key, abs(loc - lag(loc) OVER (PARTITION BY start_seg // 8 ORDER BY start_seg, key)) AS by_segment FROM st)
SELECT zone, round(avg(by_key), 4) AS by_key, round(avg(by_segment), 4) AS by_segment FROM d GROUP BY zone""")
def lag_locality(spark, sf_dir):
    """Mean distance between touches in key order and in segment order, by zones of eight segments."""
    rows = _starts(spark, sf_dir).withColumn("zone", (F.col("start_seg") / 8).cast("bigint"))
    step = lambda *order: F.abs(F.col("loc") - F.lag("loc").over(Window.partitionBy("zone").orderBy(*order)))
    d = rows.select("zone", step("key").alias("a"), step("start_seg", "key").alias("b"))
    return d.groupBy("zone").agg(F.round(F.avg("a"), 4).alias("by_key"), F.round(F.avg("b"), 4).alias("by_segment"))


@_query(_peel_sql(_fuse_sql("supplier", "s_suppkey", 3)).replace("SELECT key, layer, own FROM peel WHERE own IS NOT NULL", "SELECT CAST(own // seg AS INTEGER) AS segment, CAST(count(*) AS INTEGER) AS used, CAST(any_value(seg) - count(*) AS INTEGER) AS empty FROM peel, x WHERE own IS NOT NULL GROUP BY 1"))
def udtf_occupancy(spark, sf_dir):
    """Owned cells by segment, by a table function over the array of owners."""
    from sieve.functions.udfs import register_occupancy

    register_occupancy(spark)
    keyed, length, count = portable.fuse_keyed(table(spark, sf_dir, "supplier"), "s_suppkey", 3)
    owners = relational.layers(keyed)[0].agg(F.collect_set("own").alias("own"))  # one array of a filter's cells
    cells = owners.select(F.transform(F.sequence(F.lit(0), F.lit(length * count - 1)), lambda i: F.array_contains("own", i.cast("bigint")).cast("int")).alias("cells"))
    cells.createOrReplaceTempView("sieve_cells")
    return spark.sql(f"SELECT o.* FROM sieve_cells, LATERAL sieve_occupancy(cells, {length}) o WHERE used > 0")


__all__ = ["ORACLES", "QUERIES", "sizing"]
