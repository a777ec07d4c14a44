"""Joins behind every kind of filter; their SQL is the plain join."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from sieve.operators import joins, probe
from sieve.operators.build import build
from sieve.queries.tables import building_orders, money, table

QUERIES = {}
ORACLES = {}

_BUILDING = "SELECT o_orderkey, o_orderpriority FROM orders JOIN customer ON o_custkey = c_custkey WHERE c_mktsegment = 'BUILDING'"


def _query(sql: str):
    def keep(f):
        QUERIES[f.__name__], ORACLES[f.__name__] = f, sql
        return f

    return keep


def _revenue(spark: SparkSession, sf_dir: str, kind: str, **how) -> DataFrame:
    """Revenue by priority over the lines of one market segment's orders."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_extendedprice", "l_discount")
    orders = building_orders(spark, sf_dir)
    joined = joins.gated(lines, orders, ("l_orderkey", "o_orderkey"), "inner", kind, **how)
    return joined.groupBy("o_orderpriority").agg(F.count("*").alias("n_lines"), money(F.col("l_extendedprice") * (1 - F.col("l_discount")), "revenue"))


_REVENUE = f"SELECT o_orderpriority, count(*) AS n_lines, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM lineitem JOIN ({_BUILDING}) o ON l_orderkey = o_orderkey GROUP BY o_orderpriority"

#: Semi joins of lines with a quarter of the orders, one query for each kind and setting.
KINDS = {
    "xor8_semi": ("xor", {}), "xor16_semi": ("xor", {"fp_bits": 16}), "bloom12_semi": ("bloom", {"bits_per_key": 12.0}), "bloom16_semi": ("bloom", {"bits_per_key": 16.0}), "blocked_semi": ("blocked", {}),
    "cuckoo12_semi": ("cuckoo", {"fp_bits": 12}), "cuckoo16_semi": ("cuckoo", {"fp_bits": 16}), "ribbon8_std_semi": ("ribbon", {"fp_bits": 8}), "ribbon15_std_semi": ("ribbon", {"fp_bits": 15}),
    "ribbon8_homog_semi": ("ribbon", {"fp_bits": 8, "homogeneous": True}), "ribbon15_homog_semi": ("ribbon", {"fp_bits": 15, "homogeneous": True}), "vqf_semi": ("vqf", {"max_load": 0.93}), "xorplus_semi": ("xorplus", {}),
    "bloom_by_aggregation_semi": ("bloom", {"engine": "sql"}), "blocked_by_aggregation_semi": ("blocked", {"engine": "sql"}), "fuse5_semi": ("fuse5", {"size_factor": 1.35}),
    "fuse6_semi": ("fuse6", {"size_factor": 1.5}), "fuse7_semi": ("fuse7", {"size_factor": 1.65}), "fuse8_semi": ("fuse8", {"size_factor": 1.8}), "overlap_semi": ("fuse3", {"layout": "overlap", "size_factor": 1.4}),
    "plain_fuse_semi": ("fuse3", {"layout": "plain"}), "fuse3_32bit_semi": ("fuse3", {"fp_bits": 32}), "xor8_buffered_semi": ("xor", {"buffered": True}),
    "own_fingerprint_semi": ("fuse3", {"fingerprint": "sieve.functions.hashing:FOLDED"}), "cuckoo_pow2_semi": ("cuckoo", {"power_of_two": True, "max_load": 0.96}), "murmur_family_semi": ("fuse3", {"family": "murmur64"}), "md5_family_semi": ("fuse3", {"family": "md5"}),
}
_QUARTER = "SELECT l_returnflag, count(*) AS n_lines, count(DISTINCT l_orderkey) AS n_orders FROM lineitem WHERE l_orderkey IN (SELECT o_orderkey FROM orders WHERE o_orderkey % 4 = 0) GROUP BY l_returnflag"


def quarter(spark: SparkSession, sf_dir: str, kind: str, **how) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_returnflag")
    members = table(spark, sf_dir, "orders").select("o_orderkey").filter("o_orderkey % 4 = 0")
    kept = joins.semi(lines, members, ("l_orderkey", "o_orderkey"), kind, **how)
    return kept.groupBy("l_returnflag").agg(F.count("*").alias("n_lines"), F.count_distinct("l_orderkey").alias("n_orders"))


for _name, (_kind, _how) in KINDS.items():
    QUERIES[_name] = lambda spark, sf_dir, k=_kind, h=_how: quarter(spark, sf_dir, k, **h)
    ORACLES[_name] = _QUARTER


@_query(_REVENUE)
def fuse3_semi_join(spark, sf_dir):
    return _revenue(spark, sf_dir, "fuse3")


@_query(_REVENUE)
def fuse4_semi_join(spark, sf_dir):
    return _revenue(spark, sf_dir, "fuse4")


@_query("SELECT l_linestatus, count(*) AS n_lines, round(sum(l_quantity), 2) AS quantity FROM lineitem WHERE l_partkey IN (SELECT p_partkey FROM part WHERE p_size <= 10) GROUP BY l_linestatus")
def fuse3_16_semi_join(spark, sf_dir):
    lines = table(spark, sf_dir, "lineitem").select("l_partkey", "l_linestatus", "l_quantity")
    parts = table(spark, sf_dir, "part").filter("p_size <= 10").select("p_partkey")
    kept = joins.semi(lines, parts, ("l_partkey", "p_partkey"), "fuse3", fp_bits=16)
    return kept.groupBy("l_linestatus").agg(F.count("*").alias("n_lines"), money(F.col("l_quantity"), "quantity"))


@_query("SELECT l_linestatus, count(*) AS n_lines, round(sum(l_tax), 2) AS tax FROM lineitem WHERE l_suppkey IN (SELECT s_suppkey FROM supplier WHERE s_acctbal < 1000) GROUP BY l_linestatus")
def fuse4_16_semi_join(spark, sf_dir):
    lines = table(spark, sf_dir, "lineitem").select("l_suppkey", "l_linestatus", "l_tax")
    suppliers = table(spark, sf_dir, "supplier").filter("s_acctbal < 1000").select("s_suppkey")
    kept = joins.semi(lines, suppliers, ("l_suppkey", "s_suppkey"), "fuse4", fp_bits=16)
    return kept.groupBy("l_linestatus").agg(F.count("*").alias("n_lines"), money(F.col("l_tax"), "tax"))


@_query("SELECT o_orderpriority, count(*) AS n_orders FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem) GROUP BY o_orderpriority")
def anti_join_gate(spark, sf_dir):
    """Orders without lines: what the gate rejects needs no lookup."""
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority")
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey")
    return joins.anti(orders, lines, ("o_orderkey", "l_orderkey"), predistinct=True).groupBy("o_orderpriority").agg(F.count("*").alias("n_orders"))


@_query(f"SELECT l_returnflag, count(*) AS n_lines FROM lineitem WHERE l_orderkey IN (SELECT o_orderkey FROM ({_BUILDING})) AND l_partkey IN (SELECT p_partkey FROM part WHERE p_size <= 10) AND l_suppkey IN (SELECT s_suppkey FROM supplier WHERE s_nationkey < 10) GROUP BY l_returnflag")
def star_three_gates(spark, sf_dir):
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_returnflag")
    orders, parts, suppliers = building_orders(spark, sf_dir), table(spark, sf_dir, "part").filter("p_size <= 10"), table(spark, sf_dir, "supplier").filter("s_nationkey < 10")
    dims = [(suppliers, ("l_suppkey", "s_suppkey")), (parts, ("l_partkey", "p_partkey")), (orders, ("l_orderkey", "o_orderkey"))]
    return joins.star(lines, dims, pass_rates=[0.4, 0.2, 0.2]).groupBy("l_returnflag").agg(F.count("*").alias("n_lines"))


@_query("SELECT l_returnflag, count(*) AS n_lines FROM lineitem WHERE l_partkey IN (SELECT p_partkey FROM part WHERE p_size = 1) OR l_suppkey IN (SELECT s_suppkey FROM supplier WHERE s_nationkey = 3) GROUP BY l_returnflag")
def any_of_gates(spark, sf_dir):
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_returnflag")
    parts, suppliers = table(spark, sf_dir, "part").filter("p_size = 1"), table(spark, sf_dir, "supplier").filter("s_nationkey = 3")
    maybe = probe.any_of(lines, [(build(parts, "p_partkey"), "l_partkey"), (build(suppliers, "s_suppkey"), "l_suppkey")])
    p, s = parts.select(F.col("p_partkey").alias("l_partkey"), F.lit(True).alias("p")), suppliers.select(F.col("s_suppkey").alias("l_suppkey"), F.lit(True).alias("s"))
    exact = maybe.join(p, "l_partkey", "left").join(s, "l_suppkey", "left").filter("p OR s")
    return exact.groupBy("l_returnflag").agg(F.count("*").alias("n_lines"))


@_query("SELECT l_orderkey % 10 AS digit, count(*) AS n_lines FROM lineitem WHERE l_orderkey % 97 = 0 AND l_orderkey < 97 * 500 GROUP BY 1")
def in_list_gate(spark, sf_dir):
    values = list(range(0, 97 * 500, 97))
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey")
    exact = probe.in_list(lines, "l_orderkey", values).filter(F.col("l_orderkey").isin(values))
    return exact.groupBy((F.col("l_orderkey") % 10).alias("digit")).agg(F.count("*").alias("n_lines"))


@_query("SELECT j AS share, count(*) AS n_members FROM lineitem JOIN (SELECT unnest([1, 2, 3, 4]) AS j) ON l_orderkey % 4 < j AND l_orderkey IN (SELECT o_orderkey FROM orders) GROUP BY j UNION ALL SELECT 0, 0")
def hit_share_sweep(spark, sf_dir):
    """Exact members among the probes at 0, 25, 50, 75 and 100 % hits, behind a gate each."""
    lines, orders = table(spark, sf_dir, "lineitem").select("l_orderkey"), table(spark, sf_dir, "orders").select("o_orderkey")
    out = None
    for j in range(5):
        members = orders.filter(F.col("o_orderkey") % 4 < j)
        kept = joins.semi(lines, members, ("l_orderkey", "o_orderkey"), n_hint=1 << 20)
        one = kept.agg(F.lit(j).alias("share"), F.count("*").alias("n_members"))
        out = one if out is None else out.unionByName(one)
    return out


@_query("SELECT is_member, count(*) AS n FROM (SELECT l_orderkey % 4 = 0 AND l_orderkey IN (SELECT o_orderkey FROM orders) AS is_member FROM lineitem) GROUP BY is_member")
def mixed_query_25(spark, sf_dir):
    """A quarter of the shuffled probes are members."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey").orderBy(F.rand(7))
    members = table(spark, sf_dir, "orders").select("o_orderkey").filter("o_orderkey % 4 = 0")
    flagged = probe.contains(lines, build(members, "o_orderkey"), "l_orderkey")
    truth = members.select(F.col("o_orderkey").alias("l_orderkey"), F.lit(True).alias("t"))
    exact = flagged.join(truth, "l_orderkey", "left").select((F.col("maybe_member") & F.coalesce("t", F.lit(False))).alias("is_member"))
    return exact.groupBy("is_member").agg(F.count("*").alias("n"))


_SPLIT = r"string_split_regex(lower(text), '[^a-z]+')"


@_query(f"WITH v AS (SELECT DISTINCT unnest({_SPLIT}) AS w FROM benchmark), d AS (SELECT lang, unnest({_SPLIT}) AS w FROM documents) SELECT lang, count(*) AS n_words, count(DISTINCT w) AS n_distinct FROM d WHERE w <> '' AND w IN (SELECT w FROM v WHERE w <> '') GROUP BY lang")
def string_key_words(spark, sf_dir):
    """Words of documents that the benchmark's vocabulary has."""
    words = lambda name, *cols: table(spark, sf_dir, name).select(*cols, F.explode(F.split(F.lower("text"), "[^a-z]+")).alias("w")).filter("w <> ''")
    kept = joins.semi(words("documents", "lang"), words("benchmark"), "w", predistinct=True)
    return kept.groupBy("lang").agg(F.count("*").alias("n_words"), F.count_distinct("w").alias("n_distinct"))


@_query(r"WITH h AS (SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host FROM pages) SELECT host, count(*) AS n_pages FROM h WHERE host IN (SELECT host FROM h WHERE page_id % 5 = 0) GROUP BY host")
def url_host_gate(spark, sf_dir):
    hosts = table(spark, sf_dir, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host"))
    return joins.semi(hosts, hosts.filter("page_id % 5 = 0").select("host"), "host").groupBy("host").agg(F.count("*").alias("n_pages"))


@_query("SELECT l_returnflag, count(*) AS n_lines FROM lineitem WHERE (l_orderkey, l_partkey, l_suppkey, l_linenumber) IN (SELECT (l_orderkey, l_partkey, l_suppkey, l_linenumber) FROM lineitem WHERE l_quantity < 10) GROUP BY l_returnflag")
def composite_key_gate(spark, sf_dir):
    keys = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"]
    lines = table(spark, sf_dir, "lineitem").select(*keys, "l_returnflag", "l_quantity")
    members = lines.filter("l_quantity < 10").select(*keys)
    return joins.semi(lines, members, [(k, k) for k in keys]).groupBy("l_returnflag").agg(F.count("*").alias("n_lines"))


_GRAMS = "SELECT source, id, unnest(list_transform(range(1, len(w) - 6), lambda i: array_to_string(w[i:i + 7], ' '))) AS g FROM (SELECT {source} AS source, {id} AS id, list_filter(string_split_regex(lower({text}), '[^a-z]+'), lambda x: x <> '') AS w FROM {t})"


#: Words of a run.
RUN = 8


def _words(text: str) -> Column:
    return F.filter(F.split(F.lower(text), "[^a-z]+"), lambda x: x != "")


def _places(w: Column, made) -> Column:
    """``made(place)`` for every place of ``w`` where a run begins."""
    return F.when(F.size(w) >= RUN, F.transform(F.sequence(F.lit(1), F.size(w) - (RUN - 1)), made))


def _run_hashes(df: DataFrame, key: str, text: str = "text") -> DataFrame:
    """(id, text_hash, place, h): runs by the hash of their words' hashes; no run is written out as a string."""
    w = F.col("w")
    hashed = df.select(F.col(key).alias("id"), F.xxhash64(text).alias("text_hash"), F.transform(_words(text), lambda x: F.xxhash64(x)).alias("w"))
    return hashed.select("id", "text_hash", F.explode(_places(w, lambda i: F.struct(i.alias("place"), F.xxhash64(F.slice(w, i, RUN)).alias("h")))).alias("x")).select("id", "text_hash", "x.place", "x.h")


def _grams(df: DataFrame, key: str, text: str = "text", places: str | None = None) -> DataFrame:
    """(id, g): runs of words as strings, of all places or of those in a column."""
    w = F.col("w")
    made = lambda i: F.array_join(F.slice(w, i, RUN), " ")
    chosen = F.transform(F.col(places), made) if places else _places(w, made)
    rows = df.select(F.col(key).alias("id"), _words(text).alias("w"), *([places] if places else []))
    return rows.select("id", F.explode(chosen).alias("g"))


def _contaminated(df: DataFrame, f, members: DataFrame, key: str, text: str) -> DataFrame:
    """(id, n_hits, n_grams): the gate takes hashes; only runs that pass are written out and compared."""
    passed = probe.semi(_run_hashes(df, key, text), f, "h").groupBy("id", "text_hash").agg(F.collect_set("place").alias("places"))
    few = df.select(F.col(key).alias("id"), text, F.xxhash64(text).alias("text_hash")).join(passed, ["id", "text_hash"])
    return joins.exact_semi(_grams(few, "id", text, "places"), members, "g").groupBy("id").agg(F.count("*").alias("n_hits"), F.count_distinct("g").alias("n_grams"))


_BENCH = _GRAMS.format(source="'benchmark'", id="item_id", text="text", t="benchmark")


@_query(f"SELECT id AS doc_id, count(*) AS n_hits, count(DISTINCT g) AS n_grams FROM ({_GRAMS.format(source="'documents'", id='doc_id', text='text', t='documents')}) WHERE g IN (SELECT g FROM ({_BENCH})) GROUP BY id")
def contamination_shingles(spark, sf_dir):
    """Documents with eight-word runs of the benchmark: the shipped filter probes every run."""
    items = table(spark, sf_dir, "benchmark")
    f = build(_run_hashes(items, "item_id").select("h"), "h", fp_bits=16)
    found = _contaminated(table(spark, sf_dir, "documents"), f, _grams(items, "item_id").select("g"), "doc_id", "text")
    return found.withColumnRenamed("id", "doc_id")


_OTHERS = " UNION ALL ".join(_GRAMS.format(source=f"'{t}'", id=i, text=x, t=t) for t, i, x in (("pages", "page_id", "html"), ("conversations", "conv_id", "text")))


@_query(f"SELECT source, id, count(*) AS n_hits, count(DISTINCT g) AS n_grams FROM ({_OTHERS}) WHERE g IN (SELECT g FROM ({_BENCH})) GROUP BY source, id")
def contamination_of_other_sources(spark, sf_dir):
    """The same filter, built once, probed by the runs of pages and of conversations."""
    items = table(spark, sf_dir, "benchmark")
    f, out = build(_run_hashes(items, "item_id").select("h"), "h", fp_bits=16), None
    for name, key, text in (("pages", "page_id", "html"), ("conversations", "conv_id", "text")):
        found = _contaminated(table(spark, sf_dir, name), f, _grams(items, "item_id").select("g"), key, text)
        found = found.select(F.lit(name).alias("source"), "id", "n_hits", "n_grams")
        out = found if out is None else out.unionByName(found)
    return out


@_query("SELECT count(*) AS n_lines FROM (SELECT nullif(l_orderkey, 0) AS k FROM lineitem) WHERE k IN (SELECT nullif(o_orderkey, 0) FROM orders WHERE o_orderkey % 2 = 0 AND nullif(o_orderkey, 0) IS NOT NULL)")
def null_key_policy(spark, sf_dir):
    """A null key is never a member and never passes."""
    lines = table(spark, sf_dir, "lineitem").select(F.expr("nullif(l_orderkey, 0)").alias("k"))
    orders = table(spark, sf_dir, "orders").filter("o_orderkey % 2 = 0").select(F.expr("nullif(o_orderkey, 0)").alias("k"))
    return joins.semi(lines, orders, "k").agg(F.count("*").alias("n_lines"))


@_query("SELECT CAST(count(DISTINCT l_orderkey) AS BIGINT) AS n_keys FROM lineitem")
def duplicates_policy(spark, sf_dir):
    """Repeated keys count once in the filter."""
    f = build(table(spark, sf_dir, "lineitem"), "l_orderkey", predistinct=True, shard_bits=2)
    return f.table.agg(F.sum("n").alias("n_keys"))
