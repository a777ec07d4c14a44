"""Operators around the gates: joins, aggregations, windows, sets and functions."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.window import Window

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


def _gated_lines(spark, sf_dir):
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_returnflag", "l_linestatus", "l_quantity")
    return joins.gated(lines, building_orders(spark, sf_dir), ("l_orderkey", "o_orderkey"))


_GATED = f"(SELECT * FROM lineitem JOIN ({_BUILDING}) o ON l_orderkey = o_orderkey)"


@_query("SELECT event_type, count(*) AS n FROM events e JOIN (SELECT o_custkey, date_trunc('day', o_orderdate) AS d FROM orders GROUP BY ALL) o ON e.user_id = o_custkey AND CAST(strftime(e.ts, '2000-%m-%d') AS DATE) >= CAST(strftime(d, '2000-%m-%d') AS DATE) AND CAST(strftime(e.ts, '2000-%m-%d') AS DATE) < CAST(strftime(d, '2000-%m-%d') AS DATE) + 7 GROUP BY event_type")
def range_join_after_gate(spark, sf_dir):
    """Events within a week of a customer's order day, years apart put on one calendar."""
    day = lambda c: F.to_date(F.date_format(c, "2000-MM-dd"))
    events = table(spark, sf_dir, "events").select("user_id", "event_type", day("ts").alias("at"))
    orders = table(spark, sf_dir, "orders").select("o_custkey", F.date_trunc("day", "o_orderdate").alias("d")).distinct().select("o_custkey", day("d").alias("a"))
    periods = orders.withColumn("b", F.date_add("a", 7))
    kept = probe.semi(events, build(orders, "o_custkey", predistinct=True), "user_id")
    return joins.range_join(kept, periods, ("user_id", "o_custkey"), "at", "a", "b").groupBy("event_type").agg(F.count("*").alias("n"))


@_query("SELECT event_id, (SELECT max_by(x.value, (x.ts, x.value)) FROM events x WHERE x.event_type = 'purchase' AND x.user_id = e.user_id AND x.ts <= e.ts) AS last_value FROM events e WHERE event_type = 'click'")
def asof_after_gate(spark, sf_dir):
    """Each click with its user's last purchase value so far."""
    events = table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", "value")
    clicks, buys = events.filter("event_type = 'click'").select("event_id", "ts", "user_id"), events.filter("event_type = 'purchase'")
    flagged = probe.contains(clicks, build(buys, "user_id", predistinct=True), "user_id")
    sure = flagged.filter("NOT maybe_member").select("event_id", F.lit(None).cast("double").alias("last_value"))
    found = joins.asof_join(flagged.filter("maybe_member").drop("maybe_member"), buys, ("user_id", "user_id"), ("ts", "ts"), "value", "last_value")
    return found.select("event_id", "last_value").unionByName(sure)


@_query("SELECT p_size, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey AND l_extendedprice > 20 * p_retailprice WHERE p_size <= 5 GROUP BY p_size")
def theta_residual(spark, sf_dir):
    """A gate on the key, then a join with an inequality besides."""
    lines = table(spark, sf_dir, "lineitem").select("l_partkey", "l_extendedprice")
    parts = table(spark, sf_dir, "part").filter("p_size <= 5").select("p_partkey", "p_size", "p_retailprice")
    joined = joins.gated(lines, parts, ("l_partkey", "p_partkey")).filter("l_extendedprice > 20 * p_retailprice")
    return joined.groupBy("p_size").agg(F.count("*").alias("n"))


@_query("SELECT c_mktsegment, count(*) AS n_rows, count(o_orderkey) AS n_orders FROM customer LEFT JOIN (SELECT * FROM orders WHERE o_orderpriority LIKE '1-%') o ON c_custkey = o_custkey GROUP BY c_mktsegment")
def outer_join_legal(spark, sf_dir):
    """A left join keeps every row: sure non-members skip the lookup and get nulls."""
    customers = table(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment")
    orders = table(spark, sf_dir, "orders").filter("o_orderpriority LIKE '1-%'").select("o_orderkey", "o_custkey")
    joined = joins.gated(customers, orders, ("c_custkey", "o_custkey"), "left_outer")
    return joined.groupBy("c_mktsegment").agg(F.count("*").alias("n_rows"), F.count("o_orderkey").alias("n_orders"))


@_query("SELECT count(*) AS n_rows, count(l_orderkey) AS n_left, count(o_orderkey) AS n_right FROM (SELECT * FROM lineitem WHERE l_linenumber = 1) l FULL JOIN (SELECT * FROM orders WHERE o_orderkey % 3 = 0) o ON l_orderkey = o_orderkey")
def full_join_legal(spark, sf_dir):
    lines = table(spark, sf_dir, "lineitem").filter("l_linenumber = 1").select("l_orderkey")
    orders = table(spark, sf_dir, "orders").filter("o_orderkey % 3 = 0").select("o_orderkey")
    return joins.gated(lines, orders, ("l_orderkey", "o_orderkey"), "full_outer").agg(F.count("*").alias("n_rows"), F.count("l_orderkey").alias("n_left"), F.count("o_orderkey").alias("n_right"))


@_query(f"SELECT o_orderpriority, l_returnflag, grouping_id(o_orderpriority, l_returnflag) AS level, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM {_GATED} GROUP BY ROLLUP (o_orderpriority, l_returnflag)")
def rollup_measures(spark, sf_dir):
    return _gated_lines(spark, sf_dir).rollup("o_orderpriority", "l_returnflag").agg(F.grouping_id().alias("level"), F.count("*").alias("n"), money(F.col("l_quantity"), "quantity"))


@_query(f"SELECT l_linestatus, l_returnflag, count(*) AS n FROM {_GATED} GROUP BY CUBE (l_linestatus, l_returnflag)")
def cube_gate_counts(spark, sf_dir):
    return _gated_lines(spark, sf_dir).cube("l_linestatus", "l_returnflag").agg(F.count("*").alias("n"))


@_query(f"SELECT o_orderpriority, l_returnflag, count(*) AS n FROM {_GATED} GROUP BY GROUPING SETS ((o_orderpriority), (l_returnflag), ())")
def grouping_sets(spark, sf_dir):
    lines = _gated_lines(spark, sf_dir)
    return lines.groupingSets([[F.col("o_orderpriority")], [F.col("l_returnflag")], []], F.col("o_orderpriority"), F.col("l_returnflag")).agg(F.count("*").alias("n"))


@_query(f"SELECT o_orderpriority, CAST(count(*) FILTER (l_returnflag = 'A') AS BIGINT) AS a, CAST(count(*) FILTER (l_returnflag = 'N') AS BIGINT) AS n, CAST(count(*) FILTER (l_returnflag = 'R') AS BIGINT) AS r FROM {_GATED} GROUP BY o_orderpriority HAVING count(*) > 10")
def pivot_having(spark, sf_dir):
    counts = _gated_lines(spark, sf_dir).groupBy("o_orderpriority").pivot("l_returnflag", ["A", "N", "R"]).count().na.fill(0)
    return counts.filter(F.col("A") + F.col("N") + F.col("R") > 10).select("o_orderpriority", F.col("A").alias("a"), F.col("N").alias("n"), F.col("R").alias("r"))


@_query(f"SELECT l_orderkey, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM {_GATED} GROUP BY l_orderkey ORDER BY quantity DESC, l_orderkey LIMIT 20")
def topk_gate(spark, sf_dir):
    """The heaviest gated orders (a report of twenty)."""
    per_order = _gated_lines(spark, sf_dir).groupBy("l_orderkey").agg(F.count("*").alias("n"), money(F.col("l_quantity"), "quantity"))
    return per_order.orderBy(F.desc("quantity"), "l_orderkey").limit(20)


@_query("WITH a AS (SELECT DISTINCT l_orderkey AS k FROM lineitem WHERE l_quantity < 10), b AS (SELECT o_orderkey AS k FROM orders WHERE o_orderkey % 3 = 0) SELECT 'union' AS op, count(*) AS n FROM (SELECT * FROM a UNION SELECT * FROM b) UNION ALL SELECT 'intersect', count(*) FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT 'except', count(*) FROM (SELECT * FROM a EXCEPT SELECT * FROM b)")
def set_ops_keys(spark, sf_dir):
    """Exact set algebra, which filters over the same sets stand in for."""
    a = table(spark, sf_dir, "lineitem").filter("l_quantity < 10").select(F.col("l_orderkey").alias("k")).distinct()
    b = table(spark, sf_dir, "orders").filter("o_orderkey % 3 = 0").select(F.col("o_orderkey").alias("k"))
    one = lambda df, op: df.agg(F.lit(op).alias("op"), F.count("*").alias("n"))
    both = joins.semi(a, b, "k")
    return one(a.unionByName(b).distinct(), "union").unionByName(one(both, "intersect")).unionByName(one(joins.anti(a, b, "k"), "except"))


@_query("SELECT l_returnflag, count(DISTINCT l_orderkey) AS orders, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY l_returnflag")
def distinct_aggs(spark, sf_dir):
    lines = table(spark, sf_dir, "lineitem")
    return lines.groupBy("l_returnflag").agg(F.count_distinct("l_orderkey").alias("orders"), F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"))


@_query("WITH e AS (SELECT event_type, CAST(json_extract_string(props, '$.k') AS VARCHAR) AS k, value FROM events) SELECT event_type, k, count(*) AS n, min(value) AS least, max(value) AS most FROM e GROUP BY ALL")
def json_functions(spark, sf_dir):
    events = table(spark, sf_dir, "events").select("event_type", F.get_json_object("props", "$.k").alias("k"), "value")
    return events.groupBy("event_type", "k").agg(F.count("*").alias("n"), F.min("value").alias("least"), F.max("value").alias("most"))


@_query("SELECT user_id, count(*) AS n_events, count(DISTINCT event_type) AS n_types, date_diff('day', min(ts), max(ts)) AS days FROM events GROUP BY user_id")
def array_map_functions(spark, sf_dir):
    events = table(spark, sf_dir, "events").groupBy("user_id").agg(F.collect_list("event_type").alias("types"), F.min("ts").alias("a"), F.max("ts").alias("b"))
    m = F.map_from_arrays(F.array(F.lit("events"), F.lit("types")), F.array(F.size("types"), F.size(F.array_distinct("types"))))
    return events.select("user_id", F.element_at(m, "events").cast("bigint").alias("n_events"), F.element_at(m, "types").cast("bigint").alias("n_types"), F.datediff("b", "a").cast("bigint").alias("days"))


@_query("SELECT user_id, event_id, rank() OVER w AS place, ntile(4) OVER w AS quarter, round(sum(value) OVER (w ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS recent FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def ranking_windows(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    events = table(spark, sf_dir, "events")
    return events.select("user_id", "event_id", F.rank().over(w).cast("bigint").alias("place"), F.ntile(4).over(w).cast("bigint").alias("quarter"), F.round(F.sum("value").over(w.rowsBetween(-2, 0)), 4).alias("recent"))


@_query("SELECT user_id, event_id, count(*) OVER (w RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS in_a_day, round(percent_rank() OVER (PARTITION BY event_type ORDER BY value, event_id), 6) AS standing FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)")
def range_frames(spark, sf_dir):
    """A frame by time rather than by rows, and standing among all events of a type."""
    micros = F.unix_micros(F.col("ts").cast("timestamp"))
    day = Window.partitionBy("user_id").orderBy(micros).rangeBetween(-86_400_000_000, 0)
    standing = F.percent_rank().over(Window.partitionBy("event_type").orderBy("value", "event_id"))
    return table(spark, sf_dir, "events").select("user_id", "event_id", F.count("*").over(day).alias("in_a_day"), F.round(standing, 6).alias("standing"))


@_query("SELECT o_orderpriority, count(*) AS n_sample, CAST(min(o_orderkey) AS BIGINT) AS least FROM orders WHERE ('0x' || substr(md5(CAST(o_orderkey AS VARCHAR)), 1, 8))::BIGINT % 10 = 3 GROUP BY o_orderpriority")
def hash_sample(spark, sf_dir):
    """A sampling operator: a tenth of the keys by a portable hash, the same in every run and table."""
    share = F.conv(F.substring(F.md5(F.col("o_orderkey").cast("string").cast("binary")), 1, 8), 16, 10).cast("long") % 10
    picked = table(spark, sf_dir, "orders").filter(share == 3)
    return picked.groupBy("o_orderpriority").agg(F.count("*").alias("n_sample"), F.min("o_orderkey").alias("least"))


@_query("SELECT o_orderpriority, count(*) AS n FROM orders WHERE o_orderpriority IN ('1-URGENT', '2-HIGH') GROUP BY o_orderpriority")
def stratified_sample(spark, sf_dir):
    """Sampling by stratum: all of two priorities, none of the others."""
    orders = table(spark, sf_dir, "orders")
    return orders.sampleBy("o_orderpriority", {"1-URGENT": 1.0, "2-HIGH": 1.0}, seed=5).groupBy("o_orderpriority").agg(F.count("*").alias("n"))


@_query("SELECT k, n FROM (SELECT k, count(*) AS n FROM (SELECT l_orderkey AS k FROM lineitem EXCEPT ALL SELECT o_orderkey FROM orders) GROUP BY k) ORDER BY n DESC, k LIMIT 50 OFFSET 10")
def except_all_offset(spark, sf_dir):
    """Bag difference, then the second page of a report."""
    lines, orders = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("k")), table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("k"))
    return lines.exceptAll(orders).groupBy("k").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "k").offset(10).limit(50)


@_query("""SELECT event_type, '{"k":' || json_extract_string(props, '$.k') || ',"t":"' || event_type || '"}' AS again, count(*) AS n FROM events GROUP BY ALL""")
def json_round_trip(spark, sf_dir):
    """A column of JSON read by a schema and written again."""
    events = table(spark, sf_dir, "events").select("event_type", F.from_json("props", "k int").alias("p"))
    again = F.to_json(F.struct(F.col("p.k").alias("k"), F.col("event_type").alias("t")))
    return events.groupBy("event_type", again.alias("again")).agg(F.count("*").alias("n"))


@_query("WITH a AS (SELECT nullif(o_custkey % 50, 7) AS k FROM orders), b AS (SELECT nullif(c_custkey % 50, 7) AS k, c_mktsegment FROM customer WHERE c_custkey < 50) SELECT c_mktsegment, count(*) AS n FROM a JOIN b ON a.k IS NOT DISTINCT FROM b.k GROUP BY c_mktsegment")
def null_safe_join(spark, sf_dir):
    """Null keys that meet each other: no gate stands before such a join."""
    a = table(spark, sf_dir, "orders").select(F.expr("nullif(o_custkey % 50, 7)").alias("k"))
    b = table(spark, sf_dir, "customer").filter("c_custkey < 50").select(F.expr("nullif(c_custkey % 50, 7)").alias("m"), "c_mktsegment")
    return a.join(b, a.k.eqNullSafe(b.m)).groupBy("c_mktsegment").agg(F.count("*").alias("n"))


@_query("SELECT p_size, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey WHERE regexp_matches(p_name, '^[a-m].*t$') AND p_size BETWEEN 10 AND 20 GROUP BY p_size")
def rlike_between_gate(spark, sf_dir):
    """Members chosen by a pattern and a range; both reach the scan of the small side."""
    parts = table(spark, sf_dir, "part").filter(F.col("p_name").rlike("^[a-m].*t$") & F.col("p_size").between(10, 20)).select("p_partkey", "p_size")
    return joins.gated(table(spark, sf_dir, "lineitem").select("l_partkey"), parts, ("l_partkey", "p_partkey")).groupBy("p_size").agg(F.count("*").alias("n"))


@_query("SELECT l_returnflag, quantile_disc(l_quantity, 0.5) AS median, quantile_disc(l_quantity, 0.9) AS tail FROM lineitem GROUP BY l_returnflag")
def percentiles(spark, sf_dir):
    """Quantiles by the engine's sketch, at an accuracy that makes them exact here."""
    q = lambda p: F.percentile_approx("l_quantity", p, 1_000_000)
    return table(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(q(0.5).alias("median"), q(0.9).alias("tail"))
