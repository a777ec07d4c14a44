"""Streams of events behind a customer filter; their SQL is the batch answer."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sieve.operators import joins
from sieve.operators.build import build
from sieve.queries.tables import table
from sieve.streaming import gates

QUERIES = {}
ORACLES = {}

_MEMBERS = "SELECT * FROM events WHERE user_id IN (SELECT c_custkey FROM customer WHERE c_mktsegment = 'BUILDING')"


def _query(sql: str):
    def keep(f):
        QUERIES[f.__name__], ORACLES[f.__name__] = f, sql
        return f

    return keep


def _members(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "customer").filter("c_mktsegment = 'BUILDING'").select("c_custkey")


def _gated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The gated and verified stream: filter first, exact semi join after."""
    members = _members(spark, sf_dir)
    stream = gates.gate_stream(gates.read_table(spark, sf_dir, "events"), build(members, "c_custkey"), "user_id")
    return joins.exact_semi(stream, members, ("user_id", "c_custkey")).withWatermark("ts", "1 hour")


@_query(f"SELECT CAST(floor(epoch(ts) / 86400) AS BIGINT) AS day, event_type, count(*) AS n FROM ({_MEMBERS}) GROUP BY ALL")
def stream_tumbling_members(spark, sf_dir):
    counts = _gated(spark, sf_dir).groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("n"))
    return gates.run(counts, "complete").select((F.unix_timestamp("window.start") / 86400).cast("bigint").alias("day"), "event_type", "n")


@_query(f"SELECT CAST(floor(epoch(ts) / 43200) - k AS BIGINT) AS half_day, count(*) AS n FROM ({_MEMBERS}), (SELECT unnest([0, 1]) AS k) GROUP BY ALL")
def stream_sliding(spark, sf_dir):
    counts = _gated(spark, sf_dir).groupBy(F.window("ts", "1 day", "12 hours")).agg(F.count("*").alias("n"))
    return gates.run(counts, "complete").select((F.unix_timestamp("window.start") / 43200).cast("bigint").alias("half_day"), "n")


@_query(f"""WITH m AS ({_MEMBERS}), g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM m),
s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g)
SELECT user_id, count(*) AS n_events, CAST(floor(epoch(min(ts))) AS BIGINT) AS begins FROM s GROUP BY user_id, k""")
def stream_session(spark, sf_dir):
    sessions = _gated(spark, sf_dir).groupBy(F.session_window("ts", "6 hours"), "user_id").agg(F.count("*").alias("n_events"))
    return gates.run(sessions, "complete").select("user_id", "n_events", F.unix_timestamp("session_window.start").alias("begins"))


@_query(f"SELECT DISTINCT user_id, event_type FROM ({_MEMBERS})")
def stream_dedup(spark, sf_dir):
    once = _gated(spark, sf_dir).dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type")
    return gates.run(once).distinct()


@_query("SELECT count(*) AS n_rows, CAST(count(*) FILTER (ts < top - INTERVAL 10 DAY) AS BIGINT) AS n_late FROM events, (SELECT max(ts) AS top FROM events)")
def stream_late_rows(spark, sf_dir):
    """Rows far behind the newest of their batch, counted beside it."""
    found: list[tuple[int, int]] = []

    def count(df: DataFrame, _: int) -> None:
        top = df.agg(F.max("ts").alias("top"))
        r = df.crossJoin(F.broadcast(top)).agg(F.count("*"), F.count_if(F.col("ts") < F.col("top") - F.expr("INTERVAL 10 DAYS"))).first()  # one row on the right
        found.append((r[0], r[1]))

    gates.run(gates.read_table(spark, sf_dir, "events"), batch=count)
    return spark.createDataFrame([(sum(a for a, _ in found), sum(b for _, b in found))], "n_rows bigint, n_late bigint")


@_query("SELECT DISTINCT user_id FROM events")
def stream_progressive_bloom(spark, sf_dir):
    """First-seen users, by a filter that takes keys as they come; what it is unsure of is looked up."""
    return gates.distinct_keys(gates.read_table(spark, sf_dir, "events").select("user_id"), "user_id")[0]


@_query("SELECT event_type, count(*) AS n FROM events GROUP BY event_type")
def stream_refresh(spark, sf_dir):
    """A filter that follows a stream of new keys: afterwards every event passes, checked exactly."""
    events = table(spark, sf_dir, "events").select("user_id", "event_type")
    some = events.filter("user_id % 2 = 0").select("user_id").distinct()
    f = gates.refresh_by_batch(gates.read_table(spark, sf_dir, "events"), build(some, "user_id", shard_bits=3), "user_id", some)
    return joins.gated(events, events.select("user_id").distinct(), ("user_id", "user_id"), "left_semi", f=f).groupBy("event_type").agg(F.count("*").alias("n"))
