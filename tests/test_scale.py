"""Measures and simulations over key sets of more than one shard, and over the given tables."""

from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from sieve.plans import workloads

SMALL = "/root/testdata/sf0.001"


@pytest.fixture
def small_shards(monkeypatch):
    """Shards of 512 to 1024 keys: sets of some thousand keys stand for those of millions."""
    monkeypatch.setattr("sieve.operators.build.SHARD_LOG2", 9)
    monkeypatch.setattr("sieve.plans.workloads.MOST_KEYS", 1000)


def test_a_sweep_measures_sets_of_many_shards_whole(spark, small_shards):
    # 6000 lines, two of them alike
    got = workloads.size_sweep(spark, workloads.table_key_sets(spark, SMALL), [700]).toPandas()
    lines = got[got.workload == "size of lineitem"]
    assert set(lines["filter"]) == {"fuse3-8", "fuse4-8", "xor-8"} and (lines.n == 5999).all() and (lines.n_probe == 800_000).all()
    assert (got[got.workload == "size"].n == 700).all() and len(got) == 18
    assert ((lines.fpr - 1 / 256).abs() < 0.0005).all() and (lines.build_ns_per_key > 0).all()


def test_failures_are_tried_on_every_shard(spark, small_shards, tmp_path):
    for t, c in (("supplier", "s_suppkey"), ("part", "p_partkey"), ("orders", "o_orderkey")):
        spark.range({"supplier": 0, "part": 700, "orders": 6000}[t]).withColumnRenamed("id", c).write.parquet(str(tmp_path / f"{t}.parquet"))
    got = entry.queries()["failure_sim"](spark, str(tmp_path)).toPandas()
    assert set(zip(got.kind, got.source)) == {("fuse3", "supplier"), ("fuse3", "part"), ("fuse4", "orders"), ("xor", "supplier"), ("xor", "part")}
    assert got[got.source == "supplier"].rare.all()


@pytest.mark.parametrize("name, pairs", [("failure_sim", 5), ("failure_sim_others", 4)])
def test_every_key_set_tries_as_many_seeds(spark, monkeypatch, name, pairs):
    done = []

    def over_shards(sets, run, schema, tasks=1):
        done.extend(r for s in sets for turn in range(3) for r in run(s, 0, 1, turn, 3, np.arange(40)))
        return spark.createDataFrame(done, schema)

    monkeypatch.setattr("sieve.queries.invariants.over_shards", over_shards)
    assert entry.queries()[name](spark, SMALL).count() == pairs
    assert set(Counter((r["kind"], r["source"]) for r in done).values()) == {200}


def test_failures_of_the_other_pairs_are_counted_on_every_shard(spark, small_shards, tmp_path):
    for t, c, n in (("supplier", "s_suppkey", 0), ("part", "p_partkey", 700), ("orders", "o_orderkey", 2500)):
        spark.range(n).withColumnRenamed("id", c).write.parquet(str(tmp_path / f"{t}.parquet"))
    got = entry.queries()["failure_sim_others"](spark, str(tmp_path)).toPandas().set_index(["kind", "source"])
    assert got.builds.to_dict() == {("fuse4", "supplier"): 0, ("fuse4", "part"): 200, ("fuse3", "orders"): 800, ("xor", "orders"): 800}
    some = got[got.builds > 0]
    assert (some.failure_rate == some.failed / some.builds).all() and (some.most_tries >= 1 + (some.failed > 0)).all()


def test_every_turn_gets_its_whole_shard(spark, small_shards):
    df = spark.range(3000).select(F.when(F.col("id") % 3 > 0, F.col("id")).alias("k"))
    run = lambda name, at, shards, turn, turns, keys: iter([{"name": name, "at": at, "shards": shards, "turn": turn, "n": len(keys), "x": int(keys[0]) ^ int(keys[-1])}])
    got = workloads.over_shards({"a": (df.union(df), ["k"]), "b": (df.limit(9), ["k"]), "none": (df.limit(0), ["k"])}, run, "name string, at int, shards int, turn int, n long, x long", tasks=8).toPandas()
    assert got[got.name == "a"].groupby("turn").n.sum().tolist() == [2000] * 4 and got[got.name == "a"].groupby("at").x.nunique().tolist() == [1, 1]
    assert got[got.name == "b"].n.tolist() == [df.limit(9).dropna().count()] * 8 and set(got.name) == {"a", "b"}


def test_kinds_are_measured_over_every_shard(spark, small_shards):
    members = spark.range(6000).withColumnRenamed("id", "k")
    got = workloads.measure_kinds(spark, members.union(members), "k", ["fuse3-8", "vqf-8"]).toPandas().set_index("filter")
    assert (got.n == 6000).all() and (got.n_probe == 8_000_000).all() and (got.repeat == 3).all()
    assert abs(got.fpr["fuse3-8"] - 1 / 256) < 0.0002 and got.overhead["vqf-8"] > got.overhead["fuse3-8"] > 0


def test_one_shard_is_measured_as_its_keys_are(spark):
    members = spark.range(3000).withColumnRenamed("id", "k")
    got = workloads.measure_sets(spark, {"families": (members, ["k"])}, ["fuse3-8", "xor-8"], n_probe=50_000).toPandas().set_index("filter")
    for r in workloads.measure(workloads.key_array(members, "k")[0], ["fuse3-8", "xor-8"], n_probe=50_000):
        assert {c: got[c][r["filter"]] for c in ("n", "n_probe", "bits_per_key", "fpr", "overhead", "note")} == {c: r[c] for c in ("n", "n_probe", "bits_per_key", "fpr", "overhead", "note")}


@pytest.fixture(scope="module")
def odd(spark, tmp_path_factory):
    """Tables with null and repeated keys, one of them empty; DuckDB over the same files."""
    import duckdb

    root, con = tmp_path_factory.mktemp("odd"), duckdb.connect()
    key = F.when(F.col("id") % 50 > 0, F.col("id") % 4000)
    made = {t: spark.range(n).select(key.alias(k)) for t, n, k in (("region", 5, "r_regionkey"), ("nation", 25, "n_nationkey"), ("supplier", 3, "s_suppkey"), ("customer", 0, "c_custkey"), ("part", 400, "p_partkey"), ("orders", 4700, "o_orderkey"))}
    day = F.when(F.col("id") % 7 > 0, F.date_add(F.lit("2001-01-01").cast("date"), (F.col("id") % 90).cast("int")).cast("timestamp"))
    made["lineitem"] = spark.range(9000).select(key.alias("l_orderkey"), (F.col("id") % 3).alias("l_partkey"), F.lit(1).alias("l_suppkey"), (F.col("id") % 2).cast("int").alias("l_linenumber"), day.alias("l_shipdate"))
    for t, df in made.items():
        df.coalesce(1).write.parquet(str(root / f"{t}.parquet"))
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{root}/{t}.parquet/*.parquet')")
    return str(root), con


@pytest.mark.parametrize("name", ["accesses_per_probe", "crossover", "cuckoo_equal_eps", "smallest_curve", "theory_curves"])
def test_formulas_take_their_sets_from_the_tables(spark, odd, same, name):
    root, con = odd
    df = entry.queries()[name](spark, root)
    assert df.inputFiles()
    same(df.toPandas(), con.execute(entry.oracle_sql()[name]).df())


def test_failure_curve_builds_over_the_lines(spark, odd):
    """8820 lines have some 3920 keys: larger sets are not made up."""
    got = entry.queries()["failure_curve"](spark, odd[0]).toPandas()
    assert sorted(set(got.n)) == [5, 10, 30, 100, 300, 1000, 3000] and len(got) == 21
    assert got.failure_rate.between(0, 1).all() and (got.most_tries >= 1).all()


def test_space_order_is_that_of_the_lines(spark, odd, same):
    """So few keys that padding makes the fuse array larger than xor's."""
    got = entry.queries()["space_order"](spark, odd[0]).toPandas()
    same(got, odd[1].execute(entry.oracle_sql()["space_order"]).df())
    assert not got.set_index("kind").ordered["xor over fuse3"] and got.ordered.sum() == 6
