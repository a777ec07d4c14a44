"""Hashing, sizes, peeling, kinds, probes, joins, catalogue and plans of the filter engine."""

import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

import __spark_entry__ as entry
from sieve.functions import hashing, keys, measures, sizing, theory
from sieve.operators import joins, peel, probe
from sieve.operators.build import build, build_keys
from sieve.operators.contains import Loaded
from sieve.operators.kinds import fuse_shape
from sieve.plans.workloads import CATALOGUE, measure, mixed_probes
from sieve.schema import FILTERS, spec
from sieve.sources import catalog

SF = "/root/testdata/sf0.01"
EDGES = [0, 1, -1, 42, 2**31, -(2**31), 2**63 - 1, -(2**63), 123456789123456789, -987654321987654321]


def random_keys(n, seed=0):
    return np.unique(np.random.default_rng(seed).integers(-(2**63), 2**63 - 1, n, dtype=np.int64))


# --- hashing ---------------------------------------------------------------------


@pytest.mark.parametrize("seed", [0, 1, -5, 2**40])
def test_words_match_the_jvm(spark, seed):
    df = spark.createDataFrame([(x,) for x in EDGES], "k bigint")
    a, b = hashing.word_columns(F.col("k"), F.lit(seed).cast("long"))
    got = df.select("k", a.alias("a"), b.alias("b")).collect()
    mine = hashing.words(np.array([r["k"] for r in got], np.int64), seed)
    assert [r["a"] for r in got] == mine[0].view(np.int64).tolist() and [r["b"] for r in got] == mine[1].view(np.int64).tolist()


@given(st.integers(0, 2**64 - 1), st.integers(1, 2**31 - 1))
def test_reduction_stays_in_range(x, size):
    assert 0 <= hashing.reduce32(hashing.high(np.array([x], np.uint64)), size)[0] < size


@pytest.mark.parametrize(("layout", "arity"), [("fuse", 3), ("fuse", 4), ("overlap", 3), ("plain", 3), ("blocks", 3), ("fuse", 5)])
def test_location_columns_match_numpy(spark, layout, arity):
    ks = random_keys(500)
    length, count = (1000, 3) if layout == "blocks" else (37 if layout == "plain" else 64, 11)
    a, b = hashing.words(ks, 9)
    loc = hashing.locations(a, b, length, count, arity, layout)
    ca, cb = hashing.word_columns(F.col("k"), F.lit(9).cast("long"))
    cols = hashing.location_columns(ca, cb, F.lit(length), F.lit(count), arity, layout)
    rows = spark.createDataFrame([(int(k),) for k in ks], "k bigint").select("k", *[c.alias(f"l{j}") for j, c in enumerate(cols)]).collect()
    by = {r["k"]: list(r)[1:] for r in rows}
    assert all(by[int(k)] == p for k, p in zip(ks, loc.tolist()))
    assert loc.min() >= 0 and loc.max() < length * count and all(len(set(p)) == arity for p in loc.tolist())
    if layout == "fuse":
        seg = loc // length
        assert (np.diff(seg, axis=1) == 1).all()


def test_null_keys_and_shards(spark):
    df = spark.createDataFrame([(1, None), (None, "a"), (2, "b")], "x bigint, y string")
    got = [r[0] for r in df.select(keys.key64("x", "y")).collect()]
    assert got[:2] == [None, None] and got[2] is not None
    for bits in (0, 1, 5, 20):
        s = [r[0] for r in spark.createDataFrame([(x,) for x in EDGES], "k bigint").select(keys.shard(F.col("k"), bits)).collect()]
        assert s == [int((x & (2**64 - 1)) >> (64 - bits)) if bits else 0 for x in EDGES]


# --- sizes -----------------------------------------------------------------------


@pytest.mark.parametrize("n", [0, 1, 2, 5, 25, 100, 1000, 15000, 150000, 600000, 10**6, 10**8])
def test_sizes_in_columns_and_python(spark, n):
    for arity in (3, 4):
        row = spark.range(1).select(*sizing.fuse_columns(F.lit(n), arity)).first()
        cells, length, count = sizing.fuse(n, arity)
        assert tuple(row) == (cells, length, count) and length & (length - 1) == 0 and count >= arity and count * length >= cells


def test_published_sizes():
    """Bits per key of large 8-bit filters, and segments in the hundreds."""
    for arity, want in ((3, 9.0), (4, 8.6)):
        _, length, count = sizing.fuse(10**8, arity)
        assert abs(8 * length * count / 1e8 - want) < 0.05 and 100 < count < 5000
    assert abs(3 * sizing.xor(10**6) * 8 / 1e6 - 9.84) < 0.01
    assert sizing.bloom_hashes(12) == 8 and sizing.bloom_hashes(16) == 11 and round(sizing.bloom_bits_for(0.01) * math.log(2)) == 7
    assert theory.match_cuckoo(64) == {"fuse3": 65, "fuse4": 62}


# --- peeling ---------------------------------------------------------------------


def test_worked_example():
    """Six cells in three segments of two; four keys a, b, c, d with fingerprints 1 to 4."""
    loc = np.array([[0, 2, 4], [0, 3, 4], [1, 3, 5], [1, 2, 4]])
    layers = peel.peel_layers(loc, 6)
    assert [sorted(zip(r.tolist(), c.tolist())) for r, c in layers] == [[(2, 5)], [(1, 3), (3, 1)], [(0, 0)]]
    cells = peel.assign(layers, loc, np.array([1, 2, 3, 4], np.uint8), 6)
    assert cells.tolist() == [1, 4, 0, 3, 0, 4] and peel.lookup(cells, loc).tolist() == [1, 2, 3, 4]


def test_stall_and_duplicates():
    assert peel.peeled(peel.peel_layers(np.array([[0, 2, 4], [0, 2, 4]]), 6)) == 0
    count, mask = peel.key_masks(np.array([[0, 2, 4], [0, 2, 4]]), np.array([7, 7]), 6)
    assert count[0] == 2 and mask[0] == 0


@settings(max_examples=25, deadline=None)
@given(st.integers(1, 400), st.integers(0, 10**6))
def test_orders_peel_the_same_keys(n, seed):
    ks = random_keys(n, seed)
    length, count = fuse_shape(len(ks), spec("fuse3"))
    a, b = hashing.words(ks, seed)
    loc = hashing.locations(a, b, length, count, 3, "fuse")
    layer, stack = peel.peel(loc, length * count), peel.peel(loc, length * count, "stack")
    assert peel.peeled(layer) == peel.peeled(stack)
    own = np.concatenate([c for _, c in layer]) if layer else np.zeros(0)
    assert len(set(own.tolist())) == len(own)
    if peel.peeled(layer) == len(ks):
        fp = hashing.fingerprint(a, 8)
        for order in (layer, stack):
            assert (peel.lookup(peel.assign(order, loc, fp, length * count), loc) == fp).all()


# --- kinds -----------------------------------------------------------------------


@pytest.mark.parametrize("name", CATALOGUE)
@pytest.mark.parametrize("n", [1, 2, 50, 3000])
def test_members_answer(name, n):
    kind, how = CATALOGUE[name]
    ks = random_keys(n, n)
    f, bits = measures.loaded(ks, spec(kind, **how))
    assert f.contains(ks).all() and bits > 0


@pytest.mark.parametrize("name", CATALOGUE)
def test_generated_code_and_numpy_agree(spark, name):
    kind, how = CATALOGUE[name]
    members = spark.range(0, 4000, 3).withColumnRenamed("id", "k")
    f = build(members, "k", kind, shard_bits=1, **how)
    probes = spark.range(0, 30000).withColumnRenamed("id", "k")
    rows = {r["shard"]: r.asDict() for r in f.table.collect()}
    flagged = probe.contains(probes, f, "k").withColumn("key", keys.key64("k")).withColumn("s", keys.shard(F.col("key"), 1)).toPandas()
    for s, part in flagged.groupby("s"):
        assert (Loaded(rows[s], f.spec).contains(part.key.to_numpy(np.int64)) == part.maybe_member.to_numpy()).all()
    assert flagged.maybe_member[(flagged.k % 3 == 0) & (flagged.k < 4000)].all()


@pytest.mark.parametrize("name", CATALOGUE)
def test_error_rate_is_the_models(name):
    kind, how = CATALOGUE[name]
    ks = random_keys(20000, 1)
    s = spec(kind, **how)
    f, _ = measures.loaded(ks, s)
    others = np.setdiff1d(random_keys(300_000, 2), ks)
    eps = theory.expected_fpr(kind, s.fp_bits, s.bits_per_key, s.hashes, 0.93 if kind == "vqf" else 0.94)
    got = f.contains(others).mean()
    spread = 5 * math.sqrt(eps * (1 - eps) / len(others))
    assert eps / 1.3 - spread <= got <= eps * 1.3 + spread


def test_space_order():
    """Worst first: blocked Bloom, Bloom and vector quotient; ribbon and fuse are economical."""
    rows = {r["filter"]: r for r in measure(random_keys(60000, 3), ["blocked-12", "bloom-12", "vqf-8", "xor-8", "fuse3-8", "fuse4-8", "ribbon-8"], n_probe=400_000, repeats=1)}
    over = {k: r["overhead"] for k, r in rows.items()}
    assert over["blocked-12"] > over["bloom-12"] > over["xor-8"] > over["fuse3-8"] > over["fuse4-8"] and over["vqf-8"] > over["xor-8"]
    assert over["ribbon-8"] < over["xor-8"]


def test_cells_do_not_depend_on_order_or_partitions(spark):
    df = spark.range(0, 5000).withColumnRenamed("id", "k")
    a = build(df, "k", shard_bits=1).table.sort("shard").select("cells8", "seed").collect()
    b = build(df.orderBy(F.rand(3)).repartition(13).union(df), "k", shard_bits=1, predistinct=True).table.sort("shard").select("cells8", "seed").collect()
    assert a == b


def test_bad_settings():
    for bad in (lambda: spec("nothing"), lambda: spec("fuse3", fp_bits=12), lambda: spec("fuse2"), lambda: build_keys(random_keys(1000), spec("fuse3", size_factor=0.5, max_attempts=3), 1)):
        with pytest.raises((ValueError, RuntimeError)):
            bad()


def test_empty_set(spark):
    none = spark.createDataFrame([], "k bigint")
    f = build(none, "k", shard_bits=0)
    probes = spark.range(10).withColumnRenamed("id", "k")
    assert f.table.count() == 0 and probe.semi(probes, f, "k").count() == 0 and probe.anti(probes, f, "k").count() == 10
    assert not any(r["maybe_member"] for r in probe.contains(probes, f, "k").collect())


def test_aggregation_builds_equal_bits(spark):
    df = spark.range(0, 3000).withColumnRenamed("id", "k")
    for kind in ("bloom", "blocked"):
        f = build(df, "k", kind, shard_bits=1, engine="sql")
        assert probe.semi(df, f, "k").count() == 3000
        g = build(df, "k", kind, shard_bits=1)
        assert f.table.agg(F.sum("payload_bits")).first() == g.table.agg(F.sum("payload_bits")).first()


# --- probes and joins ------------------------------------------------------------


def plan_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_gate_plan_has_no_exchange_on_the_fact(spark):
    lines = spark.read.parquet(f"{SF}/lineitem.parquet").select("l_orderkey")
    f = build(spark.range(100).withColumnRenamed("id", "k"), "k", shard_bits=0)
    text = plan_of(probe.semi(lines, f, "l_orderkey", plan="broadcast"))
    assert "BroadcastHashJoin" in text and "LeftSemi" in text and "hashpartitioning" not in text and "ArrowEval" not in text
    assert "ReadSchema: struct<l_orderkey:bigint>" in text


def test_build_plan_has_one_exchange(spark):
    f = build(spark.range(1000).withColumnRenamed("id", "k"), "k", shard_bits=2, keep=False)
    assert plan_of(f.table).count("Exchange") == 1


def test_strategy_checks_the_size(spark):
    f = build(spark.range(5000).withColumnRenamed("id", "k"), "k", shard_bits=0)
    assert probe.strategy(f) == "broadcast" and probe.strategy(f, limit=100) == "shuffle"
    v = build(spark.range(5000).withColumnRenamed("id", "k"), "k", "vqf", shard_bits=0)
    assert probe.strategy(v) == "arrow" and probe.strategy(v, limit=100) == "cogroup"


@pytest.mark.parametrize("how", ["inner", "left_semi", "left_anti", "left_outer", "full_outer", "right_outer"])
def test_gated_joins_equal_plain_joins(spark, how):
    a = spark.createDataFrame([(i if i % 7 else None, i) for i in range(300)], "x bigint, v int")
    b = spark.createDataFrame([(i * 2, f"s{i}") for i in range(60)] + [(None, "n")], "y bigint, w string")
    want = a.alias("l").join(b.alias("r"), F.col("l.x") == F.col("r.y"), how)
    got = joins.gated(a, b, ("x", "y"), how, shard_bits=1)
    key = lambda df: sorted(map(str, df.collect()))
    assert key(got) == key(want)


def test_illegal_gate():
    with pytest.raises(ValueError):
        joins.legal_prefilter("cross")


def test_asof_and_range(spark):
    a = spark.createDataFrame([(1, 5), (1, 10), (2, 1)], "k int, t int")
    b = spark.createDataFrame([(1, 4, 40.0), (1, 10, 100.0), (2, 3, 30.0)], "k int, t int, v double")
    got = sorted(tuple(r) for r in joins.asof_join(a, b, ("k", "k"), ("t", "t"), "v", "last").collect())
    assert got == [(1, 5, 40.0), (1, 10, 100.0), (2, 1, None)]
    periods = spark.createDataFrame([(1, 0, 6), (1, 9, 11)], "k int, a int, b int")
    assert joins.range_join(a, periods, ("k", "k"), "t", "a", "b").count() == 2


# --- catalogue -------------------------------------------------------------------


def test_save_load_and_refresh(spark, tmp_path):
    df = spark.range(2000).withColumnRenamed("id", "k")
    f = build(df, "k", "fuse4", shard_bits=3, filter_id="x")
    catalog.save(f, str(tmp_path))
    g = catalog.load(spark, str(tmp_path), "x", family="xxhash64")
    assert g.spec == f.spec and g.table.columns == FILTERS.fieldNames() and probe.semi(df, g, "k").count() == 2000
    with pytest.raises(ValueError):
        catalog.load(spark, str(tmp_path), "x", family="md5")
    more = spark.range(2003).withColumnRenamed("id", "k")
    h = catalog.refresh(g, more, spark.range(2000, 2003).withColumnRenamed("id", "k"), "k")
    assert h.keys() == 2003 and probe.semi(more, h, "k").count() == 2003
    before = {r["shard"]: r["seed"] for r in f.table.select("shard", "seed").collect()}
    after = {r["shard"]: r["n"] for r in h.table.select("shard", "n").collect()}
    assert set(before) == set(after)


def test_mixed_probes_have_their_share(spark):
    members = spark.range(1000).withColumnRenamed("id", "k")
    got = mixed_probes(members, "k", 8000, 0.25).agg(F.avg(F.col("is_member").cast("double"))).first()[0]
    assert abs(got - 0.25) < 0.01


# --- entry -----------------------------------------------------------------------

CORE = [n for n in sorted(entry.oracle_sql()) if not n.startswith("op") and n != "pipeline"]


@pytest.mark.parametrize("name", CORE)
def test_sql(spark, duck, same, name):
    same(entry.queries()[name](spark, SF).toPandas(), duck.execute(entry.oracle_sql()[name]).df())


def test_entry(spark):
    assert entry.entry(spark).count() > 0


def test_every_query_is_named_once():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_probes_tell_small_errors_apart():
    from sieve.queries import invariants

    assert hasattr(invariants, "outside_probes")
    for bits in (8, 12, 15, 16):
        eps = 2.0**-bits
        n = invariants.outside_probes(eps)
        assert n >= (10**7 if bits >= 15 else 200_000) and 0 < eps * n - 5 * (eps * n) ** 0.5 and eps * n + 5 * (eps * n) ** 0.5 < 1.5 * eps * n


# --- safety at scale ---------------------------------------------------------------


@pytest.mark.parametrize("plan", ["broadcast", "shuffle", "arrow", "cogroup"])
def test_clashing_columns_survive_every_plan(spark, plan):
    names = ["k", "__key", "key", "Shard", "__shard", "maybe", "__maybe", "salt", "row", "side", "f", "p"]
    df = spark.createDataFrame([(i if i % 7 else None, *range(1, len(names))) for i in range(200)], ", ".join(f"`{n}` bigint" for n in names))
    f = build(spark.range(0, 100).withColumnRenamed("id", "k"), "k", shard_bits=2)
    for got in (probe.semi(df, f, "k", plan), probe.anti(df, f, "k", plan)):
        assert got.columns == names
    members = [r for r in probe.semi(df, f, "k", plan).collect() if r["k"] is not None]
    assert {r["k"] for r in members} >= {i for i in range(100) if i % 7} and all(tuple(r)[1:] == tuple(range(1, len(names))) for r in members)
    assert probe.semi(df, f, "k", plan).count() + probe.anti(df, f, "k", plan).count() == 200
    assert probe.any_of(df.withColumnRenamed("f", "any0"), [(f, "k"), (f, "key")]).columns == [n if n != "f" else "any0" for n in names]


def test_a_hot_key_is_collapsed_before_its_shard_is_gathered(spark):
    hot = spark.range(0, 400_000).select(F.when(F.col("id") % 100 > 0, F.lit(5)).otherwise(F.col("id")).alias("k"))
    want = spark.range(0, 400_000, 100).withColumnRenamed("id", "k").unionByName(spark.createDataFrame([(5,)], "k bigint"))
    for how in ({"shard_bits": 1}, {"shard_bits": 1, "predistinct": False}, {"n_hint": 4000}, {}):
        a, b = build(hot, "k", **how), build(want, "k", **how)
        cells = lambda f: sorted((r["shard"], r["n"], r["cells8"]) for r in f.table.collect())
        assert cells(a) == cells(b)
    lazy = build(hot, "k", shard_bits=1, keep=False)
    plan = lazy.table._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1 and plan.index("HashAggregate") < plan.index("Exchange")


def test_index_asks_files_without_a_product_join(spark, tmp_path):
    from sieve.sources import index

    spark.range(0, 4000).repartitionByRange(8, "id").write.parquet(str(tmp_path / "t"))
    made = index.build_index(spark, str(tmp_path / "t"), "id")
    values = spark.createDataFrame([(3,), (3999,), (10**9,)], "id bigint")
    assert "NestedLoop" not in index.candidates(made, values, "id")._jdf.queryExecution().executedPlan().toString()
    assert 2 <= index.candidates(made, values, "id").count() <= 4
    for most in (10, 1):
        assert sorted(r[0] for r in index.read_skipping(spark, str(tmp_path / "t"), made, values, "id", most).collect()) == [3, 3999]


def test_large_filters_are_not_shipped(spark):
    from sieve.operators.contains import received, ship

    f = build(spark.range(0, 5000).withColumnRenamed("id", "k"), "k", shard_bits=2)
    assert sorted(received(ship(f, 1 << 20))) == [0, 1, 2, 3]
    with pytest.raises(ValueError):
        ship(f, 1000)


def test_a_growing_filter_decides_and_its_errors_are_looked_up(spark, tmp_path):
    """Batches of keys, with a filter so small that it errs: no key is lost, and sure keys skip the lookup."""
    from sieve.streaming import gates

    for k in range(4):
        spark.range(k * 500, k * 500 + 1000).withColumn("id", F.when(F.col("id") % 97 > 0, F.col("id"))).coalesce(1).write.mode("append").parquet(str(tmp_path / "t"))
    stream = spark.readStream.schema("id bigint").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "t"))
    for bits, errs in ((1 << 16, False), (64, True)):
        found, counts = gates.distinct_keys(stream, "id", buckets=8, bits=bits)
        assert sorted(r[0] for r in found.collect()) == [i for i in range(2500) if i % 97]
        c = counts.toPandas()
        assert (c.found_new.sum() > 0) == errs and c.sure.sum() + c.found_new.sum() == found.count()
        assert errs or c.sure.sum() == found.count()


def test_a_callers_fingerprint_function_decides(spark, tmp_path):
    keys = random_keys(5000, 11)
    df = spark.createDataFrame([(int(k),) for k in keys], "k bigint")
    plain = build(df, "k", "fuse3")
    for kind in ("fuse3", "fuse4", "xor", "xorplus"):
        own = build(df, "k", kind, fingerprint="sieve.functions.hashing:FOLDED")
        assert probe.semi(df, own, "k").count() == len(keys)
        outside = spark.range(10**15, 10**15 + 50_000).select(F.col("id").alias("k"))
        hits = probe.semi(outside, own, "k")
        assert 100 < hits.count() < 320  # 195 expected
        assert probe.contains_arrow(outside, own, ["k"]).filter("maybe_member").select("k").exceptAll(hits).count() == 0
    own = build(df, "k", "fuse3", fingerprint="sieve.functions.hashing:FOLDED")
    assert own.table.first()["cells8"] != plain.table.first()["cells8"]
    catalog.save(own, str(tmp_path / "own"))
    assert probe.semi(df, catalog.load(spark, str(tmp_path / "own")), "k").count() == len(keys)
    with pytest.raises(ValueError):
        spec("bloom", fingerprint="sieve.functions.hashing:FOLDED")
    with pytest.raises(TypeError):
        build_keys(keys, spec("fuse3", fingerprint="sieve.functions.hashing:LOW32"), 1)


def test_buffers_give_the_same_packed_cells():
    rng = np.random.default_rng(5)
    loc = np.stack([rng.integers(j * 70_000, (j + 1) * 70_000, 150_000) for j in range(3)], axis=1)
    assert (peel.packed(loc, 210_000) == peel.packed_by_region(loc, 210_000)).all()
    with pytest.raises(ValueError):
        spec("fuse3", buffered=True)
