"""Operators against SQL on the given tables and against brute force on awkward rows."""

import base64
import hashlib
import re
import zlib

import numpy as np
import pandas as pd
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from sieve.llm import bpe, chat, fingerprints, licenses, mixing, neardup, quality, registry, sharding, substrings, toxicity
from sieve.llm.text import ngrams, word_hashes

SF = "/root/testdata/sf0.01"
SMALL = "/root/testdata/sf0.001"
WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, n_words bigint, kept boolean, shard int, row int"


def prose(rng, n):
    return " ".join(rng.choice(["alpha", "beta", "gamma", "delta", "eta", "theta", "iota", "kappa"], n))


@pytest.fixture(scope="module")
def rows():
    """Nulls, empty and long texts, copies, near copies, shared passages, ties, repeated rows."""
    rng = np.random.default_rng(3)
    unique = lambda n: " ".join(f"w{x}" for x in rng.integers(0, 10**9, n))
    passage, base = unique(40), unique(120)
    words = base.split()
    out = [
        (1, None), (2, ""), (3, " \n\t "), (4, "one"), (5, "One"), (6, "a b c d"), (7, base), (8, base), (9, base.upper().lower()),
        (10, " ".join(["changed", *words[1:]])), (11, " ".join([*words[:-2], "x", "y"])), (12, f"{unique(30)} {passage} {unique(25)}"),
        (13, f"{passage}\n{unique(10)}"), (14, f"{unique(5)} {passage}"), (15, "a a a a " * 40), (16, prose(rng, 300)), (17, unique(9)),
        (18, unique(3000) + " " + passage), (None, "no id here but words"), (20, "naïve café — ünïcode   space 漢字"), (20, "naïve café — ünïcode   space 漢字"),
        (21, base + " " + base), (22, "x" * 5000), (23, "line one here\nline one here\nline one here\nother"), (24, "# $ % & * | < >"),
    ]
    return [(i, t, None if k % 3 == 0 else "en", [None, "a", "b"][k % 3], None, k, True, 7, 1) for k, (i, t) in enumerate(out)]


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.mark.parametrize("name", sorted(registry.oracle_sql()))
def test_sql(spark, duck, same, name):
    same(entry.queries()[name](spark, SF).toPandas(), duck.execute(entry.oracle_sql()[name]).df())


def brute_components(rows, n, percent=80):
    def sets(t):
        w = WORD.findall((t or "").translate({c: c + 32 for c in range(65, 91)}))
        return {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if len(w) >= n else ({tuple(w)} if w else set())

    s = [(r[0], sets(r[1])) for r in rows]
    root = {i: i for i, _ in s if i is not None}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, x in s:
        for b, y in s:
            if a is not None and b is not None and x and y and 100 * len(x & y) >= percent * len(x | y):
                p, q = sorted((find(a), find(b)))
                root[q] = p
    return sorted((str(i), len(x), str(find(i) if i is not None else None)) for i, x in s)


@pytest.mark.parametrize("n", [2, 5])
def test_near_duplicates(docs, rows, n):
    got = neardup.near_duplicates(docs, words=n).toPandas()
    fix = lambda v: str(None if v != v else int(v))
    assert sorted((fix(a), int(b), fix(c)) for a, b, c in got[["doc_id", "n_shingles", "component_id"]].itertuples(index=False)) == brute_components(rows, n)
    assert (got.kept == ((got.doc_id == got.component_id) | got.doc_id.isna())).all()


def test_near_duplicates_chain_needs_cross_links(spark):
    """A large family around the threshold: stars alone leave parts, the blocks join them."""
    rng = np.random.default_rng(5)
    base = [f"b{k}" for k in range(100)]
    rows = []
    for i in range(300):
        w = list(base)
        for at in rng.choice(100, rng.integers(1, 14), replace=False):
            w[at] = f"e{rng.integers(10**9)}"
        rows.append((i, " ".join(w)))
    got = neardup.near_duplicates(spark.createDataFrame(rows, "doc_id bigint, text string"), words=2).toPandas()
    assert sorted((str(a), int(b), str(c)) for a, b, c in got[["doc_id", "n_shingles", "component_id"]].itertuples(index=False)) == brute_components(rows, 2)


@pytest.mark.parametrize("how", [{"block": 700}, {"block_sets": 9}, {"block": 700, "split": 0}, {"split": 0}])
def test_cross_links_alone_find_all_links(spark, how):
    """With no star edges at all the exact comparison still gives the components."""
    rng = np.random.default_rng(6)
    rows = [(i, " ".join([*(f"g{i % 4}x{k}" for k in range(60)), *(f"e{rng.integers(10**9)}" for _ in range(rng.integers(1, 6)))])) for i in range(60)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    sets = neardup.features(df, "doc_id", "text", 2, 8, 4, with_sets=True).dropDuplicates(["k"])
    members = sets.select(F.lit(1).cast("long").alias("bucket"), "k", "n")
    roots = spark.createDataFrame([], "a binary, root binary")
    links = neardup.cross_links(members, roots, sets, 80, **how)
    from sieve.llm.components import components

    sizes = components(links).groupBy("root").count().toPandas()
    want = pd.Series([c for _, _, c in brute_components(rows, 2)]).value_counts()
    assert sorted(sizes["count"]) == sorted(want[want > 1])


def test_components_with_hubs(spark, monkeypatch):
    """Stars, chains and a ring, with and without the broadcast of hubs."""
    from sieve.llm import components as c

    rng = np.random.default_rng(4)
    edges = [(0, k) for k in range(1, 400)] + [(k, k + 1) for k in range(1000, 1040)] + [(2000 + k, 2000 + (k + 1) % 9) for k in range(9)] + [(399, 1500), (1500, 1501)]
    edges = [(int(a), int(b)) if rng.random() < 0.5 else (int(b), int(a)) for a, b in edges] + [(5, 5), (0, 1)]
    df = spark.createDataFrame(edges, "a bigint, b bigint").repartition(4)
    want = {0: 402, 1000: 41, 2000: 9}
    for least in (256, 1, 10**6):
        monkeypatch.setattr(c, "LEAST_HUB", least)
        got = c.components(df).toPandas()
        assert got.groupby("root").size().to_dict() == want and got.a.is_unique


def test_small_sets_and_common_phrases(spark):
    """Thousands of short texts in one bucket: none can link, and none is compared."""
    rows = [(i, f"thank you n{i}") for i in range(3000)] + [(9000 + i, f"thank you very much my dear friend n{i % 40}") for i in range(80)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    got = {r["doc_id"]: r["component_id"] for r in neardup.near_duplicates(df, words=2).collect()}
    assert got == {i: i if i < 9000 else 9000 + (i - 9000) % 40 for i, _ in rows}


def test_nodes_sort_by_id(spark):
    ids = [-(1 << 63), -5, -1, 0, 1, 255, 1 << 40, (1 << 63) - 1]
    df = spark.createDataFrame([(i, b"k") for i in ids], "i bigint, k binary").select("i", neardup.node(F.col("i"), F.col("k")).alias("n"))
    rows = df.select("i", "n", neardup.id_of(F.col("n")).alias("back")).orderBy("n").collect()
    assert [r["back"] for r in rows] == [r["i"] for r in rows] == ids


def test_ids_are_whole_numbers(spark):
    df = spark.createDataFrame([("x", "a b c")], "doc_id string, text string")
    for f in (neardup.near_duplicates, fingerprints.edited_neighbours, substrings.dedup_substrings):
        with pytest.raises(TypeError):
            f(df)


def test_sketch_estimates_similarity():
    rng = np.random.default_rng(1)
    for share in (0.2, 0.5, 0.8):
        est = []
        for _ in range(40):
            common = rng.integers(0, 2**63, int(150 * share), dtype=np.uint64)
            a = np.concatenate([common, rng.integers(0, 2**63, 150 - len(common), dtype=np.uint64)])
            b = np.concatenate([common, rng.integers(0, 2**63, 150 - len(common), dtype=np.uint64)])
            bins = fingerprints.sketch(np.concatenate([a, b]), np.array([150, 150]), 256)
            x, y = fingerprints.pack(bins, np.array([150, 150]))
            est.append(fingerprints.likeness([x], [y])[0])
        true = len(common) / (300 - len(common))
        assert abs(np.mean(est) - true) < 0.03


def brute_next(rows):
    order = sorted(range(len(rows)), key=lambda k: (rows[k][0] is None, -(rows[k][0] or 0), (rows[k][1] or "").encode()))
    for at, k in enumerate(order):
        t, f = rows[k][1] or "", rows[order[(at + 1) % len(order)]][1] or ""
        n = len(t) // 3
        yield rows[k][0], len(t), hashlib.sha256((t[: len(t) - n] + f[:n]).encode()).hexdigest()


@pytest.mark.parametrize("parts", [1, 4])
def test_edited_neighbours(spark, docs, rows, parts):
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", parts)
    try:
        got = fingerprints.edited_neighbours(docs).toPandas()
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
    fix = lambda v: None if v != v else int(v)
    assert sorted(map(str, ((fix(a), b, c) for a, b, c in got[["doc_id", "n_chars", "edited_sha256"]].itertuples(index=False)))) == sorted(map(str, brute_next(rows)))
    by = got.set_index("doc_id")
    assert by.fingerprint[7] == by.fingerprint[8] and by.fingerprint[2] == "" and got.near_edited.between(0, 1).all() and got.near_next.between(0, 1).all()
    assert by.near_next[9] == 1.0  # the next smaller id has the same text


def test_fingerprints_do_not_depend_on_the_batch(docs):
    a = {r[0]: r[1] for r in fingerprints.fingerprint(docs).collect()}
    b = {r[0]: r[1] for r in fingerprints.fingerprint(docs.repartition(11)).collect()}
    assert a == b


LICENCE_TEXTS = [
    "", "The MIT License", "Under the MIT License under the under the mit license, the MIT-license", "apache license version 2 apache license version 2.0", "CC BY-NC 4.0 cc by nc",
    "Licensed under CC BY-NC 4.0.", "This work is licensed under the GNU General Public License, version 3.", "under the mit licensed", "under the mité license",
    "permission is hereby granted free of charge to any person", None, "released under the MIT license\n\n(under-the-mit-license)", "a b Released under the MIT License.",
]
#: The phrases as the query's contract states them, written out apart from the operator's table.
BASE_PHRASES = (("under the mit license", "mit"), ("apache license version 2", "apache-2"), ("cc by nc", "cc-by-nc"))


def test_license_places(spark):
    got = licenses.scan(spark.createDataFrame(list(enumerate(LICENCE_TEXTS)), "doc_id bigint, text string")).toPandas().set_index("doc_id")
    for i, t in enumerate(LICENCE_TEXTS):
        w = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").translate({c: c + 32 for c in range(65, 91)}))
        places = [(k, label) for p, label in BASE_PHRASES for k in range(len(w)) if w[k : k + len(p.split())] == p.split()]
        assert got.n_words[i] == len(w) and got.n_base[i] == len(places)
        assert got.base_labels[i] == ",".join(sorted({x for _, x in places}))
        assert (got.first_word[i], got.last_word[i]) == (min(places)[0], max(places)[0]) if places else pd.isna(got.first_word[i])
        assert set(got.base_labels[i].split(",")) <= set(got.labels[i].split(",")) | {""}
    assert got.labels[6] == "gpl-3" and got.score[6] == 1.0 and got.labels[8] == "" and got.score[0] == 0.0


def test_license_copies_and_tails():
    w = [f"w{chr(97 + k // 26)}{chr(97 + k % 26)}" for k in range(60)]
    scanner = licenses.Scanner((("x", " ".join(w)),), ())
    spans = lambda words: [(s["start"], s["end"]) for s in scanner.digest(" ".join(words).encode())["spans"]]
    assert spans([*w, *w]) == [(0, 60), (60, 120)]
    edited = [x if k % 20 != 10 else "zz" for k, x in enumerate(w)]
    assert spans([*w[30:], "zz", *edited]) == [(31, 91)]
    assert spans([*edited, "zz", *edited]) == [(0, 60), (61, 121)]


def test_automaton_gives_matching_statistics():
    rng = np.random.default_rng(2)
    vocabulary = [b"%d" % x for x in range(4)]
    templates = [list(rng.integers(0, 4, 12)) for _ in range(5)]
    a = licenses.Automaton()
    for k, t in enumerate(templates):
        a.add([int(x) for x in t], k)
    a.finish()
    text = [int(x) for x in rng.integers(0, 4, 300)]
    have = {tuple(t[i:j]) for t in templates for i in range(12) for j in range(i + 1, 13)}
    state = n = 0
    for i, c in enumerate(text):
        while state and c not in a.step[state]:
            state = a.link[state]
            n = a.length[state]
        if c in a.step[state]:
            state = a.step[state][c]
            n += 1
        longest = next((m for m in range(min(12, i + 1), 0, -1) if tuple(text[i + 1 - m : i + 1]) in have), 0)
        assert n == longest
        if n:
            seen = {(k, j) for k, t in enumerate(templates) for j in range(n, 13) if list(t[j - n : j]) == text[i + 1 - n : i + 1]}
            assert seen <= a.ends[state]
    del vocabulary


def test_targets():
    assert mixing.targets([100, 100, 100], [5, 2, 1]) == pytest.approx([200, 500 / 3, 250 / 3])
    assert sum(mixing.targets([10, 1000, 5, 0], [5, 2, 1, 5])) == pytest.approx(1.5 * 1015)
    assert mixing.targets([], []) == []


def test_permutation_is_a_bijection():
    for n in (1, 2, 3, 17, 1000):
        x = mixing.permuted(np.arange(n), np.full(n, n), np.full(n, 99, np.uint64))
        assert sorted(x) == list(range(n))


def test_splitting_tree_is_exact():
    tree = mixing.Tree((100, 7, 0, 33), 9, 3)
    table = tree.table()
    assert (table.sum(axis=0) == [100, 7, 0, 33]).all() and np.ptp(table.sum(axis=1)) <= 1
    for s, q in enumerate(tree.quotas):
        assert (np.bincount([tree.shard(s, k) for k in range(q)], minlength=9) == table[:, s]).all()


def test_mixture(spark, docs, rows):
    got = mixing.mixture(docs, block_rows=2, shards=3).toPandas()
    sizes = pd.DataFrame([(r[3] or "~", len(WORD.findall(r[1] or ""))) for r in rows], columns=["s", "n"]).groupby("s").n.sum()
    want = mixing.targets([int(sizes[s]) for s in ("a", "b", "~")], [5, 2, 1])
    got["taken"] = [sum(d["words"] for d in x) for x in got.draws]
    assert (got.taken <= 2 * got["size"]).all()
    by = got.groupby("source_size").agg(t=("target", "max"), k=("taken", "sum"))
    assert sorted(by.t) == pytest.approx(sorted(want))
    assert (by.t - by.k).abs().max() <= got["size"].max()
    again = mixing.mixture(docs.repartition(5), block_rows=2, shards=3).toPandas()
    key = lambda x: sorted(zip(x.doc_id.astype(str), x["size"], map(str, x.draws)))
    assert key(got) == key(again)
    out = mixing.mix(docs, block_rows=2, shards=3)
    assert out.columns == docs.columns
    assert sum(len(WORD.findall(r["text"] or "")) for r in out.select("text").collect()) == pytest.approx(got.taken.sum(), abs=2)


@pytest.mark.parametrize("layout", [1, 6])
def test_mixture_of_repeated_rows(spark, layout):
    """1000 equal rows in one source: the target is met to the words of a row, and reruns agree."""
    rows = [(7, " ".join("abcdefghij"), "a")] * 1000 + [(k, f"own text {k}", "b") for k in range(30)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, source string").repartition(layout)
    got = mixing.mixture(df, block_rows=16).toPandas()
    got["taken"] = [sum(d["words"] for d in x) for x in got.draws]
    by = got.groupby("source_size").agg(t=("target", "max"), k=("taken", "sum"))
    assert (by.t - by.k).abs().max() <= 1 and (got.taken <= 2 * got["size"]).all()
    assert ((got.taken % 10 > 0) & (got.source_size == 10_000)).sum() <= 1  # one copy at most is cut
    shards = pd.DataFrame([(d["shard"]) for x in got.draws[got.source_size == 10_000] for d in x])[0]
    assert shards.nunique() > 1  # copies are dealt into blocks like other rows
    once = mixing.mixture(df.repartition(3), block_rows=16).toPandas()
    key = lambda x: sorted(zip(x.doc_id, map(str, x.draws)))
    assert key(got) == key(once)
    out = mixing.mix(df, block_rows=16)
    words = {r["source"]: r["n"] for r in out.groupBy("source").agg(F.sum(F.size(F.split("text", " "))).alias("n")).collect()}
    assert words == {"a": by.k[10_000], "b": by.k[90]}


def test_tree_remembers_a_bounded_number_of_nodes(monkeypatch):
    want = mixing.Tree((4000, 900, 33), 200, 3).table()
    monkeypatch.setattr(mixing, "MEMO_BYTES", 24 * 16)
    tree = mixing.Tree((4000, 900, 33), 200, 3)
    assert all(want[tree.shard(0, k)][0] for k in range(0, 4000, 37)) and len(tree.made) < 16
    assert (tree.table() == want).all()


def brute_quality(t):
    t = t or ""
    w = WORD.findall(t)
    grams = {}
    for i in range(len(w) - 4):
        grams.setdefault(tuple(w[i : i + 5]), []).append(i)
    rep = {i + j for g in grams.values() if len(g) > 1 for i in g for j in range(5)}
    lines = [x for x in t.split("\n") if WORD.search(x)]
    return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t), len(lines) - len(set(lines)), len(rep)


def test_quality(docs, rows):
    names = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
    got = quality.judge(docs, quality.order_rules(docs), report=names)
    assert sorted(map(str, ((r[0], *r[1:6]) for r in got.collect()))) == sorted(str((r[0], *brute_quality(r[1]))) for r in rows)


def test_cascade_order_moves_cost_not_verdicts():
    rng = np.random.default_rng(4)
    texts = [prose(rng, int(n)).encode() for n in rng.integers(0, 60, 80)] + [b"# $ % & a b c d e f g h" * 3]
    a, _, looked = quality.cascade(texts, quality.RULES)
    b, _, other = quality.cascade(texts, quality.RULES[::-1])
    assert (a == b).all() and looked[0] == other[0] == len(texts) and looked[-1] < len(texts)
    found = quality.trial(texts)
    rates = [found[i][1] / found[i][0] for i in quality.best_first(found)]
    assert rates == sorted(rates, reverse=True) and quality.best_first([(1.0, 2), (1.0, 9), (0.1, 2)]) == [2, 1, 0]
    m = quality.Measures(texts)
    m.get("n_repeat_words")
    assert (quality.cascade(texts, quality.RULES, m)[0] == a).all()


def brute_substrings(rows, least=20):
    first, order = {}, sorted({(r[0] if r[0] is not None else -(10**9), r[1] or "") for r in rows})
    out = {}
    for i, t in order:
        w = WORD.findall(t)
        for p in range(len(w) - least + 1):
            first.setdefault(tuple(w[p : p + least]), (i, p))
    for i, t in order:
        w = WORD.findall(t)
        gone = {p + k for p in range(len(w) - least + 1) if first[tuple(w[p : p + least])] != (i, p) for k in range(least)}
        kept = " ".join(x for k, x in enumerate(w) if k not in gone)
        out[i, t] = (len(w), len(gone), kept)
    return sorted(str((r[0], *out[r[0] if r[0] is not None else -(10**9), r[1] or ""])) for r in rows)


def test_substrings(docs, rows):
    got = substrings.dedup_substrings(docs).drop("factors")
    assert sorted(str(tuple(r)) for r in got.collect()) == brute_substrings(rows)


@pytest.mark.parametrize("batch", ["7", "10000"])
def test_substrings_random(spark, batch):
    """Heavy overlap over small batches: shared passages cut at random places."""
    rng = np.random.default_rng(8)
    pool = [f"v{k}" for k in range(400)]
    rows = []
    for i in range(120):
        w = []
        for _ in range(rng.integers(1, 5)):
            a = int(rng.integers(0, 360))
            w += pool[a : a + int(rng.integers(5, 60))] if rng.random() < 0.7 else [f"u{x}" for x in rng.integers(0, 10**9, 12)]
        rows.append((i, " ".join(w)))
    before = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", batch)
    try:
        got = substrings.dedup_substrings(spark.createDataFrame(rows, "doc_id bigint, text string").repartition(5)).drop("factors").collect()
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", before)
    assert sorted(str(tuple(r)) for r in got) == brute_substrings(rows)


def test_substrings_edit_beside_an_earlier_batch(spark):
    """T, then in another batch an edited T and T again: windows beside the edit repeat the first T."""
    rng = np.random.default_rng(21)
    early, late, orders = [], [], set()
    for i in range(0, 1200, 100):
        t = [f"e{x}" for x in rng.integers(0, 10**9, 60)]
        edited = [*t[:30], f"n{i}", *t[31:]]
        early.append((i + 5, " ".join(t)))
        late += [(i + 7, " ".join(edited)), (i + 10, " ".join(t))]
        found = [list(zip(*(x.tolist() for x in substrings.runs(*word_hashes([" ".join(w).encode()], (0, 1)))[3:5]))) for w in (edited, t)]
        orders |= {np.int64(np.uint64(c).view(np.int64)) < np.uint64(d).view(np.int64) for a, c in found[0] for b, d in found[1] if a == b and c != d}
    assert orders == {True, False}  # either content may be the one that an anchor is told of
    parts = spark.sparkContext.parallelize(early, 1).union(spark.sparkContext.parallelize(late, 1))
    got = substrings.dedup_substrings(spark.createDataFrame(parts, "doc_id bigint, text string")).drop("factors").collect()
    assert sorted(str(tuple(r)) for r in got) == brute_substrings(early + late)


def test_a_marked_entry_opens_its_group_across_batches():
    place = lambda start, flag=0: int(substrings.pack(np.array([start]), np.array([3]), flag)[0])
    rows = [(1, 4, 4, 5, 0, place(0), 0, 0), (1, 4, 4, 6, 0, place(0), 0, 0), (1, 4, 4, 7, 0, place(0, 2), 0, 0), (2, 9, 9, 5, 0, place(9), 0, 0), (2, 9, 9, 8, 0, place(9), 0, 0)]
    for size in range(1, 6):
        cut = [pa.RecordBatch.from_pylist([dict(zip(substrings._NAMES, r)) for r in rows[a : a + size]]) for a in range(0, len(rows), size)]
        out = sorted((r["key"], r["doc"], r["place"] & 3, r["ref_doc"]) for b in substrings._match(iter(cut)) for r in b.to_pylist())
        assert out == [(1, 5, 2, 0), (1, 6, 1, 5), (1, 7, 1, 5), (2, 8, 1, 5)]


def test_factors_are_longest_copies(spark):
    rng = np.random.default_rng(9)
    source = [f"s{x}" for x in rng.integers(0, 10**9, 200)]
    target = [f"t{x}" for x in rng.integers(0, 10**9, 30)] + source[50:120] + ["gap"] + source[130:155] + source[10:45]
    out = substrings.dedup_substrings(spark.createDataFrame([(1, " ".join(source)), (2, " ".join(target))], "doc_id bigint, text string")).collect()
    by = {r["doc_id"]: [tuple(f) for f in r["factors"]] for r in out}
    assert by == {1: [], 2: [(30, 70, 1, 50), (101, 25, 1, 130), (126, 35, 1, 10)]}


def test_parse_is_greedy_and_borders_are_checked():
    """Factors reach as far as any match from their start; with border windows they cover all matches."""
    rng = np.random.default_rng(0)
    for _ in range(300):
        n, k = int(rng.integers(25, 120)), int(rng.integers(1, 8))
        start, width = rng.integers(0, n - 24, k), rng.integers(1, 5, k)
        doc, ref = rng.integers(0, 2, k), rng.integers(0, 3, k) + start
        place = substrings.pack(start, width, 1)
        factors = substrings.parse(place, doc, ref)
        want = np.zeros(n, bool)
        for s, w in zip(start, width):
            want[s : s + w + 19] = True
        assert (substrings.spans(n, place, factors) == want).all()
        at = 0
        for s, words, d, r in factors:
            own = {(i, j) for a, w, x, y in zip(start, width, doc, ref) if x == d and y - a == r - s for i in range(a, a + w + 19) for j in [i]}
            assert s >= at and words >= 20 and all((i, i) in own for i in range(s, s + words)) and (s + words, s + words) not in own
            at = s + words


def thue_morse(n, a="a", b="b"):
    return "".join((a, b)[bin(i).count("1") & 1] for i in range(n))


def test_structured_words_have_their_own_hashes():
    """Thue-Morse words and their complements share every polynomial hash modulo 2**64."""
    for n in (1024, 2048, 4096, 100_000):
        x, y = (thue_morse(n, *ab).encode() for ab in ("ab", "ba"))
        h, counts = word_hashes([x, y, x + b" " + y], (0, 1))
        assert counts.tolist() == [1, 1, 2]
        assert all(lane[0] == lane[2] and lane[1] == lane[3] and lane[0] != lane[1] for lane in h)
    words = [thue_morse(1 << k, "p", "q") for k in range(11)]
    seq = [list(w) for w in (thue_morse(2048), thue_morse(2048, "b", "a"))]
    grams = [ngrams(word_hashes([" ".join(s).encode()])[0], 2048)[0] for s in seq]
    assert grams[0] != grams[1] and len(set(word_hashes([" ".join(words).encode()])[0].tolist())) == len(words)


def test_structured_words_lose_nothing(spark):
    rows = [(k + 1, " ".join([*(f"w{i}" for i in range(19)), thue_morse(1024, *ab)])) for k, ab in enumerate(("ab", "ba"))]
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    got = substrings.dedup_substrings(df).drop("factors")
    assert sorted(str(tuple(r)) for r in got.collect()) == brute_substrings(rows) and {r["n_removed"] for r in got.collect()} == {0}
    assert {r["n_shingles"] for r in neardup.near_duplicates(df, words=2).collect()} == {19}


def tiny_codec():
    ranks = {bytes([b]): b for b in range(256)}
    for k, w in enumerate([b"ab", b"abab", b"ba", b"aab", b"bb", b"abb", b"abababab"]):
        ranks[w] = 256 + k
    return bpe.Codec(ranks, r"\S+|\s+")


def test_bpe_against_the_library():
    tiktoken = pytest.importorskip("tiktoken")
    import public_tokenizers as P

    path = P.path("byte_bpe_multi_50k.tiktoken")
    with open(path, "rb") as f:
        ranks = bpe.read_ranks(f.read())
    theirs = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    ours = bpe.codec(path, P.PATTERN)
    rng = np.random.default_rng(0)
    texts = ["", " ", "\n\n  x", "don't  stop", "a" * 3000, " x y　", "a\x1cb\x1d", "漢字かな交じり文" * 50, "🙂🙃" * 40, "x" + "é" * 999, "".join(map(chr, rng.integers(32, 0x2FFF, 3000)))]
    texts += ["".join(rng.choice(list("ab\n é1"), int(n))) for n in rng.integers(1, 400, 60)]
    for t in texts:
        ids = ours.encode(t)
        assert ids == theirs.encode_ordinary(t)
        assert ours.decode(ids) == t.encode()


def test_bpe_merges_lowest_rank_leftmost(monkeypatch):
    c = tiny_codec()

    def slow(b):
        parts = [b[i : i + 1] for i in range(len(b))]
        while len(parts) > 1:
            r = [c.ranks.get(x + y, 10**9) for x, y in zip(parts, parts[1:])]
            i = int(np.argmin(r))
            if r[i] == 10**9:
                break
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
        return [c.ranks[p] for p in parts]

    rng = np.random.default_rng(1)
    for n in rng.integers(1, 200, 200):
        b = bytes(rng.choice([97, 98], int(n)))
        assert c.encode(b.decode()) == ([c.ranks[b]] if b in c.ranks else slow(b))
    assert not any(c.queue.words) and not c.queue.buckets
    # Many pre-tokens in one layout, in layouts of a few, and each alone where no byte can be a wall.
    pieces = [bytes(rng.choice([97, 98], int(n))) for n in rng.integers(1, 60, 400)]
    want = [np.array([c.ranks[b]] if b in c.ranks else slow(b), "<i4").tobytes() for b in pieces]
    assert c.pieces(pieces) == want
    for room, wall in ((40, c.wall), (1 << 14, b"")):
        monkeypatch.setattr(bpe, "LAYOUT", room)
        c.wall = wall
        assert c.pieces(pieces) == want
    assert c.encode_all(["ab ba", "", "abab  b"]) == [np.array(c.encode(t), "<i4").tobytes() for t in ("ab ba", "", "abab  b")]
    assert not any(c.queue.words) and not c.queue.buckets


def test_bpe_remembers_two_generations(monkeypatch):
    monkeypatch.setattr(bpe, "REMEMBERED", 5)
    c = tiny_codec()
    text = " ".join(["ab" * k for k in range(1, 30)])
    want = tiny_codec().encode(text)
    assert c.encode(text) == want and c.encode(text) == want and len(c.known) <= 5 and len(c.known.older) <= 6


def test_bpe_tables(spark, docs, rows):
    import public_tokenizers as P

    path = P.path("byte_bpe_multi_50k.tiktoken")
    out = bpe.decode(bpe.encode(docs, path, P.PATTERN), path, P.PATTERN).collect()
    assert sorted(str((r[0], bytes(r[1]).decode())) for r in out) == sorted(str((r[0], r[1] or "")) for r in rows)
    assert base64.b64decode(b"YQ==") == b"a"


def test_sharding(docs, rows):
    for shards in (3, 7, 40):
        got = sharding.shard_documents(docs, shards).toPandas()
        sizes = np.bincount(got.shard, minlength=shards)
        assert len(got) == len(rows) and np.ptp(sizes) <= 1
        for s in range(shards):
            assert sorted(got.slot[got.shard == s]) == list(range(sizes[s]))
        want = sorted(str((r[0], len((r[1] or "").encode()) + 16, zlib.crc32((r[1] or "").encode()))) for r in rows)
        fix = lambda v: None if v != v else int(v)
        assert sorted(str((fix(a), b, c)) for a, b, c in got[["doc_id", "size", "text_crc32"]].itertuples(index=False)) == want


def test_sharding_keeps_groups_together(spark):
    rows = [(i, f"text {i % 150}" if i < 450 else f"own {i}") for i in range(900)] + [(1000 + i, "hot") for i in range(450)]
    got = sharding.shard_documents(spark.createDataFrame(rows, "doc_id bigint, text string"), 10).toPandas()
    assert set(np.bincount(got.shard)) == {135}
    group = dict(rows)
    got["text"] = got.doc_id.map(group)
    spread = got.groupby("text").shard.nunique()
    assert spread["hot"] <= 9
    small = spread[[t for t in spread.index if t.startswith("text")]]
    assert (small == 1).mean() > 0.8


def test_propagation_cuts_fewer_links(spark):
    rows = [(f"g{i % 40}", i // 40, 1) for i in range(320)]
    cells = spark.createDataFrame(rows, "group string, start int, n bigint")
    _, cut = sharding.propagate(cells.selectExpr("cast(group as binary) as group", "start", "n"), 8, 60)
    assert cut[0] > 0 and cut[-1] < cut[0] / 4


def test_toxicity_held_out(spark):
    docs, labels = spark.read.parquet("/root/testdata/sf0.1/documents.parquet"), spark.read.parquet("/root/testdata/sf0.1/labels.parquet")
    grammar = toxicity.learn(docs, labels)
    truth = labels.filter(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0)
    got = toxicity.score(docs.join(truth.select("doc_id"), "doc_id", "left_semi"), grammar).join(truth, "doc_id").toPandas()
    hit = (got.score >= 0.5) == (got.toxic == 1)
    assert hit.mean() > 0.97 and hit[got.toxic == 1].mean() > 0.85 and hit[got.toxic == 0].mean() > 0.98


def test_toxicity_rows(spark, docs, none):
    grammar = toxicity.Grammar({b"moron": 5.0}, {}, bias=-4.0)
    got = {r[0]: r[1] for r in toxicity.score(docs, grammar).collect()}
    assert got[1] == got[2] and all(0 <= x <= 1 for x in got.values())
    blank = toxicity.learn(docs, spark.createDataFrame([], "doc_id bigint, quality int, toxic int"))
    assert toxicity.score(docs, blank).count() == docs.count()
    assert toxicity.score(none, grammar).count() == 0
    assert toxicity.learn(none, spark.createDataFrame([(1, 3, 1)], "doc_id bigint, quality int, toxic int")).score(b"x") < 0.5


def test_toxicity_learns_from_whole_texts(spark):
    long = lambda w: "fine day here. " * 14_000 + f"You {w}."
    rows = [(i, long("zorgle" if i % 2 else "friend")) for i in range(60)]
    labels = spark.createDataFrame([(i, 3, i % 2) for i, _ in rows], "doc_id bigint, quality int, toxic int")
    grammar = toxicity.learn(spark.createDataFrame(rows, "doc_id bigint, text string"), labels)
    assert b"zorgle" in grammar.words and grammar.score(long("zorgle").encode()) > 0.5 > grammar.score(long("friend").encode())


def test_toxicity_lexicon_is_counted_right(spark):
    """The distributed counts against a count in one place, for both folds and all texts."""
    rng = np.random.default_rng(12)
    words = [f"{x}{y}" for x in ("grumb", "wobble", "tree") for y in ("le", "ly", "ling", "ed", "ish")]
    rows = [(int(k % 2), int(k % 3 == 0), " ".join(rng.choice(words[: 15 if k % 3 == 0 else 5], 6)) + " common. word") for k in range(240)]
    texts = spark.createDataFrame(rows, "fold int, toxic int, text string").repartition(3)
    many = {(f, y): sum(r[:2] == (f, y) for r in rows) for f in (0, 1) for y in (0, 1)}
    got = toxicity._lexicons(texts, many)
    for fold in range(3):
        own = [({w for c in toxicity.clauses(t.encode()) for w in c}, y) for f, y, t in rows if fold == 2 or f == fold]
        count = lambda item, y: sum(y == label and any(item(w) for w in ws) for ws, label in own)  # noqa: E731, B023
        n1, n0 = sum(y for _, y in own), sum(not y for _, y in own)
        known = {w for ws, y in own for w in ws}
        odds = lambda item: np.log((count(item, 1) + 0.5) / (n1 + 1)) - np.log((count(item, 0) + 0.5) / (n0 + 1))  # noqa: E731, B023
        want_words = {w: odds(lambda x: x == w) for w in known if count(lambda x: x == w, 1) >= 4 and odds(lambda x: x == w) >= 3}  # noqa: B023
        stems = {w[:n] for w in known for n in toxicity.STEM if n < len(w)}
        begins = lambda s: lambda x: x.startswith(s) and len(x) > len(s)
        forms = lambda s: len({w for ws, y in own if y for w in ws if begins(s)(w)})  # noqa: E731, B023
        want_stems = {s: odds(begins(s)) for s in stems if count(begins(s), 1) >= 4 and odds(begins(s)) >= 3 and forms(s) >= 3}
        assert got[fold][0] == pytest.approx(want_words) and got[fold][1] == pytest.approx(want_stems)
    assert got[2][0] and got[2][1]


def brute_patterns(classes):
    """Labels of every attack in a clause, from the words of the rules alone."""
    t = toxicity
    out = []
    for i, c in enumerate(classes):
        if c in t.ATTACKS:
            labels = t.NEGATED * any(x == t.NOT for x in classes[max(0, i - 3) : i]) | t.TOLD * (t.REPORT in classes[:i])
            out.append((i, labels | {t.THREAT: t.THREATENED, t.VERB: t.BARE}.get(c, 0) | t.AIMED * (t.TARGET in classes)))
    return out


def test_patterns_against_every_short_clause():
    """All clauses of up to five classes, and random longer ones, against the rules in words."""
    import itertools

    words = [b"other", b"you", b"not", b"said", b"moron", b"kill", b"stab"]
    g = toxicity.Grammar({b"moron": 3.0, b"kill": 5.0}, {})
    assert [g.symbol(w)[0] for w in words] == list(toxicity.CLASSES)
    rng = np.random.default_rng(0)
    longer = [tuple(rng.integers(0, 7, rng.integers(6, 15)).tolist()) for _ in range(2000)]
    for classes in itertools.chain(*(itertools.product(toxicity.CLASSES, repeat=n) for n in range(1, 6)), longer):
        want = {}
        for i, labels in brute_patterns(classes):
            if not labels & toxicity.BARE or labels & toxicity.AIMED:
                want[labels] = want.get(labels, 0) + {4: 3.0, 5: 5.0, 6: toxicity.THREAT_WEIGHT}[classes[i]]
        assert g.clause([words[c] for c in classes]) == want


def test_composition_unites_what_the_parts_write():
    t = toxicity
    rng = np.random.default_rng(0)
    for _ in range(200):
        word = rng.integers(0, 7, rng.integers(0, 12)).tolist()

        def walk(m):
            q, labels = 0, []
            for c in word:  # noqa: B023
                q, f = m.step[q][c]
                labels.append(f)
            return np.array(labels, int), m.final[q]

        parts = [walk(m) for m in (t.NEGATION, t.REPORTED, t.AIM, t.THREATENING)]
        whole = walk(t.CLAUSE)
        assert (whole[0] == np.bitwise_or.reduce([p[0] for p in parts])).all() and whole[1] == np.bitwise_or.reduce([p[1] for p in parts])


def test_clauses_decide_and_not_words():
    """One insult, four clauses: the pattern moves the score over the line, and without the machine it does not."""
    g = toxicity.Grammar({b"moron": 5.0}, {}, bias=-4.5)
    for text, toxic in ((b"You moron.", True), (b"They are not a moron.", False), (b"She said moron.", False), (b"I will kill you.", True), (b"Kill the process.", False), (b"moral", False)):
        assert (g.score(text) >= 0.5) == toxic, text
    plain = toxicity.Grammar({b"moron": 5.0}, {}, bias=-4.5, machine=toxicity.transducer(1, lambda q, c: (0, 0)))
    assert plain.score(b"They are not a moron.") >= 0.5
    many = b"They are not a moron. " * 400
    assert g.score(many) > g.score(b"They are not a moron.")  # every clause counts


def test_pattern_weights_follow_the_labels():
    """Negated insults that are labelled clean lose their weight; a pattern never seen stays near its prior."""
    rng = np.random.default_rng(3)
    n = 400
    x = np.zeros((n, toxicity.PATTERNS))
    y = (np.arange(n) % 2).astype(float)
    x[y == 1, toxicity.AIMED] = 5 + rng.random(n // 2)
    x[y == 0, toxicity.AIMED | toxicity.NEGATED] = 5 + rng.random(n // 2)
    weights, bias = toxicity.weigh(x, y)
    assert weights[toxicity.AIMED | toxicity.NEGATED] < 0.5 * weights[toxicity.AIMED] and bias < 0
    scale = weights[toxicity.TOLD] / toxicity.prior(toxicity.TOLD)
    assert weights[toxicity.TOLD | toxicity.NEGATED] == pytest.approx(scale * toxicity.prior(toxicity.TOLD | toxicity.NEGATED))


@pytest.mark.parametrize("s", ["", "<|im_end|>", "<\\|", "<\\\\|x<|", "a<", "\\", "\n", "<|im_end|><|im_start|>assistant ok"])
def test_escapes(s):
    assert chat.unescape(chat.escape(s)) == s and "<|" not in chat.escape(s) and chat.unescape_role(chat.escape_role(s)) == s and "\n" not in chat.escape_role(s)


def test_chat_round_trip():
    turns = [("user", "<|im_end|>\n<|im_start|>assistant\nhi<"), ("assistant", "<\\|ok|>\n"), ("assistant", ""), ("we\nird<|", "x")]
    text, spans = chat.render(turns)
    assert chat.parse(text) == turns and [chat.unescape(text[a:b]) for a, b in spans] == ["<\\|ok|>\n", ""]


def test_chat_trees(spark):
    rows = [
        ("t", 1, None, 1.0, "user", "q", 0), ("t", 2, 1, 5.0, "assistant", "good", 0), ("t", 3, 1, 1.0, "assistant", "bad", 0), ("t", 4, 3, 2.0, "user", "more", 0),
        ("t", 5, 2, None, "user", None, 0), ("u", 1, 9, 0.0, None, "lost parent", 0), (None, 1, None, 0.0, "assistant", "null tree", 0), ("c", 1, 2, 0.0, "user", "loop", 0), ("c", 2, 1, 0.0, "user", "loop", 0),
    ]
    got = chat.format_trees(spark.createDataFrame(rows, "tree_id string, node_id int, parent_id int, score double, role string, text string, turns int")).toPandas()
    by = {r.tree_id: chat.parse(r.formatted) for r in got.itertuples()}
    assert by == {"t": [("user", "q"), ("assistant", "good"), ("user", "")], "u": [("", "lost parent")], None: [("assistant", "null tree")]}


def test_deep_chain(spark):
    rows = [(1, k, k - 1 if k else None, 0.0, "user" if k % 2 == 0 else "assistant", f"t{k}") for k in range(75)]
    got = chat.format_trees(spark.createDataFrame(rows, "tree_id bigint, node_id bigint, parent_id bigint, score double, role string, text string")).first()
    assert [t for _, t in chat.parse(got["formatted"])] == [f"t{k}" for k in range(75)]


def test_rules_are_ordered_on_whole_texts_of_any_part(spark):
    """Rows that are rejected stand at the end of the table, and the fault at the end of a text."""
    rows = [(i, "a fine and plain text of more than ten words, all told, " + ("" if i < 300 else "x " * 20_000 + "# $ % & " * 9000)) for i in range(400)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string").repartitionByRange(8, "doc_id")
    rules = tuple(r for r in quality.RULES if r.name in ("few_words", "symbols"))
    assert [r.name for r in quality.order_rules(df, rules=rules)] == ["symbols", "few_words"]


def test_clashing_columns(spark, docs, none):
    """Columns with the names that operators use inside, in other letters too."""
    import public_tokenizers as P

    path = P.path("byte_bpe_multi_50k.tiktoken")
    odd = {n: F.lit(7) for n in ("TEXT_", "_text", "__text", "id", "_id", "__id", "ids", "__ids", "SRC", "h", "shard_", "place", "Doc", "tag", "copies", "part", "row", "at", "before", "k", "n", "root")}
    df = docs.withColumns(odd)
    grammar = toxicity.Grammar({b"moron": 5.0}, {}, bias=-4.0)
    keep = ("doc_id", "text", "_text", "__text", "ids", "__ids")
    n = docs.count()
    made = [
        licenses.scan(df, keep=keep), fingerprints.fingerprint(df, keep=keep), quality.judge(df, quality.RULES, keep=keep, report=("n_words",)), toxicity.score(df, grammar, keep=keep),
        bpe.decode(bpe.encode(df, path, P.PATTERN, keep=keep, ids="codes"), path, P.PATTERN, ids="codes"), mixing.mixture(df), sharding.shard_documents(df), neardup.near_duplicates(df), substrings.dedup_substrings(df), fingerprints.edited_neighbours(df),
    ]
    assert [x.count() for x in made] == [n] * len(made)
    for f in (neardup.drop_near_duplicates, substrings.strip_substrings, mixing.mix, lambda d: quality.passing(d, quality.order_rules(d))):
        out = f(df)
        assert out.columns == df.columns and 0 < out.count() <= 2 * n
        empty = f(none.withColumns(odd))
        assert empty.columns == df.columns and empty.count() == 0


def test_empty_tables(spark, none):
    import public_tokenizers as P

    path = P.path("byte_bpe_multi_50k.tiktoken")
    made = [neardup.near_duplicates(none), neardup.drop_near_duplicates(none), fingerprints.edited_neighbours(none), licenses.scan(none), mixing.mixture(none), mixing.mix(none), quality.judge(none, quality.order_rules(none)), substrings.dedup_substrings(none), substrings.strip_substrings(none), bpe.encode(none, path, P.PATTERN), sharding.shard_documents(none)]
    assert [df.count() for df in made] == [0] * len(made)
    nodes = spark.createDataFrame([], "tree_id bigint, node_id bigint, parent_id bigint, score double, role string, text string")
    assert chat.read_back(chat.format_trees(nodes)).count() == 0
