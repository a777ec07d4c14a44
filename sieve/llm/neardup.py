"""Near-duplicates: one-permutation MinHash, banded buckets, star-shaped candidates.

1. One pass hashes every text to its shingle set, a 128-bit key of the set, and the
   band hashes of its densified one-permutation sketch. Equal sets collapse to one
   key, so copies cost one aggregation whatever their number. A node stands for a set:
   the least id that has it, then the key, so that the least node of a component
   begins with the component's id.
2. Every bucket (band, value) with two sets or more gets two centres, the least and
   greatest key in it. Candidates are the star edges from members to centres: at
   most two an entry, never all pairs.
3. Star edges are confirmed on the full shingle sets and joined into components.
4. What the stars leave open is settled exactly. Sets of a bucket that still holds more
   than one component are parted by size (similar sets are of neighbouring sizes), then
   into blocks of bounded rows and shingles; blocks are compared pairwise on full sets,
   only between components. A part of more than SPLIT blocks is not compared as a whole:
   its sets are first dealt out by their rarer shingles, of which similar sets share one
   at least. Links found there are added.

With R rows in each of B bands a pair of similarity s shares a bucket with
probability 1 - (1 - s**R)**B: more than 0.9999999 at 0.8 for the defaults, so the
components are those of all links, up to that chance. Sets too small to be similar to
any other set (of fewer than 4 shingles at 80 %) are left out of the buckets.

Cases: ids are whole numbers (other types are refused); null, empty and wordless texts have no shingle, link with nothing and are
kept; a text of fewer words than a shingle is one shingle; rows with a null id take
no part in links and are kept; repeated rows are copies of each other; an empty
table gives an empty table; other columns are not read.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from sieve.llm.components import components
from sieve.llm.fingerprints import sketch
from sieve.llm.text import as_bytes, fresh, lists, mix, shingles, signed, slices, starts, whole, word_hashes
from sieve.plans.scratch import materialize

#: Bands and rows of a band (their product is the number of bins), words in a shingle, percent.
BANDS, ROWS, WORDS, PERCENT = 32, 4, 5, 80
#: Shingles and sets of one block of the exact comparison, and blocks that are compared pairwise.
BLOCK, BLOCK_SETS, SPLIT = 250_000, 1024, 8
#: A shingle is frequent in a part where more than one set in so many has it.
FREQUENT = 64
_SIGN = -(1 << 63)


def node(key: Column, k: Column) -> Column:
    """24 bytes that sort by the id, then by the set's key."""
    return F.concat(F.unhex(F.lpad(F.hex(key.bitwiseXOR(F.lit(_SIGN))), 16, "0")), k)


def id_of(node: Column) -> Column:
    """The id a node begins with."""
    return F.conv(F.hex(F.substring(node, 1, 8)), 16, -10).cast("long").bitwiseXOR(F.lit(_SIGN))


def _set_keys(hashes: np.ndarray, sizes: np.ndarray) -> list[bytes | None]:
    at = starts(sizes)
    return [hashlib.blake2b(hashes[a:b].tobytes(), digest_size=16).digest() if b > a else None for a, b in zip(at[:-1], at[1:], strict=True)]


def band_hashes(bins: np.ndarray, bands: int, rows: int) -> np.ndarray:
    """One 64-bit value for every band of every set, with the band's number mixed in."""
    b = bins.reshape(len(bins), bands, rows)
    h = np.broadcast_to(mix(np.arange(bands, dtype=np.uint64)), (len(bins), bands)).copy()
    for k in range(rows):
        h = mix(h ^ b[:, :, k]) * np.uint64(0x9E3779B97F4A7C15)
    return mix(h)


def features(df: DataFrame, key: str, text: str, words: int, bands: int, rows: int, with_sets: bool = False) -> DataFrame:
    """(doc_id, n, k, bands) of every row, or (doc_id, k, n, shingles) with ``with_sets``."""
    picked = df.select(whole(df, key).alias("doc_id"), F.coalesce(F.col(f"`{text}`"), F.lit("")).alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, 1, 4 << 20):
                hashes, sizes = shingles(*word_hashes(as_bytes(part.column(1), lower=True)), words)
                keys = pa.array(_set_keys(hashes, sizes), pa.binary())
                if with_sets:
                    yield pa.RecordBatch.from_arrays([part.column(0), keys, pa.array(sizes), lists(signed(hashes), sizes)], ["doc_id", "k", "n", "shingles"])
                    continue
                out = []
                for a in range(0, len(sizes), 1024):
                    own = sizes[a : a + 1024]
                    at = int(sizes[:a].sum())
                    out.append(band_hashes(sketch(hashes[at : at + int(own.sum())], own, bands * rows), bands, rows))
                bands_of = lists(signed(np.concatenate(out).reshape(-1)), np.full(len(sizes), bands))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sizes), keys, bands_of], ["doc_id", "n", "k", "bands"])

    return picked.mapInArrow(run, "doc_id bigint, k binary, n bigint, shingles array<bigint>" if with_sets else "doc_id bigint, n bigint, k binary, bands array<bigint>")


def _similar(inter: Column, a: Column, b: Column, percent: int) -> Column:
    return F.lit(100) * inter >= F.lit(percent) * (a + b - inter)


def confirm(edges: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The edges (a, b) whose full sets are similar enough."""
    a = sets.select(F.col("k").alias("a"), F.col("n").alias("na"), F.col("shingles").alias("sa"))
    b = sets.select(F.col("k").alias("b"), F.col("n").alias("nb"), F.col("shingles").alias("sb"))
    both = edges.join(a, "a").join(b, "b")
    return both.filter(_similar(F.size(F.array_intersect("sa", "sb")), F.col("na"), F.col("nb"), percent)).select("a", "b")


def _shared(shingles: np.ndarray, sizes: np.ndarray, few: np.ndarray) -> np.ndarray:
    """Numbers of common shingles of the sets ``few`` with all sets of a cell."""
    rows = len(sizes)
    _, at = np.unique(shingles, return_inverse=True)
    often = np.bincount(at) > 1
    column = np.cumsum(often) - 1
    use = often[at]
    owner, column = np.repeat(np.arange(rows), sizes)[use], column[at[use]]
    order = np.argsort(column, kind="stable")
    owner, column = owner[order], column[order]
    shared = np.zeros((len(few), rows), np.float32)
    wide = max(256, min(8192, (4 << 20) // rows))
    for c in range(0, int(often.sum()), wide):
        a, b = np.searchsorted(column, [c, c + wide])
        m = np.zeros((rows, wide), np.float32)
        m[owner[a:b], column[a:b] - c] = 1
        shared += m[few] @ m.T
    return shared


def cell_links(keys: list[bytes], sizes: np.ndarray, roots: list[bytes], shingles: np.ndarray, percent: int) -> list[tuple[bytes, bytes]]:
    """Links between the components of one cell, on full sets: a spanning forest of them is enough."""
    names = {r: i for i, r in enumerate(sorted(set(roots)))}
    comp = np.array([names[r] for r in roots])
    if len(names) < 2:
        return []
    near = lambda inter, a, b: 100 * inter >= percent * (a + b - inter)
    if len(keys) <= 4:
        at = starts(sizes)
        pairs = [(i, j) for i in range(len(keys)) for j in range(i) if comp[i] != comp[j] and near(min(sizes[i], sizes[j]), sizes[i], sizes[j])]
        found = [(i, j) for i, j in pairs if near(len(np.intersect1d(shingles[at[i] : at[i + 1]], shingles[at[j] : at[j + 1]], True)), sizes[i], sizes[j])]
    else:
        few = np.flatnonzero(comp != np.bincount(comp).argmax())
        inter = _shared(shingles, sizes, few)
        x, y = np.nonzero(near(inter, sizes[few][:, None], sizes[None, :]) & (comp[few][:, None] != comp[None, :]))
        found = zip(few[x], y, strict=True)
    linked: dict[int, int] = {}

    def root(v: int) -> int:
        while linked.get(v, v) != v:
            v = linked[v]
        return v

    out = []
    for i, j in found:
        p, q = root(comp[i]), root(comp[j])
        if p != q:
            linked[p] = q
            out.append((keys[i], keys[j]))
    return out


def _links_of_cells(percent: int):
    """Reads rows (part, i, j, k, root, n, shingles) sorted by cell; holds one cell at a time."""

    def flush(held: list[pa.RecordBatch]) -> list[tuple[bytes, bytes]]:
        cell = pa.Table.from_batches(held)
        first: dict[bytes, int] = {}
        for i, k in enumerate(cell.column("k").to_pylist()):
            first.setdefault(k, i)  # a set may come to a cell by several ways
        if len(first) < len(cell):
            cell = cell.take(list(first.values()))
        values = np.asarray(cell.column("shingles").combine_chunks().flatten())
        return cell_links(list(first), np.asarray(cell.column("n")).astype(np.int64), cell.column("root").to_pylist(), values, percent)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        last = None
        for batch in batches:
            cells = np.stack([np.asarray(batch.column(i)).astype(np.int64) for i in range(3)], 1)
            if not len(cells):
                continue
            cuts = [0, *(np.flatnonzero((cells[1:] != cells[:-1]).any(axis=1)) + 1).tolist(), len(cells)]
            out: list[tuple[bytes, bytes]] = []
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                if held and tuple(cells[a]) != last:
                    out += flush(held)
                    held = []
                held.append(batch.slice(a, b - a))
                last = tuple(cells[a])
            if out:
                yield pa.RecordBatch.from_arrays([pa.array([x[i] for x in out], pa.binary()) for i in range(2)], ["a", "b"])
        out = flush(held) if held else []
        yield pa.RecordBatch.from_arrays([pa.array([x[i] for x in out], pa.binary()) for i in range(2)], ["a", "b"])

    return run


def _parts(rows: DataFrame, percent: int) -> DataFrame:
    """Rows (part, k, n, root, home) of buckets parted by size; a set meets its own class and the next larger.

    Similar sets are at most one class apart. Two parts under one number would be
    compared together, which costs time and changes nothing.
    """
    step = math.log(100 / percent) * 1.000001 if percent < 100 else 1e-9
    rows = rows.withColumn("own", F.floor(F.log("n") / F.lit(step)).cast("long"))
    rows = rows.withColumn("class", F.explode(F.array("own", F.col("own") - 1)))
    return rows.select(F.xxhash64("bucket", "class").alias("part"), "k", "n", "root", (F.col("own") == F.col("class")).alias("home"))


def _mixed(rows: DataFrame, block: int, sets: int) -> DataFrame:
    """Rows of parts where several components meet, with the number of blocks their part makes.

    A part needs a set that is at home there: others meet in the part of their own class.
    """
    blocks = F.greatest(F.ceil(F.sum("n") / block), F.ceil(F.count("*") / sets)).cast("int")
    found = rows.groupBy("part").agg(F.min("root").alias("r0"), F.max("root").alias("r1"), F.max("home").alias("any"), blocks.alias("blocks"), F.count("*").alias("rows"))
    return rows.drop("home").join(found.filter("r0 <> r1 AND any").select("part", "blocks", "rows"), "part")


def _by_rare_shingle(rows: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Rows (part, k, n, root) of large parts, dealt out by shingles.

    In one common order of shingles, frequent ones last, two sets of similarity p share
    one of the first n - ceil(p * n) + 1 shingles of either: each set goes to these.
    """
    each = materialize(rows.join(sets.select("k", "shingles"), "k").select("part", "k", "n", "root", "rows", F.explode("shingles").alias("s")), "neardup-shingles")
    often = each.groupBy("part", "s").agg(F.count("*").alias("c"), F.first("rows").alias("rows")).filter(F.col("c") * FREQUENT > F.col("rows")).select("part", "s", F.lit(1).alias("often"))
    told = each.join(often, ["part", "s"], "left")
    place = F.row_number().over(Window.partitionBy("part", "k").orderBy(F.coalesce("often", F.lit(0)), "s"))
    first = F.col("n") - F.ceil(F.col("n") * percent / 100) + 1
    return told.withColumn("place", place).filter(F.col("place") <= first).select(F.xxhash64("part", "s").alias("part"), "k", "n", "root", F.lit(True).alias("home"))


def cross_links(members: DataFrame, roots: DataFrame, sets: DataFrame, percent: int, block: int = BLOCK, block_sets: int = BLOCK_SETS, split: int = SPLIT) -> DataFrame:
    """Links that join components inside a bucket; pairs within a component are not compared."""
    known = members.join(roots.withColumnRenamed("a", "k"), "k", "left").withColumn("root", F.coalesce("root", "k"))
    known = materialize(known.select("bucket", "k", "n", "root"), "neardup-known")
    open_ = materialize(_mixed(_parts(known, percent), block, block_sets), "neardup-open")
    small, large = open_.filter(F.col("blocks") <= split), open_.filter(F.col("blocks") > split)
    if not large.isEmpty():
        small = small.unionByName(_mixed(_by_rare_shingle(large, sets, percent), block, block_sets))
    own = F.pmod(F.xxhash64("k"), F.col("blocks").cast("long")).cast("int")
    cells = small.withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    cells = cells.select("part", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "k", "root")
    cells = cells.join(sets.select("k", "n", "shingles"), "k").repartition("part", "i", "j").sortWithinPartitions("part", "i", "j")
    return cells.select("part", "i", "j", "k", "root", "n", "shingles").mapInArrow(_links_of_cells(percent), "a binary, b binary")


def near_duplicates(df: DataFrame, key: str = "doc_id", text: str = "text", words: int = WORDS, percent: int = PERCENT, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) for every row.

    component_id is the least id that links reach; kept marks the row's own id.
    """
    docs = materialize(features(df, key, text, words, bands, rows), "neardup-docs")
    able = docs.filter("k IS NOT NULL AND doc_id IS NOT NULL")
    # One row a distinct set. The sketch follows from the set, so any row's bands do.
    reps = able.groupBy("k").agg(F.min(F.struct("doc_id", "n", "bands")).alias("x")).select("k", F.col("x.doc_id").alias("rep"), F.col("x.n").alias("n"), F.col("x.bands").alias("bands"))
    reps = materialize(reps.withColumn("set", F.col("k")).withColumn("k", node(F.col("rep"), F.col("k"))), "neardup-sets")
    able_to_link = F.lit(100) * F.col("n") >= F.lit(percent) * (F.col("n") + 1)
    entries = reps.filter(able_to_link).select("k", "n", F.explode("bands").alias("bucket"))
    full = entries.groupBy("bucket").agg(F.min("k").alias("c0"), F.max("k").alias("c1")).filter("c0 <> c1")
    members = materialize(entries.join(full, "bucket"), "neardup-members")
    wanted = members.select("k").distinct()
    ids = reps.join(wanted, "k", "left_semi").select(F.col("rep").alias("doc_id")).distinct()
    source = df.select(whole(df, key).alias("doc_id"), F.col(f"`{text}`").alias("text")).join(ids, "doc_id", "left_semi")
    sets = features(source, "doc_id", "text", words, bands, rows, with_sets=True).filter("k IS NOT NULL")
    sets = materialize(sets.select(node(F.col("doc_id"), F.col("k")).alias("k"), "n", "shingles").dropDuplicates(["k"]), "neardup-full")

    star = F.explode(F.array(F.struct(F.col("c0").alias("c")), F.struct(F.col("c1").alias("c"))))
    edges = members.select("k", star.alias("s")).select(F.col("s.c").alias("a"), F.col("k").alias("b")).filter("a <> b").distinct()
    links = materialize(confirm(edges, sets, percent), "neardup-links")
    roots = components(links)
    more = materialize(cross_links(members, roots, sets, percent), "neardup-cross")
    if not more.isEmpty():
        roots = components(links.unionByName(more))
    named = reps.select("k", "set").join(roots.withColumnRenamed("a", "k"), "k", "left")
    per_set = named.select(F.col("set").alias("k"), id_of(F.coalesce("root", "k")).alias("component_id"))
    linked = able.select("doc_id", "n", "k").join(per_set, "k").select("doc_id", F.col("n").alias("n_shingles"), "component_id")
    alone = docs.filter("k IS NULL OR doc_id IS NULL").select("doc_id", F.col("n").alias("n_shingles"), F.col("doc_id").alias("component_id"))
    return linked.unionByName(alone).withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))


def drop_near_duplicates(df: DataFrame, key: str = "doc_id", text: str = "text", words: int = WORDS, percent: int = PERCENT) -> DataFrame:
    """The rows of ``df`` whose id is its component's: one document of each group.

    Of rows that repeat an id, any one stays; rows with a null id all stay.
    """
    [name] = fresh(df.columns, "id")
    found = materialize(near_duplicates(df, key, text, words, percent).filter("kept").select(F.col("doc_id").alias(name)), "neardup-kept")
    out = df.join(found.distinct(), whole(df, key).eqNullSafe(F.col(name)), "left_semi")
    known = found.filter(F.col(name).isNotNull())
    if known.count() == known.distinct().count():
        return out
    return out.filter(F.col(f"`{key}`").isNotNull()).dropDuplicates([key]).unionByName(out.filter(F.col(f"`{key}`").isNull()))
