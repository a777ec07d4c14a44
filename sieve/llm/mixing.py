"""Mixing sources to target weights by a multivariate-hypergeometric splitting tree.

The documents of a source are dealt into blocks by hash. A pseudorandom permutation
of the block numbers is the order in which the source is drawn; a target of more
than the source's size takes whole passes first. The blocks that all sources hand
out are split among the output shards by a binary tree: at a node the exact block
quotas of its shards are split between its halves by a multivariate hypergeometric
draw, seeded by the node, so every leaf gets a random mixture with exact totals and
any task can recompute the part of the tree it needs. Inside a shard rows are put in
hash order.

Only per-source figures reach the driver (three rows a source); the draw of a document
follows from its source's figures and its own hash, without a join.

Cases: a null source is a source of its own, the last one; a null or empty text has
size 0 and is taken with 0 words; a source of size 0 has target 0; rows that repeat
another in id, text and source are numbered first, and the number goes into the hash:
they are dealt into blocks like other rows, and one of them at most is cut; an empty
table gives an empty table; other columns are kept by ``mix`` and not read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, LongType, StructField, StructType
from pyspark.sql.window import Window

from sieve.llm.text import as_bytes, fresh, slices
from sieve.llm.text import mix as mix64
from sieve.plans.scratch import materialize

#: Documents in a block on average, blocks in an output shard on average, sources at most.
BLOCK_ROWS, SHARD_BLOCKS, MOST_SOURCES = 1024, 8, 1_000_000
#: Output shards at most, unless asked for; beyond that a shard has more blocks.
MOST_SHARDS = 100_000
#: Bytes of upper tree nodes that a worker remembers; the others are drawn again.
MEMO_BYTES = 64 << 20
#: Blocks whose sizes one task adds up; repeated rows known by a broadcast table at most.
TASK_BLOCKS, FEW_REPEATED = 4096, 1_000_000
WEIGHTS = (5, 2, 1)
SEED = 17
_NULL = "\0null"


def targets(sizes: list[int], weights: list[float], share: float = 1.5, most: float = 2.0) -> list[float]:
    """Targets that sum to ``share`` of all sizes, by weight, none above ``most`` times its size."""
    out = [0.0] * len(sizes)
    free = [i for i in range(len(sizes)) if weights[i] > 0]
    rest = share * sum(sizes)
    while free:
        total = sum(weights[i] for i in free)
        over = [i for i in free if rest * weights[i] / total > most * sizes[i]]
        if not over:
            for i in free:
                out[i] = rest * weights[i] / total
            break
        for i in over:
            out[i] = most * sizes[i]
        rest -= sum(out[i] for i in over)
        free = [i for i in free if i not in set(over)]
    return out


def permuted(x: np.ndarray, n: np.ndarray, seed: np.ndarray) -> np.ndarray:
    """A pseudorandom permutation of 0..n-1, seeded: a Feistel network with cycle walking."""
    n = n.astype(np.uint64)
    half = np.maximum(1, np.ceil(np.log2(np.maximum(2, n.astype(np.float64))) / 2)).astype(np.uint64)
    mask = (np.uint64(1) << half) - np.uint64(1)
    y = x.astype(np.uint64)
    todo = np.ones(len(y), bool)
    while todo.any():
        left, right = y[todo] >> half[todo], y[todo] & mask[todo]
        for r in range(4):
            left, right = right, left ^ (mix64(right ^ seed[todo] ^ np.uint64(r << 56)) & mask[todo])
        y[todo] = (left << half[todo]) | right
        todo = y >= n
    return y.astype(np.int64)


@dataclass
class Source:
    """What is drawn from one source."""

    number: int
    size: int
    blocks: int
    target: float
    passes: int = 0  # whole passes
    cut: int = 0  # blocks taken whole in the last pass
    part: bool = False  # the next block is taken in part
    last: tuple[int, int] = (-(1 << 63), 0)  # order hash of the row where that ends, and its words

    @property
    def drawn(self) -> int:
        return self.passes * self.blocks + self.cut + self.part


@dataclass
class Tree:
    """Splits exact block quotas of all sources among shards."""

    quotas: tuple[int, ...]
    shards: int
    seed: int
    made: dict[tuple[int, int], np.ndarray] = field(default_factory=dict)

    def left(self, lo: int, hi: int, quotas: np.ndarray, depth: int) -> np.ndarray:
        """The part of a node's quotas that goes to the first half of its shards.

        Nodes of the upper levels are remembered, as many levels as MEMO_BYTES hold.
        """
        if (lo, hi) in self.made:
            return self.made[lo, hi]
        total, mid = int(quotas.sum()), (lo + hi) // 2
        take = total * (mid - lo) // (hi - lo)
        rng = np.random.Generator(np.random.PCG64([self.seed & 0xFFFFFFFF, lo, hi]))
        part = rng.multivariate_hypergeometric(quotas, take, method="marginals") if total else quotas
        if (2 << depth) * 8 * len(quotas) <= MEMO_BYTES:
            self.made[lo, hi] = part
        return part

    def shard(self, source: int, drawn: int) -> int:
        """The shard of a source's drawn block."""
        lo, hi, quotas, depth = 0, self.shards, np.array(self.quotas, np.int64), 0
        while hi - lo > 1:
            part, mid = self.left(lo, hi, quotas, depth), (lo + hi) // 2
            if drawn < part[source]:
                hi, quotas = mid, part
            else:
                drawn -= int(part[source])
                lo, quotas = mid, quotas - part
            depth += 1
        return lo

    def table(self) -> np.ndarray:
        """Quotas of every shard (rows) and source, for checks and reports."""
        out = np.zeros((self.shards, len(self.quotas)), np.int64)

        def walk(lo: int, hi: int, quotas: np.ndarray, depth: int) -> None:
            if hi - lo == 1:
                out[lo] = quotas
                return
            part, mid = self.left(lo, hi, quotas, depth), (lo + hi) // 2
            walk(lo, mid, part, depth + 1)
            walk(mid, hi, quotas - part, depth + 1)

        walk(0, self.shards, np.array(self.quotas, np.int64), 0)
        return out


@dataclass
class Plan:
    sources: dict[str, Source]
    shards: int
    seed: int

    def tree(self) -> Tree:
        ordered = sorted(self.sources.values(), key=lambda s: s.number)
        return Tree(tuple(s.drawn for s in ordered), self.shards, self.seed)


def _hash(key: str, text: str, seed: int) -> Column:
    return F.xxhash64(F.lit(seed), F.col(f"`{key}`"), F.col(f"`{text}`"))


def sized(df: DataFrame, key: str = "doc_id", text: str = "text", source: str = "source", seed: int = SEED) -> DataFrame:
    """(doc_id, src, h, size): the narrow table that all planning reads."""
    picked = df.select(F.col(f"`{key}`").alias("doc_id"), F.coalesce(F.col(f"`{source}`"), F.lit(_NULL)).alias("src"), _hash(key, text, seed).alias("h"), F.coalesce(F.col(f"`{text}`"), F.lit("")).alias("text"))
    kind = picked.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, 3):
                sizes = pa.array([len(t.split()) for t in as_bytes(part.column(3))], pa.int64())
                yield pa.RecordBatch.from_arrays([*part.columns[:3], sizes], ["doc_id", "src", "h", "size"])

    return picked.mapInArrow(run, f"doc_id {kind}, src string, h bigint, size bigint")


def repeated(rows: DataFrame) -> tuple[DataFrame, int]:
    """((src, h) of rows that occur more than once, their number)."""
    found = materialize(rows.groupBy("src", "h").agg(F.count("*").alias("n")).filter("n > 1").select("src", "h"), "mixing-repeated")
    return found, found.count()


def numbered(df: DataFrame, found: DataFrame, n: int, src: str = "src", h: str = "h") -> DataFrame:
    """``df`` with the number of a repeated row mixed into its hash ``h``.

    Equal rows get the numbers 0, 1, 2, ..., whichever gets which: a place among those
    of its partition, and an offset for each partition. No task sees a whole group.
    """
    if not n:
        return df
    part, row, at, before = fresh(df.columns, "part", "row", "at", "before")
    found = found.select(F.col("src").alias(src), F.col("h").alias(h))
    few = F.broadcast(found) if n <= FEW_REPEATED else found
    once, again = df.join(few, [src, h], "left_anti"), df.join(few, [src, h], "left_semi")
    again = materialize(again.withColumns({part: F.spark_partition_id(), row: F.monotonically_increasing_id()}), "mixing-again")
    counts = again.groupBy(src, h, part).agg(F.count("*").alias(at))
    earlier = F.sum(at).over(Window.partitionBy(src, h).orderBy(part).rowsBetween(Window.unboundedPreceding, -1))
    offsets = counts.select(src, h, part, F.coalesce(earlier, F.lit(0)).alias(before))
    place = F.row_number().over(Window.partitionBy(src, h, part).orderBy(row)) - 1
    told = again.withColumn(at, place.cast("long")).join(offsets, [src, h, part])
    number = F.col(at) + F.col(before)
    told = told.withColumn(h, F.when(number == 0, F.col(h)).otherwise(F.xxhash64(h, number)))
    names = [F.col(f"`{c}`") for c in df.columns]  # in their order: a join by name puts its keys first
    return once.select(*names).unionByName(told.select(*names))


def _blocks(h: np.ndarray, n: np.ndarray) -> np.ndarray:
    return (mix64(h.view(np.uint64)) % n.astype(np.uint64)).astype(np.int64)


def _seeds(plan: Plan, numbers: np.ndarray, copies: np.ndarray) -> np.ndarray:
    return mix64(numbers.astype(np.uint64) * np.uint64(1_000_003) + copies.astype(np.uint64) + np.uint64(plan.seed << 32))


def _draw(plan: Plan, tree: Tree, src: list[str], h: np.ndarray, size: np.ndarray) -> list[list[dict]]:
    """The draws of each row: copy, words, shard and place in the shard's order."""
    s = [plan.sources[x] for x in src]
    number, blocks = np.array([x.number for x in s], np.int64), np.array([x.blocks for x in s], np.int64)
    zero = np.zeros(len(s), np.int64)
    rank = permuted(_blocks(h, blocks), blocks, _seeds(plan, number, zero))
    drawn = np.array([x.drawn for x in s], np.int64)
    order = mix64(h.view(np.uint64) ^ np.uint64(0x5851F42D4C957F2D)).view(np.int64)
    out: list[list[dict]] = []
    for i, x in enumerate(s):
        takes = [(c, int(size[i])) for c in range(x.passes)]
        if rank[i] < x.cut:
            takes.append((x.passes, int(size[i])))
        elif rank[i] == x.cut and x.part and order[i] <= x.last[0]:
            takes.append((x.passes, x.last[1] if order[i] == x.last[0] else int(size[i])))
        out.append([{"copy": c, "words": w, "shard": 0, "place": 0} for c, w in takes if w or not size[i]])
    rows = [(i, d) for i, own in enumerate(out) for d in own]
    if rows:
        i = np.array([x[0] for x in rows])
        copy = np.array([x[1]["copy"] for x in rows], np.int64)
        block = copy * blocks[i] + rank[i]
        spread = permuted(block, np.maximum(1, drawn[i]), _seeds(plan, number[i], zero[i] + 7))
        place = mix64(h[i].view(np.uint64) + copy.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)).view(np.int64)
        known: dict[tuple[int, int], int] = {}
        for (at, d), b, p in zip(rows, spread.tolist(), place.tolist(), strict=True):
            k = (s[at].number, b)
            if k not in known:
                known[k] = tree.shard(*k)
            d["shard"], d["place"] = known[k], p
    return out


_DRAWS = "array<struct<copy:int,words:bigint,shard:int,place:bigint>>"
_DRAW = pa.list_(pa.struct([("copy", pa.int32()), ("words", pa.int64()), ("shard", pa.int32()), ("place", pa.int64())]))


def make_plan(rows: DataFrame, weights: tuple[float, ...] = WEIGHTS, share: float = 1.5, most: float = 2.0, block_rows: int = BLOCK_ROWS, shards: int | None = None, seed: int = SEED) -> Plan:
    """Targets, passes and cuts of every source, from the ``sized`` table."""
    totals = rows.groupBy("src").agg(F.sum("size").alias("size"), F.count("*").alias("n")).limit(MOST_SOURCES + 1).collect()
    if len(totals) > MOST_SOURCES:
        raise ValueError(f"more than {MOST_SOURCES} sources")
    totals.sort(key=lambda r: (r["src"] == _NULL, r["src"]))
    want = targets([r["size"] for r in totals], [weights[i % len(weights)] for i in range(len(totals))], share, most)
    plan = Plan({}, 1, seed)
    for i, (r, t) in enumerate(zip(totals, want, strict=True)):
        passes = min(int(most), math.floor(round(t) / r["size"])) if r["size"] else 0
        plan.sources[r["src"]] = Source(i, r["size"], max(1, math.ceil(r["n"] / block_rows)), t, passes)
    _cut(rows, plan)
    plan.shards = shards or min(MOST_SHARDS, max(1, math.ceil(sum(s.drawn for s in plan.sources.values()) / SHARD_BLOCKS)))
    return plan


def _cut(rows: DataFrame, plan: Plan) -> None:
    """Where each source's last pass ends: whole blocks, then a row in the next block."""
    kind = "src string, rank bigint, place bigint, size bigint, left bigint"

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            src, h = batch.column(0).to_pylist(), np.asarray(batch.column(1)).astype(np.int64)
            if not src:
                continue
            s = [plan.sources[x] for x in src]
            number, blocks = np.array([x.number for x in s], np.int64), np.array([x.blocks for x in s], np.int64)
            rank = permuted(_blocks(h, blocks), blocks, _seeds(plan, number, np.zeros(len(s), np.int64)))
            order = mix64(h.view(np.uint64) ^ np.uint64(0x5851F42D4C957F2D)).view(np.int64)
            left = pa.array([round(x.target) - x.passes * x.size for x in s], pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(rank), pa.array(order), batch.column(2), left], [c.split()[0] for c in kind.split(", ")])

    placed = rows.select("src", "h", "size").mapInArrow(place, kind)
    per_block = materialize(placed.groupBy("src", "rank").agg(F.sum("size").alias("words"), F.first("left").alias("need")).filter("need > 0"), "mixing-blocks")
    # A stretch of blocks, then the block, then the row: each level adds up a bounded number of sums.
    stretch = F.floor(F.col("rank") / TASK_BLOCKS).cast("long")
    wide = _where(per_block.groupBy("src", stretch.alias("at")).agg(F.sum("words").alias("words"), F.first("need").alias("need")))
    inside = per_block.withColumn("stretch", stretch).drop("need").join(_told(rows, wide, "stretch"), ["src", "stretch"])
    found = _where(inside.select("src", F.col("rank").alias("at"), "words", "need"))
    for r in found:
        s = plan.sources[r["src"]]
        s.cut, s.part = (r["at"] + 1, False) if r["words"] == r["need"] else (r["at"], True)
    parts = _told(rows, [r for r in found if plan.sources[r["src"]].part], "rank")
    inside = placed.select("src", "rank", "place", "size").join(parts, ["src", "rank"])
    for r in _where(inside.groupBy("src", F.col("place").alias("at")).agg(F.sum("size").alias("words"), F.first("need").alias("need"))):
        plan.sources[r["src"]].last = (r["at"], r["need"])


def _where(sums: DataFrame) -> list:
    """For each source the row (src, at, words, need) where the sum of words, by ``at``, reaches need; need becomes the rest."""
    run = F.sum("words").over(Window.partitionBy("src").orderBy("at").rowsBetween(Window.unboundedPreceding, -1))
    told = sums.withColumn("before", F.coalesce(run, F.lit(0))).filter("before < need AND before + words >= need")
    return told.select("src", "at", "words", (F.col("need") - F.col("before")).alias("need")).collect()  # one row a source at most


def _told(rows: DataFrame, found: list, name: str) -> DataFrame:
    """The places found, as a table to broadcast: one row a source at most."""
    made = [(r["src"], r["at"], r["need"]) for r in found]
    return F.broadcast(rows.sparkSession.createDataFrame(made, f"src string, {name} bigint, need bigint"))


def draws(rows: DataFrame, plan: Plan) -> DataFrame:
    """(doc_id, size, source_size, target, draws) for every row of the ``sized`` table."""
    kind = rows.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tree = plan.tree()
        for batch in batches:
            for a in range(0, batch.num_rows, 4096):
                part = batch.slice(a, 4096)
                src = part.column(1).to_pylist()
                made = _draw(plan, tree, src, np.asarray(part.column(2)).astype(np.int64), np.asarray(part.column(3)).astype(np.int64))
                s = [plan.sources[x] for x in src]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(3), pa.array([x.size for x in s], pa.int64()), pa.array([x.target for x in s], pa.float64()), pa.array(made, _DRAW)], ["doc_id", "size", "source_size", "target", "draws"])

    return rows.select("doc_id", "src", "h", "size").mapInArrow(run, f"doc_id {kind}, size bigint, source_size bigint, target double, draws {_DRAWS}")


def mixture(df: DataFrame, key: str = "doc_id", text: str = "text", source: str = "source", **how) -> DataFrame:
    """(doc_id, size, source_size, target, draws) for every row of ``df``."""
    rows = materialize(sized(df, key, text, source, how.get("seed", SEED)), "mixing-sized")
    rows = numbered(rows, *repeated(rows))
    return draws(rows, make_plan(rows, **how))


def mix(df: DataFrame, key: str = "doc_id", text: str = "text", source: str = "source", **how) -> DataFrame:
    """The drawn rows of ``df``, one a draw, in shards and in each shard's order.

    A row drawn in part keeps its first words, joined by single spaces.
    """
    seed = how.get("seed", SEED)
    rows = materialize(sized(df, key, text, source, seed), "mixing-sized")
    twice = repeated(rows)
    plan = make_plan(numbered(rows, *twice), **how)
    names = df.columns
    src, h, shard, place = fresh(names, "src", "h", "shard", "place")
    keyed = df.withColumns({src: F.coalesce(F.col(f"`{source}`"), F.lit(_NULL)), h: _hash(key, text, seed)})
    keyed = numbered(keyed, *twice, src, h)
    at, last = names.index(text), len(names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tree = plan.tree()
        for batch in batches:
            for part in slices(batch, at):
                texts = as_bytes(part.column(at))
                size = np.array([len(t.split()) for t in texts], np.int64)
                made = _draw(plan, tree, part.column(last).to_pylist(), np.asarray(part.column(last + 1)).astype(np.int64), size)
                own = [(i, d) for i, x in enumerate(made) for d in x]
                out = part.take(pa.array([i for i, _ in own], pa.int64()))
                cut = {j: b" ".join(texts[i].split()[: d["words"]]).decode() for j, (i, d) in enumerate(own) if d["words"] < size[i]}
                drawn = out.column(at)
                if cut:
                    drawn = pa.array([cut.get(j, t) for j, t in enumerate(drawn.to_pylist())], drawn.type)
                extra = [pa.array([d["shard"] for _, d in own], pa.int32()), pa.array([d["place"] for _, d in own], pa.int64())]
                yield pa.RecordBatch.from_arrays([*out.columns[:at], drawn, *out.columns[at + 1 : last], *extra], [*names, shard, place])

    fields = StructType([*[f for f in df.schema], StructField(shard, IntegerType()), StructField(place, LongType())])
    drawn = keyed.mapInArrow(run, fields)
    # A partition a shard, so that no two shards meet in one task by chance of hashing.
    dealt = drawn.repartitionById(plan.shards, F.col(shard))
    return dealt.sortWithinPartitions(shard, place).select(*[F.col(f"`{c}`") for c in names])
