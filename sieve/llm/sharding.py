"""Sharding by balanced label propagation.

Documents with equal texts are linked. Every document starts in the shard its hash
names. Rounds go on until two in a row leave no fewer links cut, or nothing moves. A round looks at cells of a text in a shard and their counts: a cell moves
towards the shard that holds most of its text, if that shard has room; admission is
by hash bucket until the room is used up, so no shard ever passes its quota. After
the rounds each shard keeps its linked documents first and then others up to its
exact size; what is over fills the shards that are short. Counts of the shards are
at most one apart.

All steps are aggregations and joins of narrow rows; numbering is by bucket counts
and places within a bucket, so no task sees a whole shard or group.

Cases: a null text is the empty text (of no bytes) and linked with other empty texts;
null ids are ids like others; rows that are equal in every column get different
slots; an empty table gives an empty table; other columns are not read.
"""

from __future__ import annotations

import itertools

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from sieve.plans.scratch import materialize

#: Admission buckets; rows numbered by one task on average.
BUCKETS, TASK_ROWS = 64, 50_000
#: Cells of a text in each first shard: a large group moves in parts that fit.
PARTS = 8


def _narrow(df: DataFrame, key: str, text: str, shards: int) -> DataFrame:
    t = F.coalesce(F.col(f"`{text}`"), F.lit("")).cast("binary")
    out = df.select(F.col(f"`{key}`").alias("doc_id"), (F.octet_length(t) + F.lit(16)).cast("long").alias("size"), F.crc32(t).alias("text_crc32"), F.unhex(F.md5(t)).alias("group"))
    h = F.xxhash64("doc_id", "group")
    return out.withColumn("h", h).withColumn("start", F.pmod(F.xxhash64(F.lit(1), "h"), F.lit(shards * PARTS)).cast("int"))


def propagate(cells: DataFrame, shards: int, room: int, rounds: int | None = None) -> tuple[DataFrame, list[int]]:
    """Moves cells (group, start, n); gives (group, start, shard) and the counts of cut rows by round.

    ``room``: linked documents a shard may hold at most. ``rounds``: stop after so many
    (otherwise when the cut no longer falls: it is a whole number and falls or ends).
    """
    state = materialize(cells.select("group", "start", F.pmod("start", F.lit(shards)).cast("int").alias("shard"), "n"), "sharding-state")
    cut: list[int] = []
    for turn in itertools.count():
        if turn == rounds or (len(cut) > 2 and cut[-1] >= min(cut[:-2])) and cut[-2] >= min(cut[:-2]):
            break
        held = state.groupBy("group", "shard").agg(F.sum("n").alias("m"))
        load = {r["shard"]: r["n"] for r in state.groupBy("shard").agg(F.sum("n").alias("n")).collect()}  # one row a shard
        free = {s: room - load.get(s, 0) for s in range(shards)}
        open_ = [s for s, x in free.items() if x > 0]
        weight = F.struct("m", F.xxhash64("group", "shard").alias("tie"), "shard")
        best = held.filter(F.col("shard").isin(open_)).groupBy("group").agg(F.max(weight).alias("best"))
        ranked = held.withColumn("own", weight).join(best, "group").filter(F.col("own") < F.col("best")).select("group", "shard", F.col("best.shard").alias("to"))
        bucket = F.pmod(F.xxhash64(F.lit(turn), "group", "start"), F.lit(BUCKETS)).cast("int")
        wish = state.join(ranked, ["group", "shard"]).select("group", "start", "to", "n", bucket.alias("bucket"))
        wish = materialize(wish, "sharding-wish")
        asked = wish.groupBy("to", "bucket").agg(F.sum("n").alias("n")).collect()  # shards x buckets
        cut.append(sum(r["n"] for r in asked))
        used, taken = dict.fromkeys(open_, 0), []
        for r in sorted(asked, key=lambda r: (r["to"], r["bucket"])):
            if used[r["to"]] + r["n"] <= free[r["to"]]:
                used[r["to"]] += r["n"]
                taken.append((r["to"], r["bucket"]))
        if not taken:
            break
        admitted = state.sparkSession.createDataFrame(taken, "to int, bucket int")
        moves = wish.join(F.broadcast(admitted), ["to", "bucket"]).select("group", "start", F.col("to").alias("moved"))
        state = materialize(state.join(moves, ["group", "start"], "left").select("group", "start", F.coalesce("moved", "shard").alias("shard"), "n"), "sharding-state")
    return state.select("group", "start", "shard"), cut


def _number(rows: DataFrame, by: list[str], bucket: Column, tie: list) -> DataFrame:
    """Adds ``at``: a gapless number within ``by``, from bucket counts and places in a bucket."""
    rows = rows.withColumn("__b", bucket)
    counts = rows.groupBy(*by, "__b").agg(F.count("*").alias("n"))
    before = F.coalesce(F.sum("n").over(Window.partitionBy(*by).orderBy("__b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    offsets = counts.select(*by, "__b", before.alias("__o"))
    place = F.row_number().over(Window.partitionBy(*by, "__b").orderBy(*tie)).cast("long")
    return rows.withColumn("__p", place).join(offsets, [*by, "__b"]).withColumn("at", F.col("__o") + F.col("__p") - 1).drop("__b", "__o", "__p")


def shard_documents(df: DataFrame, shards: int = 40, key: str = "doc_id", text: str = "text", rounds: int | None = None) -> DataFrame:
    """(doc_id, size, text_crc32, shard, slot) for every row; shard counts at most one apart."""
    rows = materialize(_narrow(df, key, text, shards), "sharding-rows")
    total = rows.count()
    aim = [total // shards + (s < total % shards) for s in range(shards)]
    cells = rows.groupBy("group", "start").agg(F.count("*").alias("n"))
    linked = cells.groupBy("group").agg(F.sum("n").alias("all")).filter("all > 1").select("group")
    placed, _ = propagate(cells.join(linked, "group", "left_semi"), shards, total // shards, rounds)
    placed = placed.withColumn("linked", F.lit(0))
    labelled = rows.join(placed, ["group", "start"], "left").select("doc_id", "size", "text_crc32", "h", F.coalesce("shard", F.pmod("start", F.lit(shards)).cast("int")).alias("shard"), F.coalesce("linked", F.lit(1)).alias("rest"))
    labelled = materialize(labelled, "sharding-labels")

    per_shard = max(1, total // shards // TASK_ROWS)
    tie = ["h", "doc_id", "text_crc32", "size"]
    bucket = F.col("rest") * F.lit(per_shard) + F.pmod(F.xxhash64(F.lit(2), "h"), F.lit(per_shard))
    numbered = materialize(_number(labelled, ["shard"], bucket, tie), "sharding-numbered")
    have = {r["shard"]: r["n"] for r in numbered.groupBy("shard").agg(F.count("*").alias("n")).collect()}  # one row a shard
    limit = F.element_at(F.array(*[F.lit(x).cast("long") for x in aim]), F.col("shard") + 1)
    stay = numbered.filter(F.col("at") < limit).select("doc_id", "size", "text_crc32", "shard", F.col("at").alias("slot"))

    over = numbered.filter(F.col("at") >= limit).select(*tie).withColumn("all", F.lit(0))
    many = sum(max(0, n - aim[s]) for s, n in have.items())
    pool = _number(over, ["all"], F.pmod(F.xxhash64(F.lit(3), "h"), F.lit(max(1, many // TASK_ROWS))), tie)
    bounds, slots, at = [], [], 0
    for s in range(shards):
        if (kept := min(have.get(s, 0), aim[s])) < aim[s]:
            bounds.append((s, at))
            slots.append(kept)
            at += aim[s] - kept
    if not bounds:
        return stay
    first = F.array(*[F.lit(x).cast("long") for _, x in bounds])
    which = F.size(F.filter(first, lambda b: b <= F.col("at")))
    moved = pool.withColumn("k", which).select("doc_id", "size", "text_crc32", F.element_at(F.array(*[F.lit(s) for s, _ in bounds]), F.col("k")).alias("shard"), (F.col("at") - F.element_at(first, F.col("k")) + F.element_at(F.array(*[F.lit(x).cast("long") for x in slots]), F.col("k"))).alias("slot"))
    return stay.unionByName(moved)
