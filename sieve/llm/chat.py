"""Reply trees to formatted conversations.

Nodes name their parent. Root-to-leaf paths come from iterated self-joins by
doubling: after round k every node knows its ancestor 2**k levels up and the sum
of scores on the way, so trees of depth d take log2(d) joins. Leaves are ranked by
path score, then depth, then node id; the best leaf of each tree is kept and its
ancestors are collected by walking the same jump tables from the largest jump down.
Each chosen path becomes one conversation. Rounds are written as scratch tables.

Cases: a null tree id is one tree of its own; a null node id, or a parent that is
not in the tree, makes a root; nodes on a parent cycle reach no root and are left
out; a null role or text is empty; ties in score fall to the deeper, then the
smaller node id; rows repeated with one node id are one node with several turns, in
order of role and text; an empty table gives an empty table; other columns are not
read.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sieve.plans.scratch import materialize

OPEN, CLOSE = "<|im_start|>", "<|im_end|>"
_ESCAPE = re.compile(r"<(\\*)\|")
_UNESCAPE = re.compile(r"<\\(\\*)\|")
_TURN = re.compile(re.escape(OPEN) + r"(.*?)\n(.*?)" + re.escape(CLOSE) + "\n", re.S)


def escape(s: str) -> str:
    """Puts one more backslash between ``<`` and ``|``; so no control string is left."""
    return _ESCAPE.sub(lambda m: f"<{m[1]}\\|", s)


def unescape(s: str) -> str:
    return _UNESCAPE.sub(lambda m: f"<{m[1]}|", s)


def escape_role(s: str) -> str:
    return escape(s.replace("\\", "\\\\").replace("\n", "\\n"))


def unescape_role(s: str) -> str:
    return re.sub(r"\\(.)", lambda m: "\n" if m[1] == "n" else m[1], unescape(s))


def render(turns: list[tuple[str, str]], learn: str = "assistant") -> tuple[str, list[tuple[int, int]]]:
    """The formatted conversation and the character spans under the loss mask."""
    out, spans, at = [], [], 0
    for role, text in turns:
        head, body = f"{OPEN}{escape_role(role)}\n", escape(text)
        if role == learn:
            spans.append((at + len(head), at + len(head) + len(body)))
        out.append(f"{head}{body}{CLOSE}\n")
        at += len(out[-1])
    return "".join(out), spans


def parse(formatted: str) -> list[tuple[str, str]]:
    """The turns of a formatted conversation, as they were."""
    return [(unescape_role(m[1]), unescape(m[2])) for m in _TURN.finditer(formatted)]


def _node(name: str) -> Column:
    return F.coalesce(F.col(f"`{name}`").cast("long"), F.lit(-(1 << 63)))


def chosen_paths(nodes: DataFrame, tree: str = "tree_id", node: str = "node_id", parent: str = "parent_id", score: str = "score") -> DataFrame:
    """(__tree string, node, depth) of the best root-to-leaf path in each tree."""
    key = F.coalesce(F.col(f"`{tree}`").cast("string"), F.lit("\0null"))
    base = nodes.select(key.alias("t"), _node(node).alias("n"), F.col(f"`{parent}`").cast("long").alias("p"), F.coalesce(F.col(f"`{score}`").cast("double"), F.lit(0.0)).alias("s"))
    base = base.groupBy("t", "n").agg(F.min("p").alias("p"), F.max("s").alias("s"))
    there = base.select("t", F.col("n").alias("p"), F.lit(True).alias("here"))
    base = base.join(there, ["t", "p"], "left").select("t", "n", F.when(F.col("here"), F.col("p")).alias("up"), F.lit(1).cast("long").alias("depth"), "s")
    # A round joins only nodes whose path goes on; ended ones stay in the tables they ended in.
    rounds = [materialize(base, "chat-jump")]
    ended, open_ = [rounds[0].filter("up IS NULL")], rounds[0].filter("up IS NOT NULL").count()
    while open_:
        a, b = rounds[-1].filter("up IS NOT NULL").alias("a"), rounds[-1].filter("up IS NOT NULL")
        for done in ended:
            b = b.unionByName(done)
        b = b.alias("b")
        step = a.join(b, (F.col("a.t") == F.col("b.t")) & (F.col("a.up") == F.col("b.n")))
        rounds.append(materialize(step.select("a.t", "a.n", F.col("b.up").alias("up"), (F.col("a.depth") + F.col("b.depth")).alias("depth"), (F.col("a.s") + F.col("b.s")).alias("s")), "chat-jump"))
        ended.append(rounds[-1].filter("up IS NULL"))
        before, open_ = open_, rounds[-1].filter("up IS NOT NULL").count()
        if open_ == before:  # a round ends some paths unless all that are left are cycles
            break
    whole = ended[0]
    for done in ended[1:]:
        whole = whole.unionByName(done)
    parents = rounds[0].filter("up IS NOT NULL").select("t", F.col("up").alias("n"))
    leaves = whole.join(parents, ["t", "n"], "left_anti")
    best = leaves.groupBy("t").agg(F.max(F.struct("s", "depth", F.bitwise_not("n").alias("m"), F.col("n").alias("n"))).alias("x")).select("t", F.col("x.n").alias("n"))
    path = materialize(best, "chat-walk")
    for table in reversed(rounds):
        more = path.join(table.filter("up IS NOT NULL").select("t", "n", "up"), ["t", "n"]).select("t", F.col("up").alias("n"))
        path = materialize(path.unionByName(more), "chat-walk")
    depth = whole.select("t", "n", "depth")
    return materialize(path.join(depth, ["t", "n"]).select(F.col("t").alias("__tree"), F.col("n").alias("__node"), "depth"), "chat-path")


def format_trees(nodes: DataFrame, tree: str = "tree_id", node: str = "node_id", parent: str = "parent_id", score: str = "score", role: str = "role", text: str = "text", learn: str = "assistant") -> DataFrame:
    """One row a tree: tree id, turns, formatted text, spans of the loss mask."""
    path = chosen_paths(nodes, tree, node, parent, score)
    key = F.coalesce(F.col(f"`{tree}`").cast("string"), F.lit("\0null"))
    rows = nodes.select(F.col(f"`{tree}`").alias("tree_id"), key.alias("__tree"), _node(node).alias("__node"), F.coalesce(F.col(f"`{role}`"), F.lit("")).alias("role"), F.coalesce(F.col(f"`{text}`"), F.lit("")).alias("text"))
    both = rows.join(path, ["__tree", "__node"]).groupBy("__tree").agg(F.first("tree_id").alias("tree_id"), F.sort_array(F.collect_list(F.struct("depth", "role", "text"))).alias("turns"))
    picked = both.select("tree_id", F.col("turns.role").alias("roles"), F.col("turns.text").alias("texts"))
    kind = picked.schema["tree_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, batch.num_rows, 1000):
                part = batch.slice(a, 1000)
                made = [render(list(zip(r, t, strict=True)), learn) for r, t in zip(part.column(1).to_pylist(), part.column(2).to_pylist(), strict=True)]
                spans = pa.array([[{"start": s, "end": e} for s, e in m[1]] for m in made], pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([len(r) for r in part.column(1).to_pylist()], pa.int64()), pa.array([m[0] for m in made], pa.string()), spans], ["tree_id", "n_turns", "formatted", "loss_spans"])

    return picked.mapInArrow(run, f"tree_id {kind}, n_turns bigint, formatted string, loss_spans array<struct<start:bigint,end:bigint>>")


def read_back(formatted: DataFrame) -> DataFrame:
    """Digests made from the formatted text and its loss mask alone."""
    kind = formatted.schema["tree_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for tree, text, spans in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
                turns = parse(text)
                learnt = "".join(unescape(text[s["start"] : s["end"]]) for s in spans)
                sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
                out.append((tree, len(turns), sha("".join(f"{r}\n{t}\n" for r, t in turns)), len(learnt), sha(learnt), len(text)))
            cols = list(zip(*out, strict=True)) or [()] * 6
            kinds = [batch.schema.field(0).type, pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["tree_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"])

    return formatted.select("tree_id", "formatted", "loss_spans").mapInArrow(run, f"tree_id {kind}, n_turns bigint, turns_sha256 string, loss_chars bigint, loss_sha256 string, formatted_chars bigint")
