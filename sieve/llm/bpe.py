"""Byte-level BPE by a hierarchical-bitmap rank queue.

The text is cut into pre-tokens by the tokenizer's pattern. The pre-tokens of a batch
that are not known yet are laid out one after the other, with a wall between them that
no token crosses; a very long one has a layout to itself. The live tokens form a doubly
linked list over byte offsets. A bucket per merge rank holds the list positions whose
pair has that rank; two levels of bitmaps say which buckets are in use, so
find-first-set gives the lowest rank in two steps, whatever the length. A merge makes
at most two new pairs; entries whose pair changed meanwhile are recognised as stale
when popped. The cost is O(merges) queue steps instead of a scan of the list per merge.

Cases: null and empty texts give no ids (decoded: empty bytes); texts of any
length are encoded whole; repeated rows repeat their result; an empty table gives
an empty table; only the named columns are read, so other columns cannot clash.
"""

from __future__ import annotations

import base64
import hashlib
import re
from bisect import bisect_right
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sieve.llm.text import fresh, lists, slices

#: Pre-tokens of a generation that a worker remembers; there are two generations.
REMEMBERED = 350_000
#: Bytes of pre-tokens laid out for one run of the queue; a longer pre-token has its own.
LAYOUT = 1 << 14


class RankQueue:
    """Merge ranks in use, each with its bucket of list positions; empty between pre-tokens.

    Two levels of bitmaps: words of 256 ranks, and a summary of the words in use. The
    summary lives in the loop that works the queue, which runs once for every merge.
    """

    def __init__(self, ranks: int):
        self.words = [0] * ((ranks >> 8) + 1)
        self.buckets: dict[int, list[int]] = {}


_BIT = [1 << k for k in range(1024)]


class _Known(dict):
    """Ids of the pre-tokens met so far, as 4-byte integers, in two generations."""

    def __init__(self, make):
        self.make, self.older = make, {}

    def __missing__(self, piece: str) -> bytes:
        ids = self.older.get(piece)
        if ids is None:
            ids = self.make(piece.encode("utf-8"))
        return self.put(piece, ids)

    def put(self, piece: str, ids: bytes) -> bytes:
        if len(self) >= REMEMBERED:
            self.older = self.copy()  # a plain dict
            self.clear()
        self[piece] = ids
        return ids

    def wanted(self, pieces: list[str]) -> list[str]:
        """Those of the pieces that are not known, each once."""
        older = self.older
        return [p for p in set(pieces) if p not in self and p not in older]


def _ascii_split(pattern: str):
    """The pattern for texts of ASCII alone, where properties are plain ranges; None if unsure."""
    plain = re.sub(r"\[\^[^\]]*\]", lambda m: m[0].replace(r"\p{L}", "A-Za-z").replace(r"\p{N}", "0-9"), pattern)
    plain = plain.replace(r"\p{L}", "[A-Za-z]").replace(r"\p{N}", "[0-9]")
    if r"\p" in plain or r"\P" in plain or re.search(r"\[[^\]]*\[", plain):
        return None
    return re.compile(plain, re.ASCII).findall


class Codec:
    """Encoder and decoder for one table of ranks and one split pattern."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.ranks = ranks
        size = max(ranks.values(), default=0) + 1
        if size >= 256 * len(_BIT):
            _BIT.extend(1 << k for k in range(len(_BIT), size // 256 + 1))
        # White space as a Unicode property: the module's \s also takes U+001C-U+001F.
        self.split_any = regex.compile(pattern.replace(r"\s", r"\p{White_Space}").replace(r"\S", r"\P{White_Space}")).findall
        self.split_ascii = _ascii_split(pattern) or self.split_any
        self.pairs = np.full(65536, -1, np.int64)
        self.single = np.full(256, -1, np.int64)
        walls = set(range(256))
        for word, rank in ranks.items():
            if len(word) == 1:
                self.single[word[0]] = rank
                continue
            walls.difference_update(word)
            if len(word) == 2:
                self.pairs[word[0] << 8 | word[1]] = rank
        #: A byte that no longer token has stands between pre-tokens; without one, each is laid out alone.
        self.wall = bytes([max(walls)]) if walls else b""
        self.queue = RankQueue(size)
        self.raw = [k.to_bytes(4, "little") for k in range(size)]
        self.known = _Known(lambda b: self.pieces([b])[0])
        spans = np.zeros(size + 1, np.int64)
        for word, rank in ranks.items():
            spans[rank + 1] = len(word)
        self.begin = np.cumsum(spans)
        self.length = spans[1:]
        self.blob = np.frombuffer(b"".join(w for w, _ in sorted(ranks.items(), key=lambda x: x[1])), np.uint8)

    def pieces(self, pieces: list[bytes]) -> list[bytes]:
        """Ids of pre-tokens, four bytes each."""
        get, raw = self.ranks.get, self.raw
        out: list[bytes] = [b""] * len(pieces)
        held: list[int] = []
        room = LAYOUT if self.wall else 0
        for k, b in enumerate(pieces):
            if (whole := get(b)) is not None:
                out[k] = raw[whole]
                continue
            if held and room < len(b) + 1:
                self._fill(pieces, held, out)
                held, room = [], LAYOUT if self.wall else 0
            held.append(k)
            room -= len(b) + 1
        if held:
            self._fill(pieces, held, out)
        return out

    def _fill(self, pieces: list[bytes], held: list[int], out: list[bytes]) -> None:
        """Merges the held pre-tokens in one layout and writes their ids."""
        ids, sizes = self._merge(self.wall.join(pieces[k] for k in held), [len(pieces[k]) for k in held])
        data, at = ids.astype("<i4").tobytes(), 0
        for k, n in zip(held, sizes.tolist(), strict=True):
            out[k] = data[at : at + 4 * n]
            at += 4 * n

    def _merge(self, b: bytes, lengths: list[int]) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all pre-tokens of a layout, how many each has)."""
        get, queue, bit, summary = self.ranks.get, self.queue, _BIT, 0
        words, buckets = queue.words, queue.buckets
        n, buf = len(b), np.frombuffer(b, np.uint8)
        starts = np.cumsum([0, *lengths[:-1]]) + np.arange(len(lengths))
        ends = (starts + lengths).tolist()  # where walls stand, or the layout ends
        first = np.append(self.pairs[buf[:-1].astype(np.int64) << 8 | buf[1:]], -1)
        at = np.flatnonzero(first >= 0)
        at = at[np.argsort(first[at], kind="stable")]
        in_use, begin = np.unique(first[at], return_index=True)
        for rank, own in zip(in_use.tolist(), np.split(at, begin[1:]) if len(at) else (), strict=True):
            buckets[rank] = own.tolist()
            word = rank >> 8
            summary |= bit[word]
            words[word] |= bit[rank & 255]
        after = list(range(1, n + 2))  # start of the next live token
        before = list(range(-1, n))
        pair = first.tolist()  # rank of the pair that starts here
        token = self.single[buf].tolist()  # id of the token that starts here; -1 where none does
        while summary:
            # Find first set, twice: the lowest rank in use.
            at = (summary & -summary).bit_length() - 1
            word = words[at]
            low = word & -word
            words[at] = word = word ^ low
            if not word:
                summary ^= bit[at]
            rank = (at << 8) + low.bit_length() - 1
            bucket = buckets.pop(rank)
            if len(bucket) > 1:
                bucket.sort()
            fresh = []  # pairs to put into their buckets
            hold = -1  # up to here, a pre-token has a pair that goes before this bucket's rest
            for i in bucket:
                if pair[i] != rank:
                    continue  # stale: merged meanwhile, or its pair has changed
                if i < hold:
                    fresh.append((rank, i))
                    continue
                j = after[i]
                end = after[j]
                after[i] = end
                pair[j] = token[j] = -1
                token[i] = rank
                r = q = -1
                if end < n:
                    before[end] = i
                    r = get(b[i : after[end]], -1)
                    if r >= 0:
                        fresh.append((r, i))
                pair[i] = r
                if i:
                    p = before[i]
                    pair[p] = q = get(b[p:end], -1)
                    if q >= 0:
                        fresh.append((q, p))
                if 0 <= r <= rank or 0 <= q <= rank:
                    hold = ends[bisect_right(ends, i)]
            for r, i in fresh:
                if r in buckets:
                    buckets[r].append(i)
                else:
                    buckets[r] = [i]
                    at = r >> 8
                    if not words[at]:
                        summary |= bit[at]
                    words[at] |= bit[r & 255]
        made = np.array(token, np.int64)
        made[ends[:-1]] = -1  # walls
        live = np.flatnonzero(made >= 0)
        return made[live], np.diff(np.searchsorted(live, np.append(starts, n)))

    def encode_all(self, texts: list[str]) -> list[bytes]:
        """Ids of texts, four bytes each; what is not known is made for all of them at once."""
        cut = [(self.split_ascii if t.isascii() else self.split_any)(t) for t in texts]
        new = self.known.wanted([p for c in cut for p in c])
        for piece, ids in zip(new, self.pieces([p.encode("utf-8") for p in new]), strict=True):
            self.known.put(piece, ids)
        return [b"".join(map(self.known.__getitem__, c)) for c in cut]

    def encode(self, text: str) -> list[int]:
        return np.frombuffer(self.encode_all([text])[0], "<i4").tolist()

    def decode_all(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(bytes of all ids one after the other, bytes of each id)."""
        size = self.length[ids]
        total = int(size.sum())
        first = np.cumsum(size) - size
        return self.blob[np.arange(total) + np.repeat(self.begin[ids] - first, size)], size

    def decode(self, ids: list[int]) -> bytes:
        return self.decode_all(np.asarray(ids, np.int64))[0].tobytes()


_CODECS: dict[tuple, Codec] = {}


def read_ranks(blob: bytes) -> dict[bytes, int]:
    return {base64.b64decode(a): int(b) for a, b in map(bytes.split, blob.splitlines()) if a}


def codec(path: str, pattern: str) -> Codec:
    """The codec of a local rank file, made once in each worker."""
    if (path, pattern) not in _CODECS:
        with open(path, "rb") as f:
            _CODECS[path, pattern] = Codec(read_ranks(f.read()), pattern)
    return _CODECS[path, pattern]


def encode(df: DataFrame, path: str, pattern: str, text: str = "text", keep: tuple[str, ...] = ("doc_id",), ids: str = "ids", decoded: str | None = None) -> DataFrame:
    """``keep`` columns plus the token ids of ``text``; null is the empty text.

    ``path``: rank file, installed with the tokenizer package on every node.
    ``decoded``: a further column, the SHA-256 of what the ids decode to.
    """
    [own] = fresh([*keep, ids, decoded or ids], "text")
    picked = df.select(*[F.col(f"`{c}`") for c in keep], F.coalesce(F.col(f"`{text}`"), F.lit("")).alias(own))
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in picked.schema.fields[:-1])
    at = len(keep)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path, pattern)
        for batch in batches:
            for part in slices(batch, at, 2 << 20):
                made = c.encode_all(part.column(at).to_pylist())
                values = np.frombuffer(b"".join(made), "<i4")
                out = lists(pa.array(values, pa.int32()), np.array([len(x) // 4 for x in made], np.int64))
                columns, names = [*part.columns[:at], out], [*keep, ids]
                if decoded:
                    columns, names = [*columns, pa.array([hashlib.sha256(c.decode_all(np.frombuffer(x, "<i4"))[0]).hexdigest() for x in made], pa.string())], [*names, decoded]
                yield pa.RecordBatch.from_arrays(columns, names)
            batch = part = None  # freed before the next batch is read

    return picked.mapInArrow(run, f"{fields}, `{ids}` array<int>" + (f", `{decoded}` string" if decoded else ""))


def decode(df: DataFrame, path: str, pattern: str, ids: str = "ids", out: str = "decoded") -> DataFrame:
    """Replaces the ids column by the bytes they stand for; null ids stay null."""
    others = [c for c in df.columns if c != ids]
    [own] = fresh([*others, out], "ids")
    picked = df.select(*[F.col(f"`{c}`") for c in others], F.col(f"`{ids}`").alias(own))
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in picked.schema.fields[:-1])
    at = len(others)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path, pattern)
        for batch in batches:
            for a in range(0, batch.num_rows, 500):
                part = batch.slice(a, 500)
                lists = part.column(at)
                sizes = np.asarray(lists.value_lengths().fill_null(0)).astype(np.int64)
                made, each = c.decode_all(np.asarray(lists.flatten()).astype(np.int64))
                ends = np.concatenate(([0], np.cumsum(each)))[np.concatenate(([0], np.cumsum(sizes)))]
                texts = pa.Array.from_buffers(pa.large_binary(), len(sizes), [None, pa.py_buffer(ends.tobytes()), pa.py_buffer(made.tobytes())]).cast(pa.binary())
                texts = pc.if_else(lists.is_null(), pa.scalar(None, pa.binary()), texts)
                yield pa.RecordBatch.from_arrays([*part.columns[:at], texts], [*others, out])

    return picked.mapInArrow(run, f"{fields}, `{out}` binary")


def ids_digest(ids: str = "ids") -> Column:
    """SHA-256 of the decimal ids joined by commas."""
    return F.sha2(F.array_join(F.col(ids).cast("array<string>"), ","), 256)
