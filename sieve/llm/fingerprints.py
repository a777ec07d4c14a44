"""Document fingerprints by one-permutation MinHash with optimal densification.

Every shingle is hashed once. The high part of the hash chooses one of K bins, the
bin keeps the least of the rest. An empty bin walks its own fixed sequence of bins
and copies the first filled one, so a bin's agreement probability is the Jaccard
similarity of the shingle sets. The fingerprint packs the low b bits of each bin;
the likeness of two fingerprints corrects the share of equal bins for the chance
agreement 2**-b.

Cases: null is the empty text; a text without words has the empty fingerprint ""
(likeness 1 to another such text, 0 to any other); a text of fewer words than a
shingle is one shingle; texts of any length are hashed whole; repeated rows repeat
their result; an empty table gives an empty table; other columns are not read.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sieve.llm.text import as_bytes, fresh, mix, shingles, slices, starts, whole, word_hashes
from sieve.plans.scratch import materialize

#: Bins and packed bits of a bin; words in a shingle.
BINS, BITS, WORDS = 256, 4, 5


def sketch(hashes: np.ndarray, sizes: np.ndarray, bins: int) -> np.ndarray:
    """Densified bin minima, one row a set (uint64, sets x bins). Empty sets give zeros.

    Bins, minima and donors depend on the set alone, never on the batch.
    """
    n = len(sizes)
    shift = np.uint64(64 - int(bins).bit_length() + 1)
    h = mix(hashes ^ np.uint64(0xA0761D6478BD642F))
    cell = np.repeat(np.arange(n), sizes) * bins + (h >> shift).astype(np.int64)
    out = np.full(n * bins, np.iinfo(np.uint64).max, np.uint64)
    order = np.argsort(cell, kind="stable")
    if len(order):
        c = cell[order]
        first = np.concatenate(([True], c[1:] != c[:-1]))
        out[c[first]] = np.minimum.reduceat(h[order], np.flatnonzero(first))
    out = out.reshape(n, bins)
    empty = out == np.iinfo(np.uint64).max
    filled = ~empty
    todo = np.argwhere(empty & (sizes > 0)[:, None])
    attempt = np.uint64(1)
    while len(todo):
        donor = (mix(todo[:, 1].astype(np.uint64) * np.uint64(0x9FB21C651E98DF25) + attempt) >> shift).astype(np.int64)
        ok = filled[todo[:, 0], donor]
        r, c = todo[ok, 0], todo[ok, 1]
        out[r, c] = mix(out[r, donor[ok]] + attempt)
        todo = todo[~ok]
        attempt += np.uint64(1)
    out[sizes == 0] = 0
    return out


def pack(bins: np.ndarray, sizes: np.ndarray, bits: int = BITS) -> list[str]:
    """Hex strings of the low ``bits`` (1, 2, 4 or 8) of every bin."""
    low = (bins & np.uint64((1 << bits) - 1)).astype(np.uint8)
    per = 8 // bits
    packed = np.zeros((len(low), low.shape[1] // per), np.uint8)
    for k in range(per):
        packed |= low[:, k::per] << np.uint8(k * bits)
    return [p.tobytes().hex() if s else "" for p, s in zip(packed, sizes, strict=True)]


def likeness(a: list[str], b: list[str], bits: int = BITS) -> np.ndarray:
    """Estimated Jaccard similarity of pairs of fingerprints, 0 to 1."""
    out = np.zeros(len(a))
    full = np.array([bool(x) and bool(y) for x, y in zip(a, b, strict=True)])
    out[[not x and not y for x, y in zip(a, b, strict=True)]] = 1.0
    if full.any():
        x = np.frombuffer(bytes.fromhex("".join(v for v, f in zip(a, full, strict=True) if f)), np.uint8)
        y = np.frombuffer(bytes.fromhex("".join(v for v, f in zip(b, full, strict=True) if f)), np.uint8)
        diff = (x ^ y).reshape(int(full.sum()), -1)
        mask, per = (1 << bits) - 1, 8 // bits
        same = sum(((diff >> np.uint8(k * bits)) & np.uint8(mask)) == 0 for k in range(per)).sum(axis=1)
        chance = 2.0**-bits
        out[full] = np.clip((same / (diff.shape[1] * per) - chance) / (1 - chance), 0, 1)
    return out


def fingerprints_of(texts: list[bytes], words: int = WORDS, bins: int = BINS, bits: int = BITS) -> list[str]:
    out: list[str] = []
    for a in range(0, len(texts), 512):  # bounds the bins held at once
        part = texts[a : a + 512]
        hashes, sizes = shingles(*word_hashes(part), words)
        out += pack(sketch(hashes, sizes, bins), sizes, bits)
    return out


def fingerprint(df: DataFrame, text: str = "text", keep: tuple[str, ...] = ("doc_id",), words: int = WORDS, bins: int = BINS, bits: int = BITS, out: str = "fingerprint") -> DataFrame:
    """``keep`` columns and the fingerprint of each text. One pass, no shuffle."""
    [own] = fresh([*keep, out], "text")
    picked = df.select(*[F.col(f"`{c}`") for c in keep], F.coalesce(F.col(f"`{text}`"), F.lit("")).alias(own))
    fields = "".join(f"`{f.name}` {f.dataType.simpleString()}, " for f in picked.schema.fields[:-1])
    at = len(keep)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, at):
                yield pa.RecordBatch.from_arrays([*part.columns[:at], pa.array(fingerprints_of(as_bytes(part.column(at)), words, bins, bits), pa.string())], [*keep, out])

    return picked.mapInArrow(run, fields + f"`{out}` string")


_ROW = "doc_id bigint, n_chars bigint, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def _edit(text: str, following: str) -> str:
    k = len(text) // 3
    return text[: len(text) - k] + following[:k]


def _compare(ids: list, texts: list[str], following: list[str], prints: list[str], next_prints: list[str]) -> list:
    """Columns of _ROW for texts whose next text and its fingerprint are known."""
    edited = [_edit(t, f).encode() for t, f in zip(texts, following, strict=True)]
    edited_prints = fingerprints_of(edited)
    return [ids, [len(t) for t in texts], [hashlib.sha256(e).hexdigest() for e in edited], prints, edited_prints, likeness(prints, edited_prints).tolist(), likeness(prints, next_prints).tolist()]


_TYPES = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64()]
_NAMES = [x.split()[0] for x in _ROW.split(", ")]


def edited_neighbours(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Fingerprints of texts, of the texts edited with their next one, and likenesses.

    The next text is that of the next smaller key (rows of one key: by the hash of their
    text, so equal rows stand together), after the least key the greatest (null keys come
    last). The rows are range-partitioned once by key, hash and place in the input, so that
    many rows of one key go to several tasks, and sorted inside the partitions; each
    partition compares all rows but its last. Its first and last rows, two a partition, are
    then matched across partitions as a table of their own.
    """
    parts = df.select(whole(df, key).alias("doc_id"), F.coalesce(F.col(f"`{text}`"), F.lit("")).alias("text"))
    parts = parts.withColumns({"hash": F.xxhash64("text"), "row": F.monotonically_increasing_id()})
    order = [F.col("doc_id").desc_nulls_last(), F.col("hash"), F.col("row")]
    ordered = parts.repartitionByRange(*order).sortWithinPartitions(*order).select("doc_id", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list | None = None  # the last row so far: id, text, fingerprint

        def edge(kind: int, row: list) -> pa.RecordBatch:
            cols = [pa.array([None], t) for t in _TYPES]
            return pa.RecordBatch.from_arrays([*cols, pa.array([kind], pa.int32()), pa.array([row[0]], pa.int64()), pa.array([row[1]], pa.string()), pa.array([row[2]], pa.string())], [*_NAMES, "edge", "edge_id", "edge_text", "edge_print"])

        for batch in batches:
            for part in slices(batch, 1):
                ids, texts = part.column(0).to_pylist(), part.column(1).to_pylist()
                prints = fingerprints_of([t.encode() for t in texts])
                if held is None:
                    yield edge(0, [ids[0], texts[0], prints[0]])
                else:
                    ids, texts, prints = [held[0], *ids], [held[1], *texts], [held[2], *prints]
                held = [ids[-1], texts[-1], prints[-1]]
                if len(ids) > 1:
                    cols = _compare(ids[:-1], texts[:-1], texts[1:], prints[:-1], prints[1:])
                    n = len(ids) - 1
                    yield pa.RecordBatch.from_arrays([*(pa.array(c, t) for c, t in zip(cols, _TYPES, strict=True)), pa.array([None] * n, pa.int32()), pa.array([None] * n, pa.int64()), pa.array([None] * n, pa.string()), pa.array([None] * n, pa.string())], [*_NAMES, "edge", "edge_id", "edge_text", "edge_print"])
        if held is not None:
            yield edge(1, held)

    made = materialize(ordered.mapInArrow(run, _ROW + ", edge int, edge_id bigint, edge_text string, edge_print string").withColumn("at", F.spark_partition_id()), "fingerprints")
    inner = made.filter("edge IS NULL").select(*_NAMES)
    # Two rows a partition: number the partitions that have rows, and meet last with first.
    heads = made.filter("edge = 0").select("at", F.col("edge_text").alias("next_text"), F.col("edge_print").alias("next_print"))
    places = made.filter("edge = 0").select("at").sort("at").collect()
    at = [r["at"] for r in places]
    link = df.sparkSession.createDataFrame([(a, b) for a, b in zip(at, at[1:] + at[:1], strict=True)], "at int, next_at int")
    ends = made.filter("edge = 1").select("at", "edge_id", "edge_text", "edge_print").join(link, "at").join(heads.withColumnRenamed("at", "next_at"), "next_at").select("edge_id", "edge_text", "edge_print", "next_text", "next_print")

    def close(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, texts, prints, following, next_prints = (batch.column(i).to_pylist() for i in range(5))
            if ids:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(_compare(ids, texts, following, prints, next_prints), _TYPES, strict=True)], _NAMES)

    return inner.unionByName(ends.mapInArrow(close, _ROW))
