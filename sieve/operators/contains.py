"""Membership tests of every kind: as Catalyst conditions and in numpy."""

from __future__ import annotations

import uuid
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F

from sieve.functions import sizing
from sieve.functions.hashing import fingerprint, fingerprint_function, high, high_column, location_columns, locations, low, low_column, reduce32, reduce_column, shift_left, shift_right, word_columns, words
from sieve.operators.kinds import LANES, blocked_masks, cuckoo_jump, cuckoo_places, ribbon_rows, vqf_bounds, vqf_places
from sieve.operators.peel import lookup
from sieve.schema import Spec

#: Keys probed at once in numpy.
CHUNK = 1 << 15
#: Kinds whose test is one generated expression; the others go through Arrow.
NATIVE = ("fuse", "xor", "xorplus", "bloom", "blocked", "cuckoo", "ribbon")


def native(s: Spec) -> bool:
    return any(s.kind.startswith(k) for k in NATIVE)


def _at(array: Column, index: Column) -> Column:
    return F.element_at(array, (index + 1).cast("int"))


def _all(parts: list[Column]) -> Column:
    return reduce(lambda x, y: x & y, parts)


def places(key64: Column, f: str, s: Spec) -> list[Column]:
    """What a probe of ``key64`` looks at in the filter row aliased ``f``: cells, bits (bloom), blocks or buckets."""
    col = lambda name: F.col(f"{f}.{name}")
    a, b = word_columns(key64, col("seed"))
    if s.kind == "bloom":
        h1, h2 = high_column(a), low_column(a)
        return [reduce_column(low_column(h1 + F.lit(i) * h2), col("array_len")) for i in range(s.hashes)]
    if s.kind == "blocked":
        return [reduce_column(high_column(a), col("array_len"))]
    if s.kind == "cuckoo":
        m, fp = col("seg_count").cast("long"), low_column(a) % ((1 << s.fp_bits) - 1) + 1
        one = reduce_column(high_column(a), m)
        return [one, F.pmod(reduce_column(high_column(F.xxhash64(col("seed"), fp)), m) - one, m)]
    return location_columns(a, b, col("seg_len"), col("seg_count"), s.arity, s.layout)


def condition(key64: Column, f: str, s: Spec) -> Column:
    """True if the filter row aliased ``f`` may hold ``key64`` (never false for a member)."""
    col = lambda name: F.col(f"{f}.{name}")
    a, b = word_columns(key64, col("seed"))
    mask = (1 << s.fp_bits) - 1
    if s.kind == "bloom":
        tests = []
        for bit in places(key64, f, s):
            tests.append(F.getbit(_at(col("words"), shift_right(bit, 6)), bit.bitwiseAND(F.lit(63)).cast("int")) == 1)
        return _all(tests)
    if s.kind == "blocked":
        block, lo = places(key64, f, s)[0] * 4, low_column(a)

        def lane(c: int) -> Column:  # the low 32 bits of a product of 32-bit factors, without overflow
            halves = lo.bitwiseAND(F.lit(0xFFFF)) * c + shift_left((shift_right(lo, 16) * c).bitwiseAND(F.lit(0xFFFF)), 16)
            return shift_right(low_column(halves), 27).cast("int")

        one, tests = F.lit(1).cast("long"), []
        for w in range(4):
            bits = shift_left(one, lane(LANES[2 * w])).bitwiseOR(shift_left(one, lane(LANES[2 * w + 1]) + 32))
            tests.append(_at(col("words"), block + w).bitwiseAND(bits) == bits)
        return _all(tests)
    if s.kind == "cuckoo":
        fp = low_column(a) % mask + 1
        slots = range(sizing.CUCKOO_SLOTS)
        return reduce(lambda x, y: x | y, [_at(col("cells16"), i * sizing.CUCKOO_SLOTS + k).cast("long").bitwiseAND(F.lit(0xFFFF)) == fp for i in places(key64, f, s) for k in slots])
    if s.kind == "ribbon":
        start = reduce_column(high_column(a), col("array_len") - 63)
        coeff, word, shift = b.bitwiseOR(F.lit(1)), shift_right(start, 6), start.bitwiseAND(F.lit(63)).cast("int")
        rhs = F.lit(0).cast("long") if s.homogeneous else F.xxhash64(col("seed"), b)
        tests = []
        for p in range(s.fp_bits):
            at = F.lit(p) * col("seg_len").cast("long") + word
            lower, upper = _at(col("words"), at), _at(col("words"), at + 1)
            window = shift_right(lower, shift).bitwiseOR(shift_left(shift_left(upper, 1), F.lit(63) - shift))
            parity = F.bit_count(window.bitwiseAND(coeff)).cast("long")
            tests.append((parity + shift_right(rhs, p)).bitwiseAND(F.lit(1)) == 0)
        return _all(tests)
    at = places(key64, f, s)
    cells = [_at(col(s.cells), x).cast("long") for x in (at[:2] if s.kind == "xorplus" else at)]
    if s.kind == "xorplus":
        third = at[2] - 2 * col("seg_len").cast("long")
        bitmap, bit = _at(col("words"), shift_right(third, 6)), third.bitwiseAND(F.lit(63)).cast("int")
        n_words = F.size(col("words")) / 2
        below = F.bit_count(bitmap.bitwiseAND(shift_right(F.lit((1 << 63) - 1), F.lit(63) - bit))).cast("long")
        rank = _at(col("words"), shift_right(third, 6) + n_words.cast("long")) + below
        cells.append(F.when(F.getbit(bitmap, bit) == 1, _at(col(s.cells), 2 * col("seg_len").cast("long") + rank).cast("long")).otherwise(F.lit(0).cast("long")))
    found = reduce(lambda x, y: x.bitwiseXOR(y), cells)
    return found.bitwiseXOR(fingerprint_function(s.fingerprint).column(a)).bitwiseAND(F.lit(mask)) == 0


def ship(f, limit: int) -> bytes:
    """A name and a filter's rows as one Arrow stream, to be broadcast; refused beyond ``limit`` bytes of payload."""
    if f.size_bytes() > limit:
        raise ValueError(f"a filter of more than {limit} bytes is not broadcast")
    table = f.table.drop("params").toArrow()
    sink = pa.BufferOutputStream()
    sink.write(uuid.uuid4().bytes)
    with pa.ipc.new_stream(sink, table.schema) as out:
        out.write_table(table)
    return sink.getvalue().to_pybytes()


_RECEIVED: dict[bytes, dict] = {}


def received(blob: bytes) -> dict[int, dict]:
    """The rows of a shipped filter by shard, arrays without a copy; kept for the last few filters of a worker."""
    name = blob[:16]
    if name not in _RECEIVED:
        while len(_RECEIVED) >= 4:
            _RECEIVED.pop(next(iter(_RECEIVED)))
        table = pa.ipc.open_stream(pa.py_buffer(blob).slice(16)).read_all()
        rows = {}
        for i in range(len(table)):
            row = {c: table.column(c)[i] for c in table.column_names}
            rows[row["shard"].as_py()] = {c: v.values.to_numpy() if isinstance(v, (pa.ListScalar, pa.LargeListScalar)) and v.is_valid else v.as_py() for c, v in row.items()}
        _RECEIVED[name] = rows
    return _RECEIVED[name]


def among(held: dict[int, dict], s: Spec, keys: np.ndarray, at: np.ndarray, there: np.ndarray) -> np.ndarray:
    """A flag for every key by its shard; a shard's filter is made ready once a worker."""
    flag = np.zeros(len(keys), bool)
    for k in np.unique(at[there]).tolist():
        if k in held:
            if "loaded" not in held[k]:
                held[k]["loaded"] = Loaded(held[k], s)
            mine = np.flatnonzero((at == k) & there)
            flag[mine] = held[k]["loaded"].contains(keys[mine])
    return flag


class Loaded:
    """One shard's filter in numpy."""

    def __init__(self, row: dict, s: Spec):
        self.s, self.seed = s, int(row["seed"])
        self.seg_len, self.seg_count, self.array_len = row["seg_len"], row["seg_count"], row["array_len"]
        kind = {"cells8": np.uint8, "cells16": np.uint16, "cells32": np.uint32}
        cells = next((c for c in kind if row.get(c) is not None), None)
        signed = {"cells8": np.int8, "cells16": np.int16, "cells32": np.int32}
        self.cells = None if cells is None else np.asarray(row[cells], signed[cells]).view(kind[cells])
        self.words = None if row.get("words") is None else np.asarray(row["words"], np.int64).view(np.uint64)
        self.made: dict[str, np.ndarray] = {}

    def contains(self, key64: np.ndarray) -> np.ndarray:
        """A flag for every key, in chunks whose words stay in the processor's cache."""
        if len(key64) <= CHUNK:
            return self._contains(key64)
        return np.concatenate([self._contains(key64[a : a + CHUNK]) for a in range(0, len(key64), CHUNK)])

    def _contains(self, key64: np.ndarray) -> np.ndarray:
        s, seed = self.s, self.seed
        a, b = words(key64, seed)
        if s.kind == "bloom":
            out, h1, h2 = np.ones(len(a), bool), high(a), low(a)
            for i in range(s.hashes):
                bit = reduce32((h1 + np.uint64(i) * h2) & np.uint64(0xFFFFFFFF), self.array_len)
                out &= (self.words[bit >> 6] >> (bit & 63).astype(np.uint64)) & np.uint64(1) == 1
            return out
        if s.kind == "blocked":
            block = reduce32(high(a), self.array_len) * 4
            return np.logical_and.reduce([self.words[block + w] & m == m for w, m in enumerate(blocked_masks(a))])
        if s.kind == "cuckoo":
            m = self.seg_count
            if "jump" not in self.made:
                self.made["jump"] = cuckoo_jump(s.fp_bits, seed, m)
            fp, one = cuckoo_places(a, seed, s.fp_bits, m)
            table = self.cells.reshape(m, -1)
            two = (self.made["jump"][fp] - one) % m
            return ((table[one] == fp[:, None]) | (table[two] == fp[:, None])).any(axis=1)
        if s.kind == "ribbon":
            start, coeff, rhs = ribbon_rows(a, b, seed, self.array_len, s.fp_bits)
            planes = self.words.reshape(s.fp_bits, -1)
            word, shift = start >> 6, (start & 63).astype(np.uint64)
            out = np.ones(len(a), bool)
            for p in range(s.fp_bits):
                window = (planes[p][word] >> shift) | ((planes[p][word + 1] << np.uint64(1)) << (np.uint64(63) - shift))
                want = np.uint64(0) if s.homogeneous else rhs >> np.uint64(p)
                out &= (np.bitwise_count(window & coeff).astype(np.uint64) ^ want) & np.uint64(1) == 0
            return out
        if s.kind == "vqf":
            if "bounds" not in self.made:
                self.made["bounds"] = vqf_bounds(self.words, self.array_len)
            one, two, bucket, tag = vqf_places(a, b, seed, self.array_len)
            bounds, tags = self.made["bounds"], self.cells.reshape(self.array_len, -1)
            out = np.zeros(len(a), bool)
            for block in (one, two):
                at, end = bounds[block, bucket].copy(), bounds[block, bucket + 1]
                while (live := at < end).any():
                    k = np.flatnonzero(live)
                    out[k] |= tags[block[k], at[k]] == tag[k]
                    at[k] += 1
            return out
        loc = locations(a, b, self.seg_len, self.seg_count, s.arity, s.layout)
        if s.kind == "xorplus":
            n_words = len(self.words) // 2
            third = loc[:, 2] - 2 * self.seg_len
            bitmap, bit = self.words[third >> 6], (third & 63).astype(np.uint64)
            below = np.bitwise_count(bitmap & ((np.uint64(1) << bit) - np.uint64(1))).astype(np.int64)
            at = 2 * self.seg_len + self.words[n_words + (third >> 6)].astype(np.int64) + below
            value = np.where((bitmap >> bit) & np.uint64(1) == 1, self.cells[at], 0).astype(self.cells.dtype)
            return lookup(self.cells, loc[:, :2]) ^ value == fingerprint(a, s.fp_bits, s.fingerprint)
        return lookup(self.cells, loc) == fingerprint(a, s.fp_bits, s.fingerprint)
