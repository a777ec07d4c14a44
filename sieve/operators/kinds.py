"""Builders of every kind for one shard: distinct keys in, payload out.

A builder gets sorted distinct 64-bit keys and a seed and returns a Payload, or None
if this seed fails (the caller tries the next). Everything happens inside one task;
a shard that retries costs no shuffle.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from sieve.functions import sizing
from sieve.functions.hashing import fingerprint, first_segment, high, locations, low, reduce32, seeded, words
from sieve.operators.peel import Layers, assign, peel, peeled
from sieve.schema import Spec

#: The eight odd lane multipliers of the public split-block Bloom scheme.
LANES = (0x47B6137B, 0x44974D91, 0x8824AD5B, 0xA2B7289D, 0x705495C7, 0x2DF1424B, 0x9EFC4947, 0x5C6BFB31)
#: Rounds of the random walk of a cuckoo table.
MAX_ROUNDS = 1000


@dataclass
class Payload:
    bits: int  # logical size
    cells: np.ndarray | None = None
    words: np.ndarray | None = None
    seg_len: int = 0
    seg_count: int = 0
    array_len: int = 0
    extra: dict[str, str] = field(default_factory=dict)


def _peelable(keys: np.ndarray, seed: int, s: Spec, seg_len: int, seg_count: int, late: int | None = None) -> tuple[np.ndarray, np.ndarray, Layers, int] | None:
    a, b = words(keys, seed)
    cells = seg_len * seg_count
    if s.presort and s.layout != "blocks":  # keys by starting segment: the arrays are walked forwards
        start = first_segment(a, seg_len, seg_count, s.arity, s.layout)
        order = np.argsort(start.astype(np.uint16) if seg_count < 1 << 16 else start, kind="stable")  # a radix sort for 16-bit numbers
        a, b = a.take(order), b.take(order)
    loc = locations(a, b, seg_len, seg_count, s.arity, s.layout)
    layers = peel(loc, cells, s.order, late, s.buffered)
    if peeled(layers) < len(keys):
        return None
    return a, loc, layers, cells


def fuse_shape(n: int, s: Spec) -> tuple[int, int]:
    """(segment length, segment count) of a fuse or xor array."""
    if s.layout == "blocks":
        return sizing.xor(n), 3
    cells, length, count = sizing.fuse(n, s.arity, s.size_factor)
    if s.layout == "plain":  # as many segments, cut to the exact array size instead of a power of two
        count = max(s.arity, round(cells / length))
        length = -(-cells // count)
    return length, count


def build_fuse(keys: np.ndarray, seed: int, s: Spec) -> Payload | None:
    seg_len, seg_count = fuse_shape(len(keys), s)
    found = _peelable(keys, seed, s, seg_len, seg_count)
    if found is None:
        return None
    a, loc, layers, cells = found
    out = assign(layers, loc, fingerprint(a, s.fp_bits, s.fingerprint), cells)
    return Payload(cells * s.fp_bits, cells=out, seg_len=seg_len, seg_count=seg_count, array_len=cells)


def build_xorplus(keys: np.ndarray, seed: int, s: Spec) -> Payload | None:
    """Xor whose third block keeps only its used cells, behind a bitmap with running counts.

    Keys own cells of the first two blocks as long as there are any, so that few of the
    third block's are used.
    """
    seg_len, seg_count = fuse_shape(len(keys), s)
    found = _peelable(keys, seed, s, seg_len, seg_count, late=2 * seg_len)
    if found is None:
        return None
    a, loc, layers, cells = found
    full = assign(layers, loc, fingerprint(a, s.fp_bits, s.fingerprint), cells)
    third = full[2 * seg_len :]
    used = third != 0
    n_words = -(-seg_len // 64)
    bits = np.zeros(n_words * 64, np.uint8)
    bits[:seg_len] = used
    bitmap = np.packbits(bits, bitorder="little").view(np.uint64)
    before = np.concatenate(([0], np.cumsum(np.bitwise_count(bitmap))[:-1])).astype(np.uint64)
    dense = np.concatenate((full[: 2 * seg_len], third[used], np.zeros(1, full.dtype)))
    size = (2 * seg_len + int(used.sum())) * s.fp_bits + n_words * 64 + n_words * 64 // 4
    return Payload(size, cells=dense, words=np.concatenate((bitmap, before)), seg_len=seg_len, seg_count=seg_count, array_len=len(dense), extra={"words": str(n_words)})


def build_bloom(keys: np.ndarray, seed: int, s: Spec, batch: int = 1 << 14) -> Payload:
    """Hashes a batch of keys in bulk, then sets its bits."""
    m = sizing.bloom_bits(len(keys), s.bits_per_key)
    out = np.zeros(m // 64, np.uint64)
    for at in range(0, len(keys), batch):
        a, _ = words(keys[at : at + batch], seed)
        h1, h2 = high(a), low(a)
        for i in range(s.hashes):
            bit = reduce32((h1 + np.uint64(i) * h2) & np.uint64(0xFFFFFFFF), m)
            np.bitwise_or.at(out, bit >> 6, np.uint64(1) << (bit & 63).astype(np.uint64))
    return Payload(m, words=out, array_len=m)


def blocked_masks(a: np.ndarray) -> list[np.ndarray]:
    """The four words of a key's mask in its block."""
    lo = low(a)
    bit = [((lo * np.uint64(c)) & np.uint64(0xFFFFFFFF)) >> np.uint64(27) for c in LANES]
    one = np.uint64(1)
    return [(one << bit[2 * w]) | (one << (bit[2 * w + 1] + np.uint64(32))) for w in range(4)]


def build_blocked(keys: np.ndarray, seed: int, s: Spec, batch: int = 1 << 14) -> Payload:
    blocks = sizing.blocked_blocks(len(keys), s.bits_per_key)
    out = np.zeros(blocks * 4, np.uint64)
    for at in range(0, len(keys), batch):
        a, _ = words(keys[at : at + batch], seed)
        block = reduce32(high(a), blocks) * 4
        for w, mask in enumerate(blocked_masks(a)):
            np.bitwise_or.at(out, block + w, mask)
    return Payload(blocks * 256, words=out, array_len=blocks)


def cuckoo_places(a: np.ndarray, seed: int, fp_bits: int, buckets: int) -> tuple[np.ndarray, np.ndarray]:
    """(fingerprint from 1, first bucket) of keys."""
    fp = (low(a) % np.uint64((1 << fp_bits) - 1) + np.uint64(1)).astype(np.int64)
    return fp, reduce32(high(a), buckets)


def cuckoo_jump(fp_bits: int, seed: int, buckets: int) -> np.ndarray:
    """For every fingerprint the sum that its two buckets have, modulo the bucket count."""
    return reduce32(high(seeded(seed, np.arange(1 << fp_bits, dtype=np.uint64))), buckets)


def ranks(groups: np.ndarray) -> np.ndarray:
    """The place of every entry among those of its group, in order."""
    order = np.argsort(groups, kind="stable")
    g = groups[order]
    first = np.flatnonzero(np.concatenate(([True], g[1:] != g[:-1]))) if len(g) else np.zeros(0, np.int64)
    out = np.empty(len(g), np.int64)
    out[order] = np.arange(len(g)) - np.repeat(first, np.diff(np.append(first, len(g))))
    return out


def build_cuckoo(keys: np.ndarray, seed: int, s: Spec) -> Payload | None:
    """All keys at once: into the first bucket, then the second; the rest walk in rounds.

    In a round one key a full bucket takes the place of a random one there, which goes to
    its other bucket; keys that found their bucket taken wait for the next round.
    """
    m = sizing.cuckoo_buckets(len(keys), s.max_load, s.power_of_two)
    a, _ = words(keys, seed)
    fps, first = cuckoo_places(a, seed, s.fp_bits, m)
    jump = cuckoo_jump(s.fp_bits, seed, m)
    rng = np.random.Generator(np.random.PCG64(seed & 0xFFFFFFFFFFFFFFFF))
    slots = sizing.CUCKOO_SLOTS
    table, load = np.zeros((m, slots), np.uint16), np.zeros(m, np.int64)

    def put(fp: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Mask of the keys that found no free slot."""
        slot = load[at] + ranks(at)
        fits = slot < slots
        table[at[fits], slot[fits]] = fp[fits]
        np.add.at(load, at[fits], 1)
        return ~fits

    left = put(fps, first)
    fp, at = fps[left], first[left]
    for _ in range(MAX_ROUNDS):
        at = (jump[fp] - at) % m
        left = put(fp, at)
        fp, at = fp[left], at[left]
        if not len(fp):
            return Payload(m * slots * s.fp_bits, cells=table.ravel(), array_len=m * slots, seg_count=m)
        alone = ranks(at) == 0
        k = rng.integers(0, slots, int(alone.sum()))
        out = table[at[alone], k].astype(np.int64)
        table[at[alone], k] = fp[alone]
        fp = np.concatenate((out, fp[~alone]))
        at = np.concatenate((at[alone], (jump[fp[len(out) :]] - at[~alone]) % m))  # those that wait come to the same bucket again
    return None


def ribbon_rows(a: np.ndarray, b: np.ndarray, seed: int, slots: int, bits: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(start, coefficients with a leading one, right-hand side) of keys."""
    rhs = seeded(seed, b) & np.uint64((1 << bits) - 1)
    return reduce32(high(a), slots - 63), b | np.uint64(1), rhs


def eliminate(start: np.ndarray, coeff: np.ndarray, rhs: np.ndarray, slots: int) -> tuple[np.ndarray, np.ndarray] | None:
    """Rows (coefficients, right-hand sides) by slot, in rounds over all equations that are left.

    In a round the first equation at every empty slot settles there; the others add
    the row at their slot and move on to their next coefficient. None if one contradicts.
    """
    row_c, row_r = np.zeros(slots, np.uint64), np.zeros(slots, np.uint64)
    owner = np.empty(slots, np.int64)
    i, c, r = start, coeff, rhs
    while len(i):
        free = np.flatnonzero(row_c[i] == 0)
        owner[i[free][::-1]] = free[::-1]
        put = free[owner[i[free]] == free]
        row_c[i[put]], row_r[i[put]] = c[put], r[put]
        stay = np.ones(len(i), bool)
        stay[put] = False
        i, c, r = i[stay], c[stay], r[stay]
        c, r = c ^ row_c[i], r ^ row_r[i]
        gone = c == 0
        if gone.any():
            if r[gone].any():
                return None
            i, c, r = i[~gone], c[~gone], r[~gone]
        step = np.bitwise_count((c & (~c + np.uint64(1))) - np.uint64(1))
        i, c = i + step, c >> step.astype(np.uint64)
    return row_c, row_r


def solve(row_c: np.ndarray, row_r: np.ndarray, free: np.ndarray, bits: int) -> np.ndarray:
    """Solution words (bits x blocks of 64 slots) of rows by slot; empty slots take their ``free`` value.

    Within a block of 64 slots rows are reduced until each has its own slot and slots of
    the next block alone, in all blocks at once; then blocks are solved from the last.
    """
    blocks = -(-len(row_c) // 64)
    pad = blocks * 64 - len(row_c)
    c = np.pad(row_c, (0, pad)).reshape(blocks, 64)
    r = np.pad(np.where(row_c > 0, row_r, free), (0, pad)).reshape(blocks, 64)
    place = np.arange(64, dtype=np.uint64)
    ahead = np.empty((blocks, 64), np.uint64)
    value = np.empty((blocks, bits, 64), np.uint8)
    one, plane = np.uint64(1), np.arange(bits, dtype=np.uint64)[None, :, None]
    for k in range(0, blocks, 256):  # stays in cache
        own = np.ascontiguousarray((c[k : k + 256] << place).T)
        after = np.ascontiguousarray(((c[k : k + 256] >> one) >> (np.uint64(63) - place)).T)
        right = np.ascontiguousarray(r[k : k + 256].T)
        for j in range(63, 0, -1):
            adds = ~(((own[:j] >> np.uint64(j)) & one) - one)  # all ones where the row has slot j
            after[:j] ^= adds & after[j]
            right[:j] ^= adds & right[j]
        ahead[k : k + 256] = after.T
        value[k : k + 256] = (right.T[:, None, :] >> plane) & one
    out = np.zeros((blocks + 1, bits), np.uint64)
    for k in range(blocks - 1, -1, -1):
        odd = (np.bitwise_count(ahead[k] & out[k + 1][:, None]) & np.uint8(1)) ^ value[k]
        out[k] = np.packbits(odd, axis=1, bitorder="little").view(np.uint64).ravel()
    return out[:blocks].T


def build_ribbon(keys: np.ndarray, seed: int, s: Spec, attempt: int = 0) -> Payload | None:
    slots = sizing.ribbon_slots(len(keys), attempt)
    a, b = words(keys, seed)
    start, coeff, rhs = ribbon_rows(a, b, seed, slots, s.fp_bits)
    order = np.argsort(start, kind="stable")
    found = eliminate(start[order], coeff[order], np.zeros_like(rhs) if s.homogeneous else rhs[order], slots)
    if found is None:
        return None
    free = np.zeros(slots, np.uint64)
    if s.homogeneous:
        free = np.random.Generator(np.random.PCG64(seed & 0xFFFFFFFFFFFFFFFF)).integers(0, 1 << s.fp_bits, slots, dtype=np.uint64)
    n_words = slots // 64 + 2
    planes = np.zeros((s.fp_bits, n_words), np.uint64)
    solved = solve(*found, free, s.fp_bits)
    planes[:, : solved.shape[1]] = solved
    return Payload(slots * s.fp_bits, words=planes.ravel(), array_len=slots, seg_len=n_words)


def vqf_places(a: np.ndarray, b: np.ndarray, seed: int, blocks: int) -> tuple[np.ndarray, ...]:
    """(first block, second block, bucket, tag): both blocks follow from the key."""
    tag = (low(a) & np.uint64(255)).astype(np.int64)
    bucket = reduce32(low(b), sizing.VQF_BUCKETS)
    return reduce32(high(a), blocks), reduce32(high(b), blocks), bucket, tag


def build_vqf(keys: np.ndarray, seed: int, s: Spec) -> Payload | None:
    """Puts a tag in the emptier of two blocks; a block is 48 tags and 80 unary bucket sizes."""
    blocks = max(2, -(-len(keys) * 100 // int(sizing.VQF_TAGS * s.max_load * 100)))
    a, b = words(keys, seed)
    in_order = s.presort and s.order == "sorted"
    if in_order:
        order = np.argsort(high(a), kind="stable")
        a, b = a[order], b[order]
    one, two, bucket, tag = vqf_places(a, b, seed, blocks)
    load = np.zeros(blocks, np.int64)
    where = np.empty(len(keys), np.int64)
    batch = max(64, blocks // 8)  # so few that loads hardly move while a batch chooses
    for k in range(0, len(keys), batch):
        i, j = one[k : k + batch], two[k : k + batch]
        at = np.where(load[j] < load[i], j, i)
        # Keys in order of block all choose among few blocks: there every key sees the loads as they are.
        over = np.full(len(at), in_order) | (load[at] + ranks(at) >= sizing.VQF_TAGS)
        np.add.at(load, at[~over], 1)
        for x in np.flatnonzero(over).tolist():  # the emptier block as it is now
            at[x] = i[x] if load[i[x]] <= load[j[x]] else j[x]
            if load[at[x]] >= sizing.VQF_TAGS:
                return None
            load[at[x]] += 1
        where[k : k + batch] = at
    order = np.lexsort((tag, bucket, where))
    at = where[order]
    rank = np.arange(len(at)) - np.searchsorted(at, at)
    tags = np.zeros((blocks, sizing.VQF_TAGS), np.uint8)
    tags[at, rank] = tag[order]
    sizes = np.zeros((blocks, sizing.VQF_BUCKETS), np.int64)
    np.add.at(sizes, (where, bucket), 1)
    # 128 bits a block: a zero for every tag, a one at the end of every bucket.
    ends = np.cumsum(sizes, axis=1) + np.arange(sizing.VQF_BUCKETS)
    bits = np.zeros((blocks, 128), np.uint8)
    np.put_along_axis(bits, ends, 1, axis=1)
    meta = np.packbits(bits.ravel(), bitorder="little").view(np.uint64)
    return Payload(blocks * 512, cells=tags.ravel(), words=meta, array_len=blocks)


def vqf_bounds(meta: np.ndarray, blocks: int) -> np.ndarray:
    """Where every bucket's tags begin, with the block's end as last column."""
    bits = np.unpackbits(meta.view(np.uint8), bitorder="little").reshape(blocks, 128)
    ends = np.nonzero(bits)[1].reshape(blocks, sizing.VQF_BUCKETS) - np.arange(sizing.VQF_BUCKETS)
    return np.concatenate((np.zeros((blocks, 1), np.int64), ends), axis=1)


BUILDERS = {"bloom": build_bloom, "blocked": build_blocked, "cuckoo": build_cuckoo, "vqf": build_vqf, "xorplus": build_xorplus, "xor": build_fuse}


def build_payload(keys: np.ndarray, seed: int, s: Spec, attempt: int = 0) -> Payload | None:
    if s.kind == "ribbon":
        return build_ribbon(keys, seed, s, attempt)
    return BUILDERS.get(s.kind, build_fuse)(keys, seed, s)
