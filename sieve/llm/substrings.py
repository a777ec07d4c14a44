"""Substring dedup by relative Lempel-Ziv parsing against an index of first occurrences.

Words that lie in a window of LEAST words which occurs earlier in the corpus are
removed. A document is parsed from left to right into factors, each a longest copy of
LEAST words or more of one stretch of the reference, and literal words between them.

Reference. The reference is the corpus itself, every passage at its first occurrence.
Its index is cut into blocks by the hash of an anchor: the least K-word hash in a
window. Runs of windows with one anchor place are the entries (about one in nine
words). An entry carries the anchor's hash, 128 bits of its words, and its place.
Equal windows have equal anchors, so all stretches of LEAST words that a document
shares with the reference lie in the blocks its own anchors name: looking up these
blocks is looking up every block.
Lookup. Entries of equal words are matched at once: every one but the earliest is a
copy of it. Entries that share only the anchor meet at the edge of a shared stretch:
the words agree up to some place inside the run; there single windows are looked up.
Parse. The matches of a document are joined along their sources; at every position the
factor that reaches furthest is taken and the parse goes on at its end. Windows that
straddle the border of a factor lie in none: the borders are checked for windows that
have an earlier occurrence of their own. Factors and border windows are the spans.
Skew. Each task first matches inside its own batch and sends one entry for equal
content; where a batch already knows that an anchor has several contents, entries
travel by content instead of by anchor, and one marked entry tells the anchor's group.
A passage in a third of all documents thus sends a few rows a batch under any key.
Sorted streams with constant state do the matching; no group is gathered.

Cases: null and empty texts have no words; a text of fewer words than a window keeps
them all; texts of any length are read whole; rows of one id and text are one
document; rows that share an id but not the text are not earlier than each other at
equal places; null ids come first in order; an empty table gives an empty table;
other columns are not read, or kept as they are by ``strip_substrings``. Equal words
are told by 128 bits: no two of 2**45 different windows meet but by a chance of 2**-39.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sieve.llm.text import as_bytes, fresh, mix, ngrams, slices, starts, whole, word_hashes
from sieve.plans.scratch import materialize

#: Words of a window (the least factor) and of an anchor.
LEAST, K = 20, 5
_ENTRY = "key bigint, content bigint, check bigint, doc bigint, tag bigint, place bigint, ref_doc bigint, ref_start bigint"
_NAMES = [x.split()[0] for x in _ENTRY.split(", ")]
#: place packs the start, the windows less one (5 bits) and two flags: 1, a copy that the batch
#: has settled (it has a reference and no content); 2, an entry known to need its windows compared.
_SETTLED, _OPEN = 1, 2
_NO_ID = -(1 << 63)


def pack(start: np.ndarray, windows: np.ndarray, flag: int | np.ndarray) -> np.ndarray:
    return (start.astype(np.int64) << 7) | ((windows - 1).astype(np.int64) << 2) | flag


def start_of(place: np.ndarray) -> np.ndarray:
    return place >> 7


def windows_of(place: np.ndarray) -> np.ndarray:
    return ((place >> 2) & 31) + 1


def least_places(g: np.ndarray, width: int) -> np.ndarray:
    """Position of the first least value in every window of ``width`` values (a power of two)."""
    v, p, have = g, np.arange(len(g)), 1
    while have < width:
        a, b = v[:-have], v[have:]
        left = a <= b
        p = np.where(left, p[:-have], p[have:])
        v = np.where(left, a, b)
        have *= 2
    return p


def _order(*keys: np.ndarray) -> np.ndarray:
    """Sorts by the first key, then the next."""
    return np.lexsort(keys[::-1])


def runs(w: np.ndarray, counts: np.ndarray, least: int = LEAST, k: int = K) -> tuple[np.ndarray, ...]:
    """(text number, start, windows, anchor, content, check) of every run of windows.

    ``w`` has two rows of word hashes; content and check are independent.
    """
    none = np.zeros(0, np.int64)
    nothing = (none, none, none, none.view(np.uint64), none.view(np.uint64), none.view(np.uint64))
    if w.shape[1] < least:
        return nothing
    at = starts(counts)
    owner = np.repeat(np.arange(len(counts)), counts)
    valid = np.flatnonzero(owner[: len(owner) - least + 1] == owner[least - 1 :])
    if not len(valid):
        return nothing
    grams = ngrams(w[0], k)
    anchor = least_places(grams, least - k + 1)[: len(owner) - least + 1][valid]
    new = np.concatenate(([True], (anchor[1:] != anchor[:-1]) | (valid[1:] != valid[:-1] + 1)))
    first = np.flatnonzero(new)
    n = np.diff(np.concatenate((first, [len(valid)])))
    begin = valid[first]
    content = []
    for lane in w:
        windows = ngrams(lane, least)
        content.append(mix(windows[begin] * np.uint64(0x9FB21C651E98DF25) ^ mix(windows[begin + n - 1] + n.astype(np.uint64))))
    text = owner[begin]
    return text, begin - at[text], n, grams[anchor[first]], *content


def _batch(columns: list[np.ndarray]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(x) for x in columns], _NAMES)


def settle(content: np.ndarray, check: np.ndarray, doc: np.ndarray, start: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(index of the earliest entry of equal words, mask of entries that come after it)."""
    order = np.lexsort((start, doc, content))
    c = content[order]
    new = np.concatenate(([True], c[1:] != c[:-1])) if len(c) else np.zeros(0, bool)
    lead = order[np.flatnonzero(new)[np.cumsum(new) - 1]] if len(c) else order
    first = np.empty(len(content), np.int64)
    first[order] = lead
    first = np.where(check[first] == check, first, np.arange(len(first)))
    return first, (doc[first] != doc) | (start[first] != start)


def _entries(key: np.ndarray, content: np.ndarray, check: np.ndarray, doc: np.ndarray, tag: np.ndarray, start: np.ndarray, n: np.ndarray) -> tuple[list[np.ndarray], np.ndarray, np.ndarray]:
    """Columns of entries, settled inside the batch, with what ``settle`` gives."""
    first, after = settle(content, check, doc, start)
    key = np.where(after, mix(doc.view(np.uint64) + start.astype(np.uint64)).view(np.int64), key)
    place = pack(start, n, np.where(after, _SETTLED, 0))
    columns = [key, np.where(after, 0, content), np.where(after, 0, check), doc, tag, place, np.where(after, doc[first], 0), np.where(after, start[first], 0)]
    return columns, first, after


def _index(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Entries of the index; what a batch can match by itself is matched."""
    for batch in batches:
        for part in slices(batch, 2, 4 << 20):
            doc_of, tag_of = np.asarray(part.column(0)).astype(np.int64), np.asarray(part.column(1)).astype(np.int64)
            text, start, n, anchor, content, check = runs(*word_hashes(as_bytes(part.column(2)), (0, 1)))
            if not len(text):
                continue
            anchor, content = anchor.view(np.int64), content.view(np.int64)
            columns, first, after = _entries(anchor, content, check.view(np.int64), doc_of[text], tag_of[text], start, n)
            # Anchors with several contents here: send their entries by content, one more by anchor.
            lead = np.flatnonzero(~after & (first == np.arange(len(first))))
            order = lead[np.lexsort((content[lead], anchor[lead]))]
            a = anchor[order]
            new = np.concatenate(([True], a[1:] != a[:-1]))
            several = np.bincount(np.cumsum(new) - 1)[np.cumsum(new) - 1] > 1
            many, sign = order[several], order[several & new]
            signs = [x[sign] for x in columns]
            signs[5] = signs[5] | _OPEN  # an anchor group that sees it has other contents elsewhere
            columns[0][many] = content[many]
            columns[5][many] |= _OPEN
            yield _batch([np.concatenate((x, y)) for x, y in zip(columns, signs, strict=True)])


def _match(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Reads entries by key, content, check, id and place; gives copies (settled) and open entries.

    State: the key and words read last, the earliest entry of these words, and one
    entry held back while its key has a single content and no marked entry.
    """
    last: tuple | None = None  # key, content, check, then doc and start of the earliest entry of these words
    held: tuple | None = None  # the only entry of the key so far, not yet known to be open
    for batch in batches:
        key, content, check, doc, tag, place, ref_doc, ref_start = (np.asarray(batch.column(i)).astype(np.int64) for i in range(8))
        if not len(key):
            continue
        start = start_of(place)
        ahead = last or (~key[0], 0, 0, 0, 0)
        shifted = [np.concatenate(([ahead[i]], x[:-1])) for i, x in enumerate((key, content, check))]
        passing = (place & _SETTLED) > 0
        new_key = key != shifted[0]
        new = new_key | (content != shifted[1]) | (check != shifted[2])
        lead = np.maximum.accumulate(np.where(new, np.arange(len(key)), -1))
        lead_doc = np.where(lead >= 0, doc[lead], ahead[3])
        lead_start = np.where(lead >= 0, start[lead], ahead[4])
        copy = ~passing & ~new & ((doc != lead_doc) | (start != lead_start))
        # Open: firsts of a content whose key has several contents, or any marked entry.
        group = np.cumsum(new_key)
        marked = ~passing & ((place & _OPEN) > 0)
        contents = np.bincount(group, weights=new & ~passing, minlength=int(group[-1]) + 1)
        several = (contents[group] > 1) | (np.bincount(group, weights=marked, minlength=int(group[-1]) + 1)[group] > 0)
        if not new_key[0] and (group == 0).any():
            joins = (group == 0) & ((new & ~passing) | marked)
            if joins.any():
                several |= group == 0
                if held is not None:
                    yield _batch([np.array([x], np.int64) for x in held])
                    held = None
            elif held is None:
                several |= group == 0
        if new_key.any():
            held = None  # a key that ended with a single content has nothing to compare
        opened = new & ~passing & several
        tail = group == group[-1]
        waiting = np.flatnonzero(tail & new & ~passing & ~opened)
        if len(waiting):
            i = waiting[-1]
            held = (key[i], content[i], check[i], doc[i], tag[i], place[i] | _OPEN, 0, 0)
        out = passing | copy | opened
        flags = (place & ~np.int64(3)) | np.where(opened, _OPEN, _SETTLED)
        if out.any():
            found = [key, content, check, doc, tag, flags, np.where(copy, lead_doc, ref_doc), np.where(copy, lead_start, ref_start)]
            yield _batch([x[out] for x in found])
        last = (key[-1], content[-1], check[-1], lead_doc[-1], lead_start[-1])


def _windows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Single windows of the open runs of each text, matched inside the batch first."""
    for batch in batches:
        for part in slices(batch, 2, 4 << 20):
            doc_of, tag_of = np.asarray(part.column(0)).astype(np.int64), np.asarray(part.column(1)).astype(np.int64)
            w, counts = word_hashes(as_bytes(part.column(2)), (0, 1))
            at, grams = starts(counts), [ngrams(lane, LEAST).view(np.int64) for lane in w]
            text, start = [], []
            for i, places in enumerate(part.column(3).to_pylist()):
                p = np.unique(np.array(places, np.int64))
                s, n = start_of(p), windows_of(p)
                own = np.unique(np.repeat(s, n) + np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n))
                own = own[own + LEAST <= counts[i]]
                text.append(np.full(len(own), i))
                start.append(own)
            text, start = np.concatenate(text), np.concatenate(start)
            if not len(text):
                continue
            content, check = (g[at[text] + start] for g in grams)
            yield _batch(_entries(content, content, check, doc_of[text], tag_of[text], start, np.ones(len(text), np.int64))[0])


def _matched(entries: DataFrame) -> DataFrame:
    ordered = entries.repartition(F.col("key")).sortWithinPartitions("key", "content", "check", "doc", "place")
    return ordered.mapInArrow(_match, _ENTRY)


def _identity(df: DataFrame, key: str, text: str) -> list[Column]:
    """What tells documents apart: the id as a number, and 64 bits of the text."""
    return [F.coalesce(whole(df, key), F.lit(_NO_ID)), F.xxhash64(F.coalesce(F.col(f"`{text}`"), F.lit("")))]


def copies(df: DataFrame, key: str = "doc_id", text: str = "text") -> tuple[DataFrame, DataFrame]:
    """(texts by doc, tag; matched runs as rows doc, tag, place, ref_doc, ref_start)."""
    doc, tag = _identity(df, key, text)
    texts = df.select(doc.alias("doc"), tag.alias("tag"), F.coalesce(F.col(f"`{text}`"), F.lit("")).alias("text"))
    found = materialize(_matched(texts.mapInArrow(_index, _ENTRY)).select("doc", "tag", "place", "ref_doc", "ref_start"), "substrings-found")
    flag = F.col("place").bitwiseAND(F.lit(3))
    open_ = found.filter(flag == _OPEN).groupBy("doc", "tag").agg(F.collect_list("place").alias("places"))
    single = _matched(texts.join(open_, ["doc", "tag"]).select("doc", "tag", "text", "places").mapInArrow(_windows, _ENTRY))
    single = single.filter(flag == _SETTLED).select("doc", "tag", "place", "ref_doc", "ref_start")
    return texts, found.filter(flag == _SETTLED).unionByName(single)


def _chains(start: np.ndarray, words: np.ndarray, ref_doc: np.ndarray, ref_start: np.ndarray) -> np.ndarray:
    """Matches joined along their sources: rows (start, end, source document, source start)."""
    shift = ref_start - start
    order = np.lexsort((start, shift, ref_doc))
    s, e, d, f = start[order], (start + words)[order], ref_doc[order], shift[order]
    source = np.concatenate(([True], (d[1:] != d[:-1]) | (f[1:] != f[:-1])))
    # Ends inside one source, as running maxima: sources are set apart by a step no end can make.
    step = np.cumsum(source) * np.int64(int(e.max()) + 1)
    reach = np.maximum.accumulate(e + step)
    new = source.copy()
    new[1:] |= (s + step)[1:] > reach[:-1]
    first = np.flatnonzero(new)
    last = np.concatenate((first[1:], [len(s)])) - 1
    return np.stack([s[first], (reach - step)[last], d[first], (s + f)[first]], 1)


def parse(place: np.ndarray, ref_doc: np.ndarray, ref_start: np.ndarray) -> list[tuple[int, int, int, int]]:
    """The factors (start, words, source document, source start) of one document, in order.

    Greedy: where several sources have the words at a position, the one that agrees
    furthest is copied, and the parse goes on behind it. What lies between is literal.
    """
    if not len(place):
        return []
    chains = _chains(start_of(place), windows_of(place) + LEAST - 1, ref_doc, ref_start)
    chains = chains[np.lexsort((-chains[:, 1], chains[:, 0]))].tolist()
    out: list[tuple[int, int, int, int]] = []
    known: list[tuple[int, int, int, int]] = []  # chains that begin at or before the position, furthest end first
    at = i = 0
    while True:
        while i < len(chains) and chains[i][0] <= at:
            s, e, d, r = chains[i]
            heapq.heappush(known, (-e, s, d, r))
            i += 1
        if known and -known[0][0] - at >= LEAST:
            e, s, d, r = known[0]
            out.append((at, -e - at, d, r + at - s))
            at = -e
        elif i < len(chains):
            known.clear()  # none of them has a window from here on
            at = chains[i][0]
        else:
            return out


def spans(n: int, place: np.ndarray, factors: list[tuple[int, int, int, int]]) -> np.ndarray:
    """Mask of the words in factors, and in matched windows that straddle the border of one."""
    step = np.zeros(n + 1, np.int64)
    for s, words, _, _ in factors:
        step[s] += 1
        step[s + words] -= 1
    inside = np.cumsum(step[:n]) > 0
    covered = np.concatenate(([0], np.cumsum(inside)))
    s = start_of(place)
    e = s + windows_of(place) + LEAST - 1
    border = covered[e] - covered[s] < e - s
    np.add.at(step, s[border], 1)
    np.add.at(step, e[border], -1)
    return np.cumsum(step[:n]) > 0


def _with_copies(df: DataFrame, matched: DataFrame, by: list[str], out: str) -> DataFrame:
    """``df`` with the matches of each document as a list in ``out``."""
    lists = matched.groupBy("doc", "tag").agg(F.collect_list(F.struct("place", "ref_doc", "ref_start")).alias(out))
    return df.join(lists.withColumnsRenamed(dict(zip(("doc", "tag"), by, strict=True))), by, "left")


def _parsed(column: pa.Array) -> Iterator[tuple[np.ndarray, list[tuple[int, int, int, int]]] | None]:
    """(places, factors) of each document from its list of matches; None where it has none."""
    sizes = np.asarray(pc.fill_null(pc.list_value_length(column), 0)).astype(np.int64)
    flat = column.flatten()
    place, doc, start = (np.asarray(flat.field(i)).astype(np.int64) for i in range(3))
    at = starts(sizes)
    for a, b in zip(at[:-1], at[1:], strict=True):
        yield (place[a:b], parse(place[a:b], doc[a:b], start[a:b])) if b > a else None


_FACTOR = pa.list_(pa.struct([("start", pa.int64()), ("words", pa.int64()), ("ref_doc", pa.int64()), ("ref_start", pa.int64())]))


def dedup_substrings(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, n_words, n_removed, kept_text, factors) for every row; kept words joined by one space.

    A factor has its first word, its number of words, and the document and word it copies.
    """
    texts, matched = copies(df, key, text)
    both = _with_copies(texts, matched, ["doc", "tag"], "copies").select("doc", "text", "copies")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, 1):
                n, gone, kept, factors = [], [], [], []
                for t, own in zip(as_bytes(part.column(1)), _parsed(part.column(2)), strict=True):
                    words = t.split()
                    n.append(len(words))
                    out = spans(len(words), *own) if own else np.zeros(0, bool)
                    gone.append(int(out.sum()))
                    kept.append(b" ".join(words if not gone[-1] else [w for w, x in zip(words, out.tolist(), strict=True) if not x]))
                    factors.append([dict(zip(("start", "words", "ref_doc", "ref_start"), f, strict=True)) for f in own[1]] if own else [])
                columns = [part.column(0), pa.array(n, pa.int64()), pa.array(gone, pa.int64()), pa.array(kept, pa.binary()).cast(pa.string()), pa.array(factors, _FACTOR)]
                yield pa.RecordBatch.from_arrays(columns, ["doc_id", "n_words", "n_removed", "kept_text", "factors"])

    factor = "array<struct<start:bigint,words:bigint,ref_doc:bigint,ref_start:bigint>>"
    out = both.mapInArrow(run, f"doc_id bigint, n_words bigint, n_removed bigint, kept_text string, factors {factor}")
    return out.withColumn("doc_id", F.nullif("doc_id", F.lit(_NO_ID)))


def strip_substrings(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``df`` with the words of the spans removed from its texts.

    A text that loses nothing stays as it is; one that loses words has the rest
    joined by single spaces; rows that lose every word are left out.
    """
    names = df.columns
    doc, tag, found = fresh(names, "doc", "tag", "copies")
    _, matched = copies(df, key, text)
    keyed = df.withColumns(dict(zip((doc, tag), _identity(df, key, text), strict=True)))
    both = _with_copies(keyed, matched, [doc, tag], found).select(*[F.col(f"`{c}`") for c in names], found)
    at, last = names.index(text), len(names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, at):
                kept: list[bytes | None] = []
                for t, own in zip(as_bytes(part.column(at)), _parsed(part.column(last)), strict=True):
                    if own:
                        words = t.split()
                        t = b" ".join(w for w, x in zip(words, spans(len(words), *own).tolist(), strict=True) if not x)
                        kept.append(t or None)
                    else:
                        kept.append(t)
                texts = pa.array(kept, pa.binary()).cast(part.column(at).type)
                stays = texts.is_valid()
                texts = pc.if_else(pc.and_(part.column(at).is_null(), stays), pa.scalar(None, texts.type), texts)  # null texts stay null
                yield pa.RecordBatch.from_arrays([*part.columns[:at], texts, *part.columns[at + 1 : last]], schema=part.schema.remove(last)).filter(stays)

    return both.mapInArrow(run, df.schema)
