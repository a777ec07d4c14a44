"""Quality rules as a short-circuit cascade.

Each rule needs one or more measures of a text. Every rule is first run on a random
sample of whole texts, on the executors; its measures are timed and its rejections
counted, and the rules are ordered by rejections per second. Over the whole table a rule then sees
only the texts that every rule before it has kept. A text is rejected if any rule
rejects it, so the order moves cost and never the verdict.

Cases: a null or empty text has no words and fails the least-words rule; texts of
any length are measured whole; repeated rows repeat their result; an empty table
gives an empty table (rules stay in the given order); other columns are not read.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sieve.llm.text import as_bytes, fresh, ngrams, slices, starts, word_hashes

_NO_SYMBOLS = b"#*$%&|<>"
_WHITE = b" \t\n\r\x0b\x0c"
#: Rows that the order is estimated on, about; no verdict depends on it.
SAMPLE_ROWS = 2000


class Measures:
    """Measures of a batch of texts, each made when first asked for."""

    def __init__(self, texts: list[bytes]):
        self.texts = texts
        self.have: dict[str, np.ndarray] = {}

    def get(self, name: str) -> np.ndarray:
        if name not in self.have:
            getattr(self, f"_{GROUP[name]}")()
        return self.have[name]

    def _words(self) -> None:
        self.hashes, self.have["n_words"] = word_hashes(self.texts)

    def _chars(self) -> None:
        tails = lambda b: len(b) - len(b.translate(None, _CONTINUED))
        self.have["word_chars"] = np.array([len(b) - tails(b) - (len(b) - len(b.translate(None, _WHITE))) for b in self.texts], np.int64)

    def _symbols(self) -> None:
        self.have["n_symbols"] = np.array([len(b) - len(b.translate(None, _NO_SYMBOLS)) for b in self.texts], np.int64)

    def _lines(self) -> None:
        n, dup = [], []
        for b in self.texts:
            lines = [x for x in b.split(b"\n") if x and not x.isspace()]
            n.append(len(lines))
            dup.append(len(lines) - len(set(lines)))
        self.have |= {"n_lines": np.array(n, np.int64), "n_dup_lines": np.array(dup, np.int64)}

    def _repeats(self) -> None:
        counts = self.get("n_words")
        at, grams = starts(counts), ngrams(self.hashes, 5)
        out = np.zeros(len(counts), np.int64)
        for k in np.flatnonzero(counts > 5):
            g = grams[at[k] : at[k + 1] - 4]
            order = np.argsort(g, kind="stable")
            same = g[order][1:] == g[order][:-1]
            if same.any():
                twice = np.zeros(len(g), bool)
                twice[order[1:][same]] = True
                twice[order[:-1][same]] = True
                step = np.zeros(len(g) + 5, np.int64)
                step[: len(g)] += twice
                step[5:] -= twice
                out[k] = np.count_nonzero(np.cumsum(step))
        self.have["n_repeat_words"] = out


_CONTINUED = bytes(range(0x80, 0xC0))
GROUP = {"n_words": "words", "word_chars": "chars", "n_symbols": "symbols", "n_lines": "lines", "n_dup_lines": "lines", "n_repeat_words": "repeats"}


@dataclass(frozen=True)
class Rule:
    """``rejects`` takes arrays of the named measures and gives a mask."""

    name: str
    needs: tuple[str, ...]
    rejects: Callable[..., np.ndarray]


#: At least 10 words; at most 20 % of words in repeated 5-word windows; at most one
#: symbol of the set to four words; at most 40 % repeated lines; 2 to 20 characters to a word.
RULES = (
    Rule("few_words", ("n_words",), lambda n: n < 10),
    Rule("repeated_windows", ("n_words", "n_repeat_words"), lambda n, r: 100 * r > 20 * n),
    Rule("symbols", ("n_words", "n_symbols"), lambda n, s: 100 * s > 25 * n),
    Rule("repeated_lines", ("n_lines", "n_dup_lines"), lambda n, d: 100 * d > 40 * n),
    Rule("word_length", ("n_words", "word_chars"), lambda n, c: (c < 2 * n) | (c > 20 * n)),
)


def trial(texts: list[bytes], rules: tuple[Rule, ...] = RULES) -> list[tuple[float, int]]:
    """(seconds, texts rejected) of every rule on its own."""
    found = []
    for rule in rules:
        m = Measures(texts)
        t = time.perf_counter()
        bad = rule.rejects(*map(m.get, rule.needs))
        found.append((time.perf_counter() - t, int(np.count_nonzero(bad))))
    return found


def best_first(found: list[tuple[float, int]]) -> list[int]:
    """Numbers of the rules, most rejections per second first."""
    return sorted(range(len(found)), key=lambda i: (-found[i][1] / max(found[i][0], 1e-12), i))


def order_rules(df: DataFrame, text: str = "text", rules: tuple[Rule, ...] = RULES, sample_rows: int = SAMPLE_ROWS) -> tuple[Rule, ...]:
    """The rules by rejection per cost on about ``sample_rows`` rows of ``df``, drawn at random."""
    rows = df.count()
    if not rows:
        return tuple(rules)
    picked = df.sample(min(1.0, sample_rows / rows), seed=11).select(F.coalesce(F.col(f"`{text}`"), F.lit("")).alias("t"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, 0):
                found = trial(as_bytes(part.column(0)), rules)
                columns = [range(len(found)), [x[0] for x in found], [x[1] for x in found]]
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, (pa.int32(), pa.float64(), pa.int64()), strict=True)], ["rule", "seconds", "rejected"])

    told = picked.mapInArrow(run, "rule int, seconds double, rejected bigint").groupBy("rule").agg(F.sum("seconds").alias("s"), F.sum("rejected").alias("n"))
    by = {r["rule"]: (r["s"], r["n"]) for r in told.collect()}  # one row a rule
    return tuple(rules[i] for i in best_first([by.get(i, (0.0, 0)) for i in range(len(rules))]))


def cascade(texts: list[bytes], rules: tuple[Rule, ...], known: Measures | None = None) -> tuple[np.ndarray, np.ndarray, list[int]]:
    """(kept mask, index of the rejecting rule or -1, texts each rule looked at); ``known`` is used, not made again."""
    alive = np.arange(len(texts))
    by = np.full(len(texts), -1)
    looked = []
    m = known or Measures(texts)
    for k, rule in enumerate(rules):
        looked.append(len(alive))
        bad = rule.rejects(*map(m.get, rule.needs))
        by[alive[bad]] = k
        if bad.any():
            keep = ~bad
            alive = alive[keep]
            m = m_subset(m, keep)
    return by < 0, by, looked


def m_subset(m: Measures, keep: np.ndarray) -> Measures:
    """The measures of the kept texts; what is known so far stays known."""
    out = Measures([t for t, k in zip(m.texts, keep, strict=True) if k])
    out.have = {k: v[keep] for k, v in m.have.items()}
    if "n_words" in m.have:
        out.hashes = m.hashes[np.repeat(keep, m.have["n_words"])]
    return out


def judge(df: DataFrame, rules: tuple[Rule, ...], text: str = "text", keep: tuple[str, ...] = ("doc_id",), report: tuple[str, ...] = (), verdict: str = "kept") -> DataFrame:
    """``keep`` columns, the measures in ``report`` for every row, and the verdict.

    Measures that are reported are made for all rows, once; the others only as far
    as the cascade asks for them.
    """
    [own] = fresh([*keep, *report, verdict], "text")
    picked = df.select(*[F.col(f"`{c}`") for c in keep], F.coalesce(F.col(f"`{text}`"), F.lit("")).alias(own))
    fields = "".join(f"`{f.name}` {f.dataType.simpleString()}, " for f in picked.schema.fields[:-1])
    at, names = len(keep), [*keep, *report, verdict]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, at):
                texts = as_bytes(part.column(at))
                m = Measures(texts)
                told = [pa.array(m.get(x)) for x in report]
                yield pa.RecordBatch.from_arrays([*part.columns[:at], *told, pa.array(cascade(texts, rules, m)[0])], names)

    return picked.mapInArrow(run, fields + "".join(f"`{x}` bigint, " for x in report) + f"`{verdict}` boolean")


def passing(df: DataFrame, rules: tuple[Rule, ...], text: str = "text") -> DataFrame:
    """The rows of ``df`` that every rule keeps; columns as they came."""
    at = df.columns.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, at):
                yield part.filter(pa.array(cascade(as_bytes(part.column(at)), rules)[0]))

    return df.mapInArrow(run, df.schema)
