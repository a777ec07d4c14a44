"""Toxicity by a weighted finite-state pattern grammar.

Words map to classes: insult, threat, bare threat verb, target, negation, reported
speech, other. The insult and threat lexicons are learnt from labelled texts as words
and word stems with weights; targets, negations, reporting verbs and threat verbs are
closed lists. Each clause runs through the composition of small transducers that write
labels: negated (an attack within three words of a negation), reported (an attack
after a reporting verb), threat, bare threat verb, and aimed (an attack and a target
in one clause). The labels of a match name its pattern, one of 32; the match carries the
lexicon weights of its words. Nothing but matched clauses counts: a bare threat verb
matches only where it is aimed.

A text is described by the strength of each pattern: the POWER-norm of the weights of
all clauses that match it, so every clause counts and strong ones decide. The score is
logistic in these strengths. Pattern weights are fitted on labelled texts whose words
the lexicon has not seen, and start from PRIOR factors, from which patterns that occur
seldom hardly move.

Cases: null and empty texts have no clause and get the score of an empty text;
texts of any length are read whole; repeated rows repeat their result; of labelled
texts that share an id one is learnt from; without labelled rows of both kinds the
lexicon is empty and all texts get the base rate; an empty table gives an empty table;
other columns are not read.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sieve.llm.text import as_bytes, fresh, slices
from sieve.plans.scratch import materialize

#: Closed word classes of the grammar (English, German, French, Spanish).
TARGETS = frozenset("you your he she they them him her his we us people everyone du ihr sie er dich dir euch tu vous il elle ils toi lui eux usted tú él ella ellos".split())
NEGATIONS = frozenset("not no never nobody isn't aren't wasn't don't doesn't nicht kein keine nie niemals ne pas jamais aucun nunca jamás ningún".split())
REPORTS = frozenset("said says say called calls wrote writes quoted reported claimed sagte sagt nannte schrieb dit disait appelé dijo llamó escribió".split())
THREATS = frozenset("kill hurt destroy burn beat shoot stab töten schlagen tuer frapper matar golpear".split())

#: Labelled rows used for fitting, at most; fitting and scoring read whole texts.
FIT_ROWS = 6000
#: An item of the lexicon is in this many toxic texts, with these log odds.
LEAST_TEXTS, LEAST_ODDS = 4, 3.0
#: A stem of the lexicon begins this many words.
LEAST_FORMS = 3
STEM = range(4, 9)
#: Norm over the clauses of a text; ridge of the pattern weights around the prior; weight of a bare threat verb.
POWER, RIDGE, THREAT_WEIGHT = 6.0, 20.0, 7.0

_CLAUSE = re.compile(rb"[.!?;:\n]+")
_TO_SPACE = bytes(c if 0x30 <= c <= 0x39 or 0x61 <= c <= 0x7A or c >= 0x80 or c == 0x27 else 0x20 for c in range(256))


def clauses(text: bytes) -> list[list[bytes]]:
    """Lower-cased words of each clause."""
    lower = text.lower() if text.isascii() else text.decode().lower().encode()
    return [w for c in _CLAUSE.split(lower) if (w := c.translate(_TO_SPACE).split())]


#: The alphabet of the transducers: classes of words. The last three are attacks.
CLASSES = OTHER, TARGET, NOT, REPORT, INSULT, THREAT, VERB = range(7)
#: The labels they write; a pattern is a set of labels.
NEGATED, TOLD, THREATENED, BARE, AIMED = 1, 2, 4, 8, 16
PATTERNS = 32
#: What a label makes of a pattern's weight before any text is read.
PRIOR = {NEGATED: 0.5, TOLD: 0.8, THREATENED: 1.2, BARE: 1.2, AIMED: 1.1}


@dataclass(frozen=True)
class Transducer:
    """A deterministic transducer over word classes that writes sets of labels.

    ``step[state][class]`` is (next state, labels of that word); ``final[state]`` are
    the labels of the whole clause. Labels unite under composition.
    """

    step: tuple[tuple[tuple[int, int], ...], ...]
    final: tuple[int, ...]


def transducer(states: int, move, final=lambda state: 0) -> Transducer:
    """Tabulates ``move(state, class) -> (state, labels)``."""
    return Transducer(tuple(tuple(move(q, c) for c in CLASSES) for q in range(states)), tuple(final(q) for q in range(states)))


def compose(a: Transducer, b: Transducer) -> Transducer:
    """Both read the same clause: states pair up, labels unite."""
    n = len(b.final)

    def move(q: int, c: int) -> tuple[int, int]:
        (x, f), (y, g) = a.step[q // n][c], b.step[q % n][c]
        return x * n + y, f | g

    return transducer(len(a.final) * n, move, lambda q: a.final[q // n] | b.final[q % n])


ATTACKS = (INSULT, THREAT, VERB)
#: An attack within three words of a negation; the state counts the words that are left.
NEGATION = transducer(4, lambda q, c: (3 if c == NOT else max(0, q - 1), NEGATED if q and c in ATTACKS else 0))
#: Every attack after a reporting verb in the clause.
REPORTED = transducer(2, lambda q, c: (1 if c == REPORT else q, TOLD if q and c in ATTACKS else 0))
#: An attack and a target in one clause, in any order; the states are what was seen.
AIM = transducer(4, lambda q, c: (q | (1 if c == TARGET else 2 if c in ATTACKS else 0), 0), lambda q: AIMED if q == 3 else 0)
#: Threats, learnt ones and bare verbs.
THREATENING = transducer(1, lambda q, c: (0, {THREAT: THREATENED, VERB: BARE}.get(c, 0)))
CLAUSE = compose(compose(compose(NEGATION, REPORTED), AIM), THREATENING)


def prior(pattern: int) -> float:
    """The pattern's weight before any text is read; a bare verb without a target is no match."""
    if pattern & BARE and not pattern & AIMED:
        return 0.0
    return math.prod(x for label, x in PRIOR.items() if pattern & label)


class _Classes(dict):
    """Classes of words, found when first asked for; bounded."""

    def __init__(self, find):
        self.find = find

    def __missing__(self, w: bytes) -> int:
        if len(self) > 200_000:
            self.clear()
        self[w] = c = self.find(w)
        return c


class Grammar:
    """Word classes with weights, read through the composed clause transducer."""

    def __init__(self, words: dict[bytes, float], stems: dict[bytes, float], weights: tuple[float, ...] = (), bias: float = 0.0, machine: Transducer = CLAUSE):
        self.words, self.stems, self.bias, self.machine = words, stems, bias, machine
        self.weights = np.array(weights or [prior(p) for p in range(PATTERNS)])
        self.closed = {w.encode(): k for k, c in ((TARGET, TARGETS), (NOT, NEGATIONS), (REPORT, REPORTS)) for w in c}
        self.threats = {w.encode() for w in THREATS}
        self.known = _Classes(lambda w: self.symbol(w)[0])

    def __getstate__(self) -> dict:
        return {k: v for k, v in self.__dict__.items() if k != "known"}

    def __setstate__(self, state: dict) -> None:
        self.__dict__.update(state)
        self.known = _Classes(lambda w: self.symbol(w)[0])

    def symbol(self, w: bytes) -> tuple[int, float]:
        """(class, weight) of a word."""
        if (x := self.words.get(w)) is not None:
            return (THREAT if w in self.threats else INSULT, x)
        if kind := self.closed.get(w):
            return (kind, 0.0)
        if w in self.threats:
            return (VERB, THREAT_WEIGHT)
        best = max((self.stems.get(w[:n], 0.0) for n in STEM if n < len(w)), default=0.0)
        return (INSULT, best) if best > 0 else (OTHER, 0.0)

    def clause(self, words: list[bytes]) -> dict[int, float]:
        """The patterns that the composed transducer matches in one clause, with their weights."""
        classes = [self.known[w] for w in words]
        if max(classes) < INSULT:
            return {}
        step, state, found = self.machine.step, 0, []
        for w, c in zip(words, classes, strict=True):
            state, labels = step[state][c]
            if c >= INSULT:
                found.append((labels, self.symbol(w)[1]))
        whole = self.machine.final[state]
        out: dict[int, float] = {}
        for labels, x in found:
            if not labels & BARE or whole & AIMED:
                out[labels | whole] = out.get(labels | whole, 0.0) + x
        return out

    def strengths(self, text: bytes) -> np.ndarray:
        """The strength of every pattern in a text, over all its clauses."""
        out = np.zeros(PATTERNS)
        for words in clauses(text):
            for p, x in self.clause(words).items():
                out[p] += x**POWER
        return out ** (1 / POWER)

    def score(self, text: bytes) -> float:
        x = float(self.weights @ self.strengths(text)) + self.bias
        return 1 / (1 + math.exp(-min(60.0, max(-60.0, x))))


def _newton(x: np.ndarray, y: np.ndarray, at: np.ndarray, ridge: np.ndarray) -> np.ndarray:
    """The weights of a logistic fit that is damped around ``at``."""
    w = at.copy()
    for _ in range(100):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        grad = x.T @ (p - y) + ridge * (w - at)
        hess = (x * (p * (1 - p))[:, None]).T @ x + np.diag(ridge)
        step = np.linalg.solve(hess, grad)
        w = w - step
        if np.abs(step).max() < 1e-9:
            break
    return w


def weigh(strengths: np.ndarray, toxic: np.ndarray) -> tuple[tuple[float, ...], float]:
    """(weights of the patterns, bias) from the strengths of labelled texts.

    First one scale for all patterns at their prior, then each pattern on its own,
    damped around that; no pattern counts against toxicity.
    """
    start = np.array([prior(p) for p in range(PATTERNS)])
    one = np.ones((len(toxic), 1))
    scale, bias = _newton(np.hstack([strengths @ start[:, None], one]), toxic, np.zeros(2), np.full(2, 0.01))
    at = np.append(max(scale, 0.0) * start, bias)
    fitted = _newton(np.hstack([strengths, one]), toxic, at, np.append(np.full(PATTERNS, RIDGE), 0.01))
    weights = np.where(start > 0, np.maximum(fitted[:-1], 0.0), 0.0)
    return tuple(weights.tolist()), float(fitted[-1])


def _items(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(item, stem, fold, toxic, n): in how many texts of a batch a word or a stem is."""
    for batch in batches:
        for part in slices(batch, 2):
            found: Counter = Counter()
            for fold, toxic, t in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), as_bytes(part.column(2)), strict=True):
                own = {w for c in clauses(t) for w in c}
                found.update((w, False, fold, toxic) for w in own)
                found.update((s, True, fold, toxic) for s in {w[:n] for w in own for n in STEM if n < len(w)})
            columns = list(zip(*((*k, n) for k, n in found.items()), strict=True)) or [()] * 5
            kinds = (pa.binary(), pa.bool_(), pa.int32(), pa.int32(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], ["item", "stem", "fold", "toxic", "n"])


def _lexicons(texts: DataFrame, many: dict[tuple[int, int], int]) -> list[tuple[dict[bytes, float], dict[bytes, float]]]:
    """Lexicons of both folds and of all texts: (words, stems) with their smoothed log odds.

    A stem counts where several words of toxic texts begin with it. Counting is an
    aggregation; only items that a lexicon takes are collected.
    """
    n = lambda fold, toxic: F.coalesce(F.sum(F.when((F.col("fold") == fold) & (F.col("toxic") == toxic), F.col("n"))), F.lit(0))
    counted = texts.select("fold", "toxic", "text").mapInArrow(_items, "item binary, stem boolean, fold int, toxic int, n bigint")
    counted = counted.groupBy("item", "stem").agg(*[n(f, y).alias(f"n{f}{y}") for f in (0, 1) for y in (0, 1)])
    counted = materialize(counted, "toxicity-counts")
    words = counted.filter("NOT stem AND n01 + n11 > 0")
    begins = F.explode(F.filter(F.array(*[F.when(F.octet_length("item") > k, F.substring("item", 1, k)) for k in STEM]), lambda x: x.isNotNull()))
    forms = words.select(begins.alias("item"), "n01", "n11").groupBy("item")
    forms = forms.agg(F.count_if(F.col("n01") > 0).alias("f0"), F.count_if(F.col("n11") > 0).alias("f1"), F.count("*").alias("f2"))
    told = counted.join(forms.withColumn("stem", F.lit(True)), ["item", "stem"], "left")

    def column(fold: int, toxic: int) -> Column:
        return F.col(f"n{fold}{toxic}") if fold < 2 else F.col(f"n0{toxic}") + F.col(f"n1{toxic}")

    odds = []
    for fold in range(3):
        n0, n1 = (many.get((fold, y), 0) if fold < 2 else many.get((0, y), 0) + many.get((1, y), 0) for y in (0, 1))
        x = F.log((column(fold, 1) + 0.5) / (n1 + 1)) - F.log((column(fold, 0) + 0.5) / (n0 + 1))
        taken = (column(fold, 1) >= LEAST_TEXTS) & (x >= LEAST_ODDS) & (~F.col("stem") | (F.col(f"f{fold}") >= LEAST_FORMS))
        odds.append(F.when(taken, x).alias(f"x{fold}"))
    rows = told.select("item", "stem", *odds).filter("x0 IS NOT NULL OR x1 IS NOT NULL OR x2 IS NOT NULL").collect()
    out = []
    for fold in range(3):
        taken = sorted((bytes(r["item"]), r["stem"], r[f"x{fold}"]) for r in rows if r[f"x{fold}"] is not None)
        out.append(({w: x for w, stem, x in taken if not stem}, {w: x for w, stem, x in taken if stem}))
    return out


def learn(docs: DataFrame, labels: DataFrame, rows: int = FIT_ROWS) -> Grammar:
    """Fits on at most ``rows`` labelled documents outside the held-out fifth, by least hash.

    The texts stay on the executors: the driver gets the lexicon and, for each labelled
    text, the strengths of its patterns.
    """
    crc = lambda c: F.crc32(c.cast("string").cast("binary"))
    ids = labels.filter("toxic IS NOT NULL AND doc_id IS NOT NULL").select("doc_id", (F.col("toxic") > 0).cast("int").alias("toxic")).filter(crc(F.col("doc_id")) % 5 != 0)
    picked = ids.distinct().orderBy(F.xxhash64("doc_id"), "doc_id", "toxic").limit(rows)
    fold = F.pmod(F.xxhash64(F.lit(5), "doc_id"), F.lit(2)).cast("int").alias("fold")
    found = docs.select("doc_id", "text").join(F.broadcast(picked), "doc_id").groupBy("doc_id", "toxic").agg(F.min("text").alias("text"))
    texts = materialize(found.select(fold, "toxic", F.coalesce("text", F.lit("")).alias("text")), "toxicity-texts")
    many = {(r["fold"], r["toxic"]): r["n"] for r in texts.groupBy("fold", "toxic").agg(F.count("*").alias("n")).collect()}
    n, n1 = sum(many.values()), sum(x for (_, y), x in many.items() if y)
    if not n1 or n1 == n:
        rate = (n1 + 0.5) / (n + 1) if n else 0.25
        return Grammar({}, {}, (0.0,) * PATTERNS, math.log(rate / (1 - rate)))
    lexicons = _lexicons(texts, many)
    unseen = [Grammar(*lexicons[1]), Grammar(*lexicons[0])]  # a fold is read with the other's words

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, 2):
                made = [unseen[f].strengths(t).tolist() for f, t in zip(part.column(0).to_pylist(), as_bytes(part.column(2)), strict=True)]
                yield pa.RecordBatch.from_arrays([part.column(1), pa.array(made, pa.list_(pa.float64()))], ["toxic", "strengths"])

    read_rows = sorted((r["toxic"], r["strengths"]) for r in texts.mapInArrow(read, "toxic int, strengths array<double>").collect())  # at most ``rows``
    weights, bias = weigh(np.array([x for _, x in read_rows]), np.array([float(y) for y, _ in read_rows]))
    return Grammar(*lexicons[2], weights, bias)


def score(df: DataFrame, grammar: Grammar, text: str = "text", keep: tuple[str, ...] = ("doc_id",), out: str = "score") -> DataFrame:
    """``keep`` columns and the score of each text. One pass, no shuffle."""
    [own] = fresh([*keep, out], "text")
    picked = df.select(*[F.col(f"`{c}`") for c in keep], F.coalesce(F.col(f"`{text}`"), F.lit("")).alias(own))
    fields = "".join(f"`{f.name}` {f.dataType.simpleString()}, " for f in picked.schema.fields[:-1])
    at = len(keep)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, at):
                scores = [grammar.score(t) for t in as_bytes(part.column(at))]
                yield pa.RecordBatch.from_arrays([*part.columns[:at], pa.array(scores, pa.float64())], [*keep, out])

    return picked.mapInArrow(run, fields + f"`{out}` double")
