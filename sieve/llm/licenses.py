"""Licence scan by a generalised suffix automaton of licence tokens.

The automaton holds every token substring of every template. A file is streamed
through it once: the state after each token is the longest suffix of what was read
that occurs in some template (its matching statistic), with one place where it
occurs. Maximal matches of enough tokens are chained per template, in file and
template order, and the template tokens the chain covers give the span's score.
Base phrases are found exactly: a place ends where the match is at least as long
as the phrase and the phrase is a suffix of the state, a fact kept per state.

Cases: a null or empty text has no words, spans or labels and scores 0; long texts
are streamed whole; repeated rows repeat their result; an empty table gives an
empty table; other columns are not read.
"""

from __future__ import annotations

from bisect import bisect_right
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sieve.llm.text import as_bytes, fresh, slices

#: Phrases looked for at every place, with their labels.
PHRASES = (
    ("under the mit license", "mit"),
    ("apache license version 2", "apache-2"),
    ("cc by nc", "cc-by-nc"),
)

#: Notices of public licences, with the labels the chains earn.
TEMPLATES = (
    ("mit", "Released under the MIT License."),
    ("mit", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software"),
    ("apache-2", "Licensed under the Apache License, Version 2.0."),
    ("apache-2", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at"),
    ("cc-by-nc", "Licensed under CC BY-NC 4.0."),
    ("cc-by-nc", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    ("cc-by", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("gpl-3", "This work is licensed under the GNU General Public License, version 3."),
    ("gpl-3", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."),
    ("bsd", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"),
    ("mpl-2", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("isc", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
)
#: A match counts from so many tokens; a chain earns its label from this share of its template.
LEAST_MATCH, LEAST_COVER = 3, 0.8

_TO_SPACE = bytes(c if 0x30 <= c <= 0x39 or 0x61 <= c <= 0x7A or c >= 0x80 else 0x20 for c in range(256))


def words_of(text: bytes) -> list[bytes]:
    """Lower-cased (A-Z) runs of digits, letters a-z and bytes from 0x80."""
    return text.lower().translate(_TO_SPACE).split()


@dataclass
class Automaton:
    """Generalised suffix automaton over small token numbers."""

    step: list[dict[int, int]] = field(default_factory=lambda: [{}])
    link: list[int] = field(default_factory=lambda: [-1])
    length: list[int] = field(default_factory=lambda: [0])
    ends: list[set] = field(default_factory=lambda: [set()])

    def _state(self, length: int, step: dict[int, int], link: int) -> int:
        self.step.append(step)
        self.link.append(link)
        self.length.append(length)
        self.ends.append(set())
        return len(self.step) - 1

    def _split(self, p: int, c: int, q: int) -> int:
        clone = self._state(self.length[p] + 1, dict(self.step[q]), self.link[q])
        self.link[q] = clone
        while p >= 0 and self.step[p].get(c) == q:
            self.step[p][c] = clone
            p = self.link[p]
        return clone

    def _append(self, last: int, c: int) -> int:
        if c in self.step[last]:  # the prefix is there already, from an earlier template
            q = self.step[last][c]
            return q if self.length[q] == self.length[last] + 1 else self._split(last, c, q)
        new, p = self._state(self.length[last] + 1, {}, 0), last
        while p >= 0 and c not in self.step[p]:
            self.step[p][c] = new
            p = self.link[p]
        if p >= 0:
            q = self.step[p][c]
            self.link[new] = q if self.length[q] == self.length[p] + 1 else self._split(p, c, q)
        return new

    def add(self, tokens: list[int], number: int) -> None:
        """Adds a template; every state keeps where its strings end in it."""
        last = 0
        for c in tokens:
            last = self._append(last, c)
        state = 0
        for at, c in enumerate(tokens):
            state = self.step[state][c]
            self.ends[state].add((number, at + 1))

    def finish(self) -> None:
        """Hands end places up the suffix links, longest strings first."""
        for v in sorted(range(1, len(self.length)), key=lambda v: -self.length[v]):
            if self.link[v] > 0:
                self.ends[self.link[v]] |= self.ends[v]


class Scanner:
    """Templates and phrases compiled for streaming."""

    def __init__(self, templates: tuple = TEMPLATES, phrases: tuple = PHRASES, least_match: int = LEAST_MATCH, least_cover: float = LEAST_COVER):
        self.least_match, self.least_cover = least_match, least_cover
        self.vocabulary: dict[bytes, int] = {}
        number = lambda s: [self.vocabulary.setdefault(w, len(self.vocabulary)) for w in words_of(s.encode())]
        self.labels = [x[0] for x in templates]
        texts = [number(x[1]) for x in templates]
        said = [number(x[0]) for x in phrases]
        self.sizes = [len(x) for x in texts]
        self.phrase_labels = [x[1] for x in phrases]
        a = self.a = Automaton()
        for k, tokens in enumerate([*texts, *said]):
            a.add(tokens, k)
        for v in range(len(a.ends)):  # only the templates' places make chains
            a.ends[v] = {x for x in a.ends[v] if x[0] < len(texts)}
        a.finish()
        # For each state the phrases that are suffixes of its longest string.
        at: dict[int, list[tuple[int, int]]] = {}
        for k, tokens in enumerate(said):
            v = 0
            for c in tokens:
                v = a.step[v][c]
            at.setdefault(v, []).append((len(tokens), k))
        self.phrases: list[tuple] = [()] * len(a.step)
        for v in sorted(range(1, len(a.step)), key=lambda v: a.length[v]):
            self.phrases[v] = (*at.get(v, ()), *self.phrases[a.link[v]])

    def scan(self, text: bytes) -> dict:
        """Words, places of phrases as (start, phrase), chains as (start, end, template, share)."""
        words = words_of(text)
        get, a = self.vocabulary.get, self.a
        step, link, length, phrases = a.step, a.link, a.length, self.phrases
        places: list[tuple[int, int]] = []
        matches: list[tuple[int, int, int]] = []  # (end, length, state) of maximal matches
        state = n = 0
        for i, w in enumerate(words):
            c = get(w)
            if c is None:
                if n >= self.least_match:
                    matches.append((i, n, state))
                state = n = 0
                continue
            if c not in step[state]:
                if n >= self.least_match:
                    matches.append((i, n, state))
                while state and c not in step[state]:
                    state = link[state]
                    n = length[state]
            if c in step[state]:
                state = step[state][c]
                n += 1
            for size, k in phrases[state]:
                if n >= size:
                    places.append((i + 1 - size, k))
        if n >= self.least_match:
            matches.append((len(words), n, state))
        return {"n_words": len(words), "places": places, "spans": self.chain(matches)}

    def chain(self, matches: list[tuple[int, int, int]]) -> list[tuple[int, int, int, float]]:
        """Chains matches in file and template order; gaps stay below a template's length."""
        done: dict[int, list[list[int]]] = {}
        open_: dict[int, list[list[int]]] = {}  # template -> chains of [start, end, template end, covered]
        for end, n, state in matches:
            places: dict[int, list[int]] = {}
            for t, at in sorted(self.a.ends[state]):
                places.setdefault(t, []).append(at)
            for t, ats in places.items():
                near = [x for x in open_.get(t, ()) if end - n < x[1] + self.sizes[t]]
                new = [[end - n, end, ats[0], n]]  # a match may begin a copy
                for x in near:  # or go on with any chain that it goes forward from; the chain as it was stays too
                    at = next((a for a in ats if a > x[2]), None)
                    if at is not None:
                        new.append([x[0], end, at, x[3] + min(n, end - x[1], at - x[2])])
                # Of chains that end here, one that starts earlier must cover more or leave more of the template.
                new.sort(key=lambda x: (-x[0], -x[3], x[2]))
                kept: list[list[int]] = []
                for x in new:
                    if not any(y[3] >= x[3] and y[2] <= x[2] for y in kept):
                        kept.append(x)
                done.setdefault(t, []).extend(kept)
                open_[t] = near + kept
        return sorted((x[0], x[1], t, x[3] / self.sizes[t]) for t, chains in done.items() for x in self.best(chains, self.sizes[t]))

    def best(self, chains: list[list[int]], size: int) -> list[list[int]]:
        """Chains that do not overlap: the most cover by chains that earn the label, then the most cover."""
        chains = sorted(chains, key=lambda x: (x[1], -x[0]))
        ends = [x[1] for x in chains]
        total: list[tuple[int, int]] = [(0, 0)]
        for i, x in enumerate(chains):
            good, all_ = total[bisect_right(ends, x[0], 0, i)]
            total.append(max(total[-1], (good + x[3] * (x[3] >= self.least_cover * size), all_ + x[3])))
        out, i = [], len(chains)
        while i:
            if total[i] != total[i - 1]:
                out.append(chains[i - 1])
                i = bisect_right(ends, chains[i - 1][0], 0, i - 1)
            else:
                i -= 1
        return out

    def digest(self, text: bytes) -> dict:
        """What a file is told to be: places, labels, score and its best spans."""
        found = self.scan(text)
        base = {self.phrase_labels[k] for _, k in found["places"]}
        good = [s for s in found["spans"] if s[3] >= self.least_cover]
        labels = base | {self.labels[s[2]] for s in good}
        first = [p for p, _ in found["places"]]
        score = 1.0 if base else max((s[3] for s in found["spans"]), default=0.0)
        return {
            "n_words": found["n_words"], "n_base": len(first), "first_word": min(first, default=None), "last_word": max(first, default=None),
            "base_labels": ",".join(sorted(base)), "labels": ",".join(sorted(labels)), "score": min(1.0, score),
            "spans": [{"start": s[0], "end": s[1], "label": self.labels[s[2]], "share": s[3]} for s in good],
        }


FIELDS = "n_words bigint, n_base bigint, first_word bigint, last_word bigint, base_labels string, labels string, score double, spans array<struct<start:bigint,end:bigint,label:string,share:double>>"
_SPAN = pa.struct([("start", pa.int64()), ("end", pa.int64()), ("label", pa.string()), ("share", pa.float64())])
_KINDS = {"n_words": pa.int64(), "n_base": pa.int64(), "first_word": pa.int64(), "last_word": pa.int64(), "base_labels": pa.string(), "labels": pa.string(), "score": pa.float64(), "spans": pa.list_(_SPAN)}


def scan(df: DataFrame, text: str = "text", keep: tuple[str, ...] = ("doc_id",), templates: tuple = TEMPLATES, phrases: tuple = PHRASES) -> DataFrame:
    """``keep`` columns with phrase places, labels, score and covered template spans."""
    [own] = fresh([*keep, *_KINDS], "text")
    picked = df.select(*[F.col(f"`{c}`") for c in keep], F.coalesce(F.col(f"`{text}`"), F.lit("")).alias(own))
    fields = "".join(f"`{f.name}` {f.dataType.simpleString()}, " for f in picked.schema.fields[:-1])
    at = len(keep)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = Scanner(templates, phrases)
        for batch in batches:
            for part in slices(batch, at):
                rows = [scanner.digest(t) for t in as_bytes(part.column(at))]
                yield pa.RecordBatch.from_arrays([*part.columns[:at], *(pa.array([r[k] for r in rows], v) for k, v in _KINDS.items())], [*keep, *_KINDS])

    return picked.mapInArrow(run, fields + FIELDS)
