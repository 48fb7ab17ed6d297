"""License scans with a generalised suffix automaton over the tokens of license templates.

Every text is streamed once through the automaton.  At each word the automaton holds the longest
run of words ending there that occurs in some template (the matching statistics); its links lead to the
shorter runs that other templates, or other places, share with it.  A run that cannot be extended at a
place of a template is kept for that place when long enough.  The runs of a template are chained in its order
for the most words, and a chain that covers enough of its template becomes a span with the template's
label, unless a template of another label explains the same stretch of text better.
"""

from __future__ import annotations

from bisect import bisect_left
from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ship
from .license_texts import LICENSES

# Phrases counted as they stand, with their labels.
PHRASES = {
    "cc by": "cc-by",
    "general public license": "gpl",
    "all rights reserved": "reserved",
}

# Short notices of common public licenses, with their labels.
TEMPLATES = {
    "mit-notice": ("mit", "released under the mit license"),
    "mit-notice-2": ("mit", "licensed under the mit license"),
    "mit-grant": (
        "mit",
        "permission is hereby granted free of charge to any person obtaining a copy of this software and"
        " associated documentation files the software to deal in the software without restriction including"
        " without limitation the rights to use copy modify merge publish distribute sublicense and or sell"
        " copies of the software",
    ),
    "apache-notice": ("apache-2.0", "licensed under the apache license version 2 0"),
    "apache-header": (
        "apache-2.0",
        "you may not use this file except in compliance with the license you may obtain a copy of the license"
        " at http www apache org licenses license 2 0",
    ),
    "gpl3-notice": ("gpl-3.0", "this work is licensed under the gnu general public license version 3"),
    "gpl-header": (
        "gpl",
        "this program is free software you can redistribute it and or modify it under the terms of the gnu"
        " general public license as published by the free software foundation",
    ),
    "lgpl-notice": ("lgpl", "under the terms of the gnu lesser general public license"),
    "agpl-notice": ("agpl", "under the terms of the gnu affero general public license"),
    "bsd-terms": (
        "bsd",
        "redistribution and use in source and binary forms with or without modification are permitted provided"
        " that the following conditions are met",
    ),
    "mpl-notice": (
        "mpl-2.0",
        "this source code form is subject to the terms of the mozilla public license v 2 0",
    ),
    "cc-by-notice": (
        "cc-by-4.0",
        "this work is licensed under a creative commons attribution 4 0 international license",
    ),
    "cc-by-sa-notice": (
        "cc-by-sa-4.0",
        "this work is licensed under a creative commons attribution sharealike 4 0 international license",
    ),
    "cc-by-short": ("cc-by-4.0", "licensed under cc by 4 0"),
    "cc-by-sa-short": ("cc-by-sa-4.0", "licensed under cc by sa 4 0"),
    "cc0-notice": ("cc0", "to the extent possible under law the author has waived all copyright"),
    "reserved-notice": ("reserved", "copyright all rights reserved"),
    "unlicense": ("unlicense", "this is free and unencumbered software released into the public domain"),
    "isc-grant": (
        "isc",
        "permission to use copy modify and or distribute this software for any purpose with or without fee is"
        " hereby granted",
    ),
}

# Word bytes stay (letters in lower case), all others become spaces.
_WORD = bytes(
    b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256)
)


def words_of(text: str | None) -> list[bytes]:
    """Words of ASCII letters and digits and of anything beyond ASCII, A-Z in lower case, as UTF-8."""
    return (text or "").encode("utf-8", "surrogatepass").translate(_WORD).split()


Run = tuple[int, int, int]  # first word in the text, first word in the template, words


@dataclass
class Automaton:
    """Suffix automaton of several token sequences; a state knows where its strings end in each template."""

    next: list[dict[int, int]] = field(default_factory=lambda: [{}])
    link: list[int] = field(default_factory=lambda: [-1])
    length: list[int] = field(default_factory=lambda: [0])
    ends: list[dict[int, list[int]]] = field(default_factory=lambda: [{}])
    paths: list[tuple[int, list[int]]] = field(default_factory=list)

    def _state(self, length: int, link: int, nxt: dict[int, int]) -> int:
        self.next.append(nxt)
        self.link.append(link)
        self.length.append(length)
        self.ends.append({})
        return len(self.next) - 1

    def _split(self, p: int, q: int, token: int) -> int:
        """A copy of q for the shorter strings that end in p's string and the token."""
        copy = self._state(self.length[p] + 1, self.link[q], dict(self.next[q]))
        self.link[q] = copy
        while p != -1 and self.next[p].get(token) == q:
            self.next[p][token] = copy
            p = self.link[p]
        return copy

    def _extend(self, last: int, token: int) -> int:
        known = self.next[last].get(token)
        if known is not None:
            return known if self.length[known] == self.length[last] + 1 else self._split(last, known, token)
        new, p = self._state(self.length[last] + 1, 0, {}), last
        while p != -1 and token not in self.next[p]:
            self.next[p][token] = new
            p = self.link[p]
        if p != -1:
            q = self.next[p][token]
            self.link[new] = q if self.length[q] == self.length[p] + 1 else self._split(p, q, token)
        return new

    def add(self, template: int, tokens: list[int]) -> None:
        last = 0
        for token in tokens:
            last = self._extend(last, token)
        self.paths.append((template, tokens))

    def finish(self) -> "Automaton":
        """Walk every template again and leave its end positions on the states and their links."""
        for template, tokens in self.paths:
            state = 0
            for i, token in enumerate(tokens):
                state = self.next[state][token]
                up = state
                while up > 0:
                    self.ends[up].setdefault(template, []).append(i)
                    up = self.link[up]
        return self


class Scanner:
    """The automaton of given phrases and templates, ready to scan texts."""

    def __init__(
        self,
        templates: dict[str, tuple[str, str]] = TEMPLATES | LICENSES,
        phrases: dict[str, str] = PHRASES,
        min_run: int = 3,
        max_gap: int = 8,
        min_cover: float = 0.8,
    ):
        self.min_run, self.max_gap, self.min_cover = min_run, max_gap, min_cover
        self.vocab: dict[bytes, int] = {}
        number = lambda t: [self.vocab.setdefault(w, len(self.vocab) + 1) for w in words_of(t)]
        self.templates = [(name, label, number(text)) for name, (label, text) in sorted(templates.items())]
        self.phrases = [(label, number(text)) for text, label in sorted(phrases.items())]
        machine = Automaton()
        for k, (_, _, tokens) in enumerate(self.templates):
            machine.add(k, tokens)
        for k, (_, tokens) in enumerate(self.phrases):
            machine.add(-1 - k, tokens)
        machine.finish()
        self.next, self.link, self.length, self.ends = machine.next, machine.link, machine.length, machine.ends
        # phrase states: which phrases end in a state's string, found along its links
        own: dict[int, list[int]] = defaultdict(list)
        for k, (_, tokens) in enumerate(self.phrases):
            state = 0
            for t in tokens:
                state = self.next[state][t]
            own[state].append(k)
        self.endings: list[list[int]] = []
        for state in range(len(self.next)):
            found, up = [], state
            while up > 0:
                found += own.get(up, [])
                up = self.link[up]
            self.endings.append(found)
        # places of templates where a state's string or a suffix of it ends: (template, place, longest match, next token)
        self.matches: list[list[tuple[int, int, int, int]]] = []
        for state in range(len(self.next)):
            seen: dict[tuple[int, int], int] = {}
            up = state
            while up > 0 and self.length[up] >= min_run:
                for template, ends in self.ends[up].items():
                    if template >= 0:
                        for end in ends:
                            seen.setdefault((template, end), self.length[up])
                up = self.link[up]
            after = lambda t, e: self.templates[t][2][e + 1] if e + 1 < len(self.templates[t][2]) else -1
            self.matches.append([(t, e, size, after(t, e)) for (t, e), size in seen.items()])

    def statistics(self, ids: list[int]) -> Iterator[tuple[int, int, int]]:
        """(place, length, state) for every known word; unknown words (0) bring the automaton to its root."""
        state = size = 0
        before = -2
        nxt, link, length = self.next, self.link, self.length
        for i, token in enumerate(ids):
            if not token:
                continue
            if before != i - 1:
                state = size = 0
            before = i
            step = nxt[state].get(token)
            while step is None and state:
                state = link[state]
                size = length[state]
                step = nxt[state].get(token)
            if step is None:
                state = size = 0
            else:
                state, size = step, size + 1
            yield i, size, state

    def scan(self, text: str | None) -> dict:
        """n_words, places of phrases [(start, label)], spans [(start, end, label, cover)]."""
        words = words_of(text)
        ids = list(map(self.vocab.get, words, (0,) * len(words)))
        places: list[tuple[int, str]] = []
        runs: dict[int, list[Run]] = defaultdict(list)
        for i, size, state in self.statistics(ids):
            for k in self.endings[state]:
                label, tokens = self.phrases[k]
                if len(tokens) <= size:
                    places.append((i - len(tokens) + 1, label))
            if size >= self.min_run:
                follows = ids[i + 1] if i + 1 < len(ids) else 0
                for template, end, most, after in self.matches[state]:
                    if after != follows:
                        n = min(size, most)
                        runs[template].append((i - n + 1, end - n + 1, n))
        return {"n_words": len(words), "places": places, "spans": self.spans(runs)}

    def chains(self, runs: list[Run]) -> list[tuple[int, int, int, int]]:
        """(words covered, -runs, -template's words left out between them, first word) of the best chain that ends in
        each of one template's sorted runs.

        Runs follow each other in text and template with gaps up to max_gap words; what overlaps counts once."""
        best: list[tuple[int, int, int, int]] = []
        longest = max((size for _, _, size in runs), default=0)
        for j, (start, at, size) in enumerate(runs):
            top = (size, -1, 0, start)
            for i in range(j - 1, -1, -1):
                begin, place, n = runs[i]
                if begin + longest + self.max_gap < start:
                    break
                cut = max(0, begin + n - start, place + n - at)
                if cut < size and start + cut - begin - n <= self.max_gap and at + cut - place - n <= self.max_gap:
                    words, number, out, first = best[i]
                    top = max(top, (words + size - cut, number - 1, out - (at + cut - place - n), first))
            best.append(top)
        return best

    def within(self, runs: list[Run], low: int, high: int, longest: int) -> list[Run]:
        """The parts of sorted runs in the words from low up to high."""
        out = []
        for k in range(bisect_left(runs, (low - longest, 0, 0)), len(runs)):
            start, at, size = runs[k]
            if start >= high:
                break
            skip = max(0, low - start)
            size = min(start + size, high) - start - skip
            if size >= self.min_run:
                out.append((start + skip, at + skip, size))
        return sorted(out)

    def covered(self, runs: list[Run], length: int) -> list[tuple[int, int, int, int, int]]:
        """(first word, next word, words covered, -runs, -words left out) of one template's chains that cover enough and don't overlap."""
        out, parts = [], [runs]
        while parts:
            part = parts.pop()
            found = [
                (-words, -number, -out, start + size - first, first)
                for (words, number, out, first), (start, _, size) in zip(self.chains(part), part)
                if words >= self.min_cover * length
            ]
            taken: list[tuple[int, int]] = []
            for words, number, left, wide, first in sorted(found):
                k = bisect_left(taken, (first, first))
                if (k == 0 or taken[k - 1][1] <= first) and (k == len(taken) or taken[k][0] >= first + wide):
                    taken.insert(k, (first, first + wide))
                    out.append((first, first + wide, -words, -number, -left))
            if taken:
                edges = [part[0][0], *(e for t in taken for e in t), max(start + size for start, _, size in part)]
                rest = [self.within(part, low, high, length) for low, high in zip(edges[::2], edges[1::2]) if low < high]
                parts += [r for r in rest if r]
        return out

    def spans(self, runs: dict[int, list[Run]]) -> list[tuple[int, int, str, float]]:
        """Chains that cover enough of their template, less those whose words a template of another label explains better:
        by more words, by as many in fewer runs, with fewer words of the template left out between these, or else by more
        of the template."""
        runs = {template: sorted(found) for template, found in runs.items()}
        spans = []
        for template, found in runs.items():
            _, label, tokens = self.templates[template]
            for start, end, words, number, left in self.covered(found, len(tokens)):
                mine = (words, number, left, words / len(tokens))
                for other, theirs in runs.items():
                    _, name, text = self.templates[other]
                    if name != label:
                        part = self.within(theirs, start, end, len(text))
                        if any((w, n, o, w / len(text)) > mine for w, n, o, _ in self.chains(part)):
                            break
                else:
                    spans.append((start, end, label, mine[3]))
        return sorted(set(spans))


SCHEMA = (
    "{key} bigint, n_words bigint, n_base bigint, first_word bigint, last_word bigint, base_labels string,"
    " labels string, score double, spans array<struct<start:bigint,`end`:bigint,label:string,cover:double>>"
)

_SCANNERS: dict[str, Scanner] = {}


def scan_licenses(df: DataFrame, key: str = "doc_id", text: str = "text", **settings) -> DataFrame:
    """One row for each row of df, with phrase places, labels and covered template spans.

    A null or empty text has no words, no places, empty labels and score 0.  Repeated rows each get their row;
    a null key stays null; an empty table gives an empty result; other columns are not read, so their names may clash
    with the result's.  The score is the largest part of a template that a span covers, and 1 where a phrase stands in
    the text.  Of chains that cover as many words the one of fewer runs stays, then the shorter and the earlier one.  A
    very long text is streamed whole, and a chain looks back as far as its template's longest run and the gap reach.
    Rows stream through one narrow pass: no shuffle, memory bounded by a batch and one text's runs."""
    ship(df.sparkSession)
    rows = df.select(F.col(key).cast("bigint").alias("key"), F.col(text).cast("string").alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        name = repr(sorted(settings.items()))
        scanner = _SCANNERS[name] = _SCANNERS.get(name) or Scanner(**settings)
        for batch in batches:
            out = [scanner.scan(t.as_py()) for t in batch.column(1)]
            starts = [[p for p, _ in x["places"]] for x in out]
            base = [sorted({n for _, n in x["places"]}) for x in out]
            arrays = [
                batch.column(0),
                pa.array([x["n_words"] for x in out], pa.int64()),
                pa.array([len(s) for s in starts], pa.int64()),
                pa.array([min(s, default=None) for s in starts], pa.int64()),
                pa.array([max(s, default=None) for s in starts], pa.int64()),
                pa.array([",".join(b) for b in base], pa.string()),
                pa.array([",".join(sorted({*b, *(s[2] for s in x["spans"])})) for b, x in zip(base, out)], pa.string()),
                pa.array([1.0 if b else max((min(1.0, s[3]) for s in x["spans"]), default=0.0) for b, x in zip(base, out)], pa.float64()),
                pa.array(
                    [[dict(zip(("start", "end", "label", "cover"), s)) for s in x["spans"]] for x in out],
                    pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("label", pa.string()), ("cover", pa.float64())])),
                ),
            ]
            names = ["key", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score", "spans"]
            yield pa.RecordBatch.from_arrays(arrays, names=names)

    return rows.mapInArrow(run, SCHEMA.format(key="key")).withColumnRenamed("key", key)
