"""Licence scans: matching statistics against a generalised suffix automaton of template tokens.

The automaton holds the word sequences of all templates.  A file is streamed through it once: at
each word the automaton knows the longest run of words ending there that some template holds.  Runs
of at least ``least`` words are chained, in template order, into spans that cover a template.  A span
that covers at least the share ``cover`` of its template gives the template's label.  The score is the
largest share of a template, among those of the labels found, that one span or base phrase covers.

Null and empty texts have no words and no labels; null first and last words, score 0.  Repeated
rows are scanned apart.  Extra columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame

#: Public licence notices, short ones whole and opening words of longer ones, by label.
TEMPLATES = {
    "apache": (
        "licensed under the apache license version 2.0 the license you may not use this file except in compliance with the license",
        "unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis",
        "licensed under the apache license version 2.0",
    ),
    "bsd": (
        "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met",
        "redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer",
        "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met "
        "redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer "
        "redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution "
        "this software is provided by the copyright holders and contributors as is and any express or implied warranties including but not limited to the implied warranties of merchantability and fitness for a particular purpose are disclaimed",
    ),
    "cc-by": (
        "this work is licensed under a creative commons attribution 4.0 international license",
        "this work is licensed under cc by 4.0",
    ),
    "gpl": (
        "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation",
        "this work is licensed under the gnu general public license version 3",
    ),
    "mit": (
        "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files",
        "the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability",
        "released under the mit license",
        "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction "
        "including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions "
        "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software "
        "the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability fitness for a particular purpose and noninfringement "
        "in no event shall the authors or copyright holders be liable for any claim damages or other liability whether in an action of contract tort or otherwise arising from out of or in connection with the software or the use or other dealings in the software",
    ),
    "isc": (
        "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies",
    ),
    "mpl": ("this source code form is subject to the terms of the mozilla public license v 2.0",),
    "reserved": ("all rights reserved",),
}

#: Phrases that are always reported, with their labels.
BASE_PHRASES = (("cc by", "cc-by"), ("general public license", "gpl"), ("all rights reserved", "reserved"))

#: Upper case to lower, other ASCII but digits and lower case to a space; bytes of 0x80 and over stay.
_FOLD = bytes(b + 32 if 0x41 <= b <= 0x5A else b if b >= 0x80 or 0x30 <= b <= 0x39 or 0x61 <= b <= 0x7A else 0x20 for b in range(256))


def scan_words(text: bytes) -> list[bytes]:
    return text.translate(_FOLD).split()


@dataclass
class SuffixAutomaton:
    """A generalised suffix automaton over integer tokens, built one template after another.

    ``length``, ``link`` and ``step`` are the usual longest length, suffix link and transitions;
    ``ends`` gives for each state one (template, position) where its words end.
    """

    length: list[int] = field(default_factory=lambda: [0])
    link: list[int] = field(default_factory=lambda: [-1])
    step: list[dict[int, int]] = field(default_factory=lambda: [{}])
    ends: list[list[tuple[int, int]]] = field(default_factory=lambda: [[]])

    def _state(self, length: int, link: int, step: dict[int, int]) -> int:
        self.length.append(length)
        self.link.append(link)
        self.step.append(step)
        self.ends.append([])
        return len(self.length) - 1

    def _split(self, at: int, token: int, to: int) -> int:
        """The state for exactly the runs that reach ``to`` through ``at``."""
        if self.length[to] == self.length[at] + 1:
            return to
        copy = self._state(self.length[at] + 1, self.link[to], dict(self.step[to]))
        self.link[to] = copy
        while at != -1 and self.step[at].get(token) == to:
            self.step[at][token] = copy
            at = self.link[at]
        return copy

    def add(self, template: int, tokens: list[int]) -> None:
        last = 0
        for position, token in enumerate(tokens):
            if token in self.step[last]:  # some template already has this run
                last = self._split(last, token, self.step[last][token])
            else:
                new, at = self._state(self.length[last] + 1, 0, {}), last
                while at != -1 and token not in self.step[at]:
                    self.step[at][token] = new
                    at = self.link[at]
                if at != -1:
                    self.link[new] = self._split(at, token, self.step[at][token])
                last = new
            self.ends[last].append((template, position))

    def close(self) -> None:
        """Each state gets the ends of the longer runs that end with it."""
        for s in sorted(range(1, len(self.length)), key=self.length.__getitem__, reverse=True):
            if self.link[s] > 0:
                self.ends[self.link[s]].extend(self.ends[s])

    def statistics(self, tokens, state: int = 0, matched: int = 0):
        """(state, length of the longest match ending there) after each token; None resets."""
        for token in tokens:
            if token is None:
                state = matched = 0
            else:
                while state and token not in self.step[state]:
                    state = self.link[state]
                    matched = self.length[state]
                if token in self.step[state]:
                    state, matched = self.step[state][token], matched + 1
                else:
                    state = matched = 0
            yield state, matched


@dataclass(frozen=True)
class Hit:
    label: str
    first: int
    last: int
    covered: float


class LicenceScanner:
    def __init__(self, templates: dict[str, tuple[str, ...]] | None = None, phrases=BASE_PHRASES, least: int = 3, cover: float = 0.8):
        self.least, self.cover = least, cover
        self.vocabulary: dict[bytes, int] = {}
        self.labels: list[str] = []
        self.sizes: list[int] = []
        self.automaton = SuffixAutomaton()
        for label, texts in (TEMPLATES if templates is None else templates).items():
            for text in texts:
                tokens = [self.vocabulary.setdefault(w, len(self.vocabulary)) for w in scan_words(text.encode())]
                self.automaton.add(len(self.sizes), tokens)
                self.labels.append(label)
                self.sizes.append(len(tokens))
        self.automaton.close()
        self.phrases = [(scan_words(p.encode()), label) for p, label in phrases]
        for words, _ in self.phrases:
            for w in words:
                self.vocabulary.setdefault(w, len(self.vocabulary))
        # the share of its label's shortest template that a base phrase is
        self.phrase_cover = {label: min(1.0, len(words) / min((n for n, own in zip(self.sizes, self.labels) if own == label), default=len(words))) for words, label in self.phrases}

    def runs(self, words: list[bytes]):
        """(start, tokens) of maximal stretches of words that templates or phrases use."""
        ids = list(map(self.vocabulary.get, words))
        at = [i for i, x in enumerate(ids) if x is not None]
        lo = 0
        for k in range(1, len(at) + 1):
            if k == len(at) or at[k] != at[k - 1] + 1:
                yield at[lo], ids[at[lo] : at[k - 1] + 1]
                lo = k

    def base(self, words: list[bytes]) -> list[tuple[int, str]]:
        """(start, label) of every place of every base phrase."""
        found = []
        for phrase, label in self.phrases:
            at = -1
            for _ in range(words.count(phrase[-1])):
                at = words.index(phrase[-1], at + 1)
                start = at - len(phrase) + 1
                if start >= 0 and words[start : at + 1] == phrase:
                    found.append((start, label))
        return found

    def hits(self, words: list[bytes]) -> list[Hit]:
        """Templates of which chained matches cover at least the wanted share."""
        return [h for h in self.spans(words) if h.covered >= self.cover]

    def spans(self, words: list[bytes]) -> list[Hit]:
        """Chained matches with the share of their template that they cover."""
        pieces: dict[int, list[tuple[int, int, int]]] = {}
        for start, tokens in self.runs(words):
            if len(tokens) < self.least:
                continue
            stats = list(self.automaton.statistics(tokens))
            for k, (state, n) in enumerate(stats):
                if n < self.least or k + 1 < len(stats) and stats[k + 1][1] == n + 1:
                    continue  # a longer match follows
                for template, position in self.automaton.ends[state]:
                    pieces.setdefault(template, []).append((start + k - n + 1, position - n + 1, n))
        out = []
        for template, found in pieces.items():
            for first, last, words_covered in self._chains(sorted(found), self.sizes[template]):
                out.append(Hit(self.labels[template], first, last, min(1.0, words_covered / self.sizes[template])))
        return out

    def _chains(self, found, size: int):
        """Matches in text and template order, with gaps of at most half the template, joined."""
        chain: tuple[int, int, int, int] | None = None  # first word, last word, template end, covered
        for at, position, n in found:
            if chain and position >= chain[2] and at > chain[1] and at - chain[1] <= max(2, size // 2):
                chain = (chain[0], at + n - 1, position + n, chain[3] + n)
            else:
                if chain:
                    yield chain[0], chain[1], chain[3]
                chain = (at, at + n - 1, position + n, n)
        if chain:
            yield chain[0], chain[1], chain[3]

    def scan(self, text: bytes) -> dict:
        words = scan_words(text)
        base = self.base(words)
        spans = self.spans(words)
        hits = [h for h in spans if h.covered >= self.cover]
        labels = {label for _, label in base}
        found = labels | {h.label for h in hits}
        return {
            "n_words": len(words), "n_base": len(base), "first_word": min((s for s, _ in base), default=None), "last_word": max((s for s, _ in base), default=None),
            "base_labels": ",".join(sorted(labels)), "labels": ",".join(sorted(found)),
            "score": max([h.covered for h in spans if h.label in found] + [self.phrase_cover[label] for label in labels], default=0.0),
            "spans": [{"label": h.label, "first": h.first, "last": h.last, "covered": h.covered} for h in hits],
        }


SCHEMA = "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, spans array<struct<label:string,first:long,last:long,covered:double>>"
_ARROW = pa.schema([
    ("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_base", pa.int64()), ("first_word", pa.int64()), ("last_word", pa.int64()), ("base_labels", pa.string()), ("labels", pa.string()), ("score", pa.float64()),
    ("spans", pa.list_(pa.struct([("label", pa.string()), ("first", pa.int64()), ("last", pa.int64()), ("covered", pa.float64())]))),
])


def scan_licences(df: DataFrame, templates: dict | None = None, least: int = 3, cover: float = 0.8) -> DataFrame:
    """doc_id, counts and labels of the base phrases, labels with the method's, score, covered spans."""

    def run(batches):
        scanner = LicenceScanner(templates, least=least, cover=cover)
        for batch in batches:
            rows = [{"doc_id": d} | scanner.scan((t or "").encode()) for d, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist())]
            yield pa.RecordBatch.from_pylist(rows, schema=_ARROW)

    return df.select(df.doc_id.cast("long").alias("doc_id"), "text").mapInArrow(run, SCHEMA)
