"""License scans (6): phrases, and template markup compiled into token automata.

A template is a license or notice text in which ``{? ... ?}`` is optional and ``{= a-b =}`` stands for a
to b replaceable words. It compiles into an automaton over words with edges for a given word, for any
word, and for none; a text is accepted if from some place on its words run through an automaton to the
end, so that all mandatory wording stands there exactly. Automata only run on texts that hold one of the
anchor words, found by hash for all words at once.

Defined cases: a null or empty text has no words, no labels and score 0; null ids and repeated rows are
rows like others; ties can't arise, labels are sorted sets; an empty table gives an empty result. Extra
columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels as K
from .shared import text_parts

#: Phrases and their labels.
PHRASES = {"gnu general public license": "gpl", "apache license": "apache", "cc by": "cc-by", "mit license": "mit"}

#: Well-known notices and license texts, as templates.
TEMPLATES = {
    "apache-2.0-notice": "licensed under the apache license version 2 0",
    "gpl-notice": "licensed under {? the terms of ?} the gnu general public license {? as published by the free software foundation ?} {? either ?} version {= 1-2 =}",
    "mit-notice": "{? this {= 1-3 =} is ?} {? released ?} {? licensed ?} under the {? terms of the ?} mit license",
    "cc-by-nc-notice": "licensed under {? a ?} {? the ?} {? creative commons ?} cc by nc {= 1-2 =}",
    "cc-by-sa-notice": "licensed under {? a ?} {? the ?} {? creative commons ?} cc by sa {= 1-2 =}",
    "mit-text": "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions the above copyright notice and this permission notice {? including the next paragraph ?} shall be included in all copies or substantial portions of the software",
    "isc-text": "permission to use copy modify and {? or ?} distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies",
    "bsd-text": "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met {? 1 ?} redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer {? 2 ?} redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution {? {? 3 ?} neither the name of {= 1-12 =} nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission ?}",
}
#: One of these words stands in every phrase and template.
ANCHORS = ("gnu", "apache", "cc", "mit", "license", "granted", "redistributions")

_WORD = np.zeros(256, bool)
_WORD[48:58] = _WORD[97:123] = _WORD[128:] = True
ANY = None


@dataclass
class Automaton:
    """``steps[state]``: edges (word or ANY, next state); ``free[state]``: states reached without a word."""

    steps: list[list[tuple[str | None, int]]] = field(default_factory=list)
    free: list[list[int]] = field(default_factory=list)
    end: int = 0

    def state(self) -> int:
        self.steps.append([])
        self.free.append([])
        return len(self.steps) - 1

    def closure(self, states: set[int]) -> set[int]:
        todo = list(states)
        while todo:
            for s in self.free[todo.pop()]:
                if s not in states:
                    states.add(s)
                    todo.append(s)
        return states

    def accepts_at(self, words: list[str], at: int) -> bool:
        now = self.closure({0})
        for word in words[at:]:
            if self.end in now:
                return True
            now = self.closure({to for s in now for w, to in self.steps[s] if w is ANY or w == word})
            if not now:
                return False
        return self.end in now

    def openings(self) -> set[str | None]:
        return {w for s in self.closure({0}) for w, _ in self.steps[s]}

    def accepts(self, words: list[str]) -> bool:
        first = self.openings()
        return any((ANY in first or w in first) and self.accepts_at(words, i) for i, w in enumerate(words))


def compile_template(markup: str) -> Automaton:
    out = Automaton()
    at, opened = out.state(), []
    for token in re.findall(r"\{\?|\?\}|\{=[^=]*=\}|[^\s{}?=]+", markup):
        if token == "{?":
            opened.append(at)
        elif token == "?}":
            to = out.state()
            out.free[at].append(to)
            out.free[opened.pop()].append(to)
            at = to
        elif token.startswith("{="):
            least, most = map(int, token[2:-2].split("-"))
            ends = []
            for i in range(most):
                to = out.state()
                out.steps[at].append((ANY, to))
                at = to
                if i + 1 >= least:
                    ends.append(at)
            to = out.state()
            for s in ends:
                out.free[s].append(to)
            at = to
        else:
            to = out.state()
            out.steps[at].append((token, to))
            at = to
    if opened:
        raise ValueError("an optional part is not closed")
    out.end = at
    return out


def scan_words(words: list[str], automata: dict[str, Automaton], phrases: dict[str, str] = PHRASES) -> tuple[list[int], set[str], set[str]]:
    """(starts of phrases, labels of phrases, labels of accepted templates)."""
    starts, base = [], set()
    for phrase, label in phrases.items():
        p = phrase.split()
        for i in range(len(words) - len(p) + 1):
            if words[i] == p[0] and words[i : i + len(p)] == p:
                starts.append(i)
                base.add(label)
    return starts, base, {label for label, a in automata.items() if a.accepts(words)}


def scan(documents: DataFrame, templates: dict[str, str] = TEMPLATES, phrases: dict[str, str] = PHRASES, anchors: tuple[str, ...] = ANCHORS) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score of every whole text. score:
    1 if a template is accepted, 0.5 if there are phrases only, else 0."""
    for text in (*phrases, *templates.values()):
        if not set(anchors) & set(text.split()):
            raise ValueError(f"no anchor word in: {text}")
    schema = "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double"
    names = [x.split()[0] for x in schema.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        automata = {k: compile_template(v) for k, v in templates.items()}
        rare = np.sort(np.array([K.span_hash(K.prefix(b := np.frombuffer(a.encode(), np.uint8)), np.array([0]), np.array([len(b)]))[0] for a in anchors], np.uint64))
        for batch in batches:
            n = batch.num_rows
            n_words, n_base, score = np.zeros(n, np.int64), np.zeros(n, np.int64), np.zeros(n)
            first, last, base_labels, labels = [None] * n, [None] * n, [""] * n, [""] * n
            for a, b, buf, off in text_parts(batch.column("text")):
                low = K.LOWER[buf]
                start, end, bounds = K.spans(_WORD[low], off)
                n_words[a:b] = np.diff(bounds)
                hashes = K.span_hash(K.prefix(low), start, end)
                place = np.minimum(np.searchsorted(rare, hashes), len(rare) - 1)
                for i in np.unique(np.searchsorted(bounds, np.flatnonzero(rare[place] == hashes), side="right") - 1):
                    raw = low.tobytes() if b - a == 1 else low[off[i] : off[i + 1]].tobytes()
                    s, e = start[bounds[i] : bounds[i + 1]] - off[i], end[bounds[i] : bounds[i + 1]] - off[i]
                    words = [raw[x:y].decode("utf-8", "replace") for x, y in zip(s.tolist(), e.tolist(), strict=True)]
                    starts, base, found = scan_words(words, automata, phrases)
                    if starts:
                        n_base[a + i], first[a + i], last[a + i] = len(starts), min(starts), max(starts)
                    base_labels[a + i], labels[a + i] = ",".join(sorted(base)), ",".join(sorted(base | found))
                    score[a + i] = 1.0 if found else 0.5 if base else 0.0
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(n_words), pa.array(n_base), pa.array(first, pa.int64()), pa.array(last, pa.int64()), pa.array(base_labels), pa.array(labels), pa.array(score)], names)

    return documents.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).mapInArrow(run, schema)
