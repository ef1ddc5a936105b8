"""License scans by template markup.

A template is plain wording with `<<opt>> ... <</opt>>` around omittable regions (they nest), `<<a|b>>` for
replaceable single words and `<<any:N>>` for up to N free words. It compiles to a token automaton whose states are
bits of one integer: a step is a mask and a shift, free words are bounded chains of any-word edges. A text is
accepted at a place when the mandatory wording from there on matches exactly. A run starts only where one of the
automaton's possible first two words stands, found by substring search.

Beside it stand the base phrases: places where a phrase's words follow each other.

Defined cases: null text counts as the empty text (no words, no labels, score 0); any doc_id, one row per input row;
an empty table gives an empty result; other columns are ignored. One narrow pass, no shuffle.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

from lowrank_spark.runtime import ship_package

_WORD = re.compile(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")

# The base phrases and their labels.
BASE = (("under the mit license", "mit"), ("apache license version 2", "apache-2"), ("cc by nc", "cc-by-nc"))

# Wording of public license texts and of customary notices, with markup.
TEMPLATES = (
    ("mit-notice", "<<released|licensed|distributed|available>> under the <<opt>>terms of the<</opt>> mit license"),
    ("apache-2.0-notice", "licensed under the apache license version 2 0 <<opt>>the license<</opt>> <<opt>>you may not use this file except in compliance with the license<</opt>>"),
    ("gpl-3.0-notice", "this <<work|program|software|file|library>> is licensed under the <<opt>>terms of the<</opt>> gnu <<opt>>lesser<</opt>> general public license <<opt>>as published by the free software foundation<</opt>> version 3 <<opt>>or <<opt>>at your option<</opt>> any later version<</opt>>"),
    ("cc-by-nc-4.0-notice", "licensed under <<opt>><<a|the>><</opt>> <<opt>>creative commons<</opt>> cc by nc 4 0 <<opt>>international<</opt>> <<opt>>license<</opt>>"),
    (
        "mit-text",
        "permission is hereby granted free of charge to any person obtaining a copy of this <<opt>>software and associated documentation files the<</opt>> software "
        "to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software "
        "and to permit persons to whom the software is furnished to do so subject to the following conditions the above copyright notice and this permission notice "
        "<<opt>>including the next paragraph<</opt>> shall be included in all copies or substantial portions of the software "
        "the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability "
        "fitness for a particular purpose and noninfringement in no event shall the authors or copyright holders be liable for any claim damages or other liability "
        "whether in an action of contract tort or otherwise arising from out of or in connection with the software or the use or other dealings in the software",
    ),
    (
        "mpl-2.0-notice",
        "this source code form is subject to the terms of the mozilla public license v 2 0 if a copy of the mpl was not distributed with this file "
        "you can obtain one at <<http|https>> <<opt>>www<</opt>> mozilla org mpl 2 0",
    ),
    (
        "apache-2.0-boilerplate",
        "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license you may obtain a copy of the license at "
        "<<http|https>> www apache org licenses license 2 0 unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis "
        "without warranties or conditions of any kind either express or implied see the license for the specific language governing permissions and limitations under the license",
    ),
    (
        "gpl-text-notice",
        "this <<program|library|file|work>> is free software you can redistribute it and or modify it under the terms of the gnu <<opt>><<lesser|affero>><</opt>> general public license "
        "as published by the free software foundation either version <<2|3>> of the license or <<opt>>at your option<</opt>> any later version",
    ),
    (
        "isc-text",
        "permission to use copy modify and <<opt>>or<</opt>> distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice "
        "and this permission notice appear in all copies the software is provided as is and <<any:4>> disclaims all warranties with regard to this software",
    ),
    (
        "bsd-text",
        "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met <<opt>>1<</opt>> redistributions of source code "
        "must retain the above copyright notice this list of conditions and the following disclaimer <<opt>>2<</opt>> redistributions in binary form must reproduce the above copyright notice "
        "this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution "
        "<<opt>><<opt>>3<</opt>> neither the name of <<any:8>> nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission<</opt>>",
    ),
)

_MARK = re.compile(r"<<(/?opt|any:\d+|[^<>]*)>>|([^\s<>]+)")


def parse(template: str) -> list:
    """Tree of words: ('word', {..}), ('any', n) and ('opt', [...])."""
    stack: list[list] = [[]]
    for m in _MARK.finditer(template):
        mark, word = m[1], m[2]
        if word is not None:
            stack[-1].append(("word", frozenset([word.encode()])))
        elif mark == "opt":
            stack.append([])
        elif mark == "/opt":
            if len(stack) < 2:
                raise ValueError("an optional region ends that never began")
            body = stack.pop()
            stack[-1].append(("opt", body))
        elif mark.startswith("any:"):
            stack[-1].append(("any", int(mark[4:])))
        else:
            stack[-1].append(("word", frozenset(w.strip().encode() for w in mark.split("|"))))
    if len(stack) != 1:
        raise ValueError("an optional region does not end")
    return stack[0]


class Automaton:
    """Position automaton of a template: bit k of the state set means that position k is to be read next."""

    def __init__(self, label: str, template: str):
        self.label = label
        self.reads: list[frozenset | None] = []  # words read at a position; None reads any word
        self.skips: list[tuple[int, int]] = []  # from a position straight to a later one
        self._add(parse(template))
        self.end = len(self.reads)
        self.onward = []  # closure of a position under skips
        for k in range(self.end + 1):
            self.onward.append(1 << k)
        for k in range(self.end, -1, -1):
            for a, b in self.skips:
                if a == k:
                    self.onward[k] |= self.onward[b]
        self.by_word: dict[bytes, int] = {}
        self.any = 0
        for k, r in enumerate(self.reads):
            if r is None:
                self.any |= 1 << k
            else:
                for w in r:
                    self.by_word[w] = self.by_word.get(w, 0) | 1 << k
        self.final = 1 << self.end
        self.first = self.onward[0]

    def _add(self, tree: list) -> None:
        for kind, x in tree:
            if kind == "word":
                self.reads.append(x)
            elif kind == "any":
                a = len(self.reads)
                self.reads += [None] * x
                self.skips += [(k, a + x) for k in range(a, a + x)]
            else:
                a = len(self.reads)
                self._add(x)
                self.skips.append((a, len(self.reads)))

    def step(self, states: int, word: bytes) -> int:
        live = states & (self.by_word.get(word, 0) | self.any)
        out = 0
        while live:
            low = live & -live
            out |= self.onward[low.bit_length()]
            live ^= low
        return out

    def accept(self, words: list[bytes], start: int) -> int:
        """End of the longest accepted run from start, or -1."""
        states, best = self.first, (start if self.first & self.final else -1)
        for p in range(start, len(words)):
            states = self.step(states, words[p])
            if not states:
                break
            if states & self.final:
                best = p + 1
        return best

    def openings(self) -> list[bytes]:
        """' first second ' of every way to begin (the first alone where the second is free)."""
        out = set()
        for k in range(self.end):
            if self.first >> k & 1:
                if self.reads[k] is None:
                    raise ValueError("a template begins with a word of its own")
                for w in self.reads[k]:
                    nxt = self.onward[k + 1]
                    if nxt & self.final:  # the run may end here
                        out.add(b" %b " % w)
                    for j in range(self.end):
                        if nxt >> j & 1:
                            out |= {b" %b " % w} if self.reads[j] is None else {b" %b %b " % (w, v) for v in self.reads[j]}
        return sorted(out)


def compile_templates(templates=TEMPLATES) -> list[tuple[Automaton, list[bytes]]]:
    autos = [Automaton(*t) for t in templates]
    return [(a, a.openings()) for a in autos]


def _starts(flat: bytes, phrase: bytes) -> list[int]:
    """Word indices at which ' phrase ' stands in the space-joined words (overlaps included)."""
    out, p, at, n = [], flat.find(phrase), 0, 0
    while p >= 0:
        n += flat.count(b" ", at, p)
        at = p
        out.append(n)
        p = flat.find(phrase, p + 1)
    return out


def scan(text: str | None, compiled, base=BASE) -> dict:
    words = _WORD.findall((text or "").encode("utf-8", "surrogatepass").lower())
    flat = b" %b " % b" ".join(words)
    base_at, base_labels, labels, places = [], set(), set(), []
    for phrase, label in base:
        if at := _starts(flat, b" %b " % phrase.encode()):
            base_at += at
            base_labels.add(label)
    for auto, openings in compiled:
        for o in openings:
            for s in _starts(flat, o):
                e = auto.accept(words, s)
                if e > s:
                    labels.add(auto.label)
                    places.append((s, e, auto.label))
    return {
        "n_words": len(words),
        "n_base": len(base_at),
        "first_word": min(base_at, default=None),
        "last_word": max(base_at, default=None),
        "base_labels": ",".join(sorted(base_labels)),
        "labels": ",".join(sorted(base_labels | labels)),
        "score": 1.0 if labels else 0.5 if base_labels else 0.0,
        "matches": sorted(set(places)),
    }


_TYPES = {"n_words": pa.int64(), "n_base": pa.int64(), "first_word": pa.int64(), "last_word": pa.int64(), "base_labels": pa.string(), "labels": pa.string(), "score": pa.float64()}
_MATCH = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("label", pa.string())]))


def scan_licenses(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", templates=TEMPLATES, base=BASE) -> DataFrame:
    """id + base counts, labels, score and the accepted places (word ranges) of every template."""
    ship_package(docs.sparkSession)
    schema = f"{id_col} {docs.schema[id_col].dataType.simpleString()}, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, matches array<struct<start: long, end: long, label: string>>"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        compiled = compile_templates(templates)
        for b in batches:
            rows = [scan(t.as_py(), compiled, base) for t in b.column(1)]
            cols = [pa.array([r[k] for r in rows], ty) for k, ty in _TYPES.items()]
            hits = pa.array([[dict(zip(("start", "end", "label"), m, strict=True)) for m in r["matches"]] for r in rows], _MATCH)
            yield pa.RecordBatch.from_arrays([b.column(0), *cols, hits], names=[id_col, *_TYPES, "matches"])

    return docs.select(id_col, text_col).mapInArrow(run, schema)


def op4_license_markup(spark, sf_dir: str) -> DataFrame:
    return scan_licenses(spark.read.parquet(f"{sf_dir}/documents.parquet")).drop("matches")
