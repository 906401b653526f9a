"""Licence scans: matching statistics of files against a generalised suffix automaton of licence templates.

The automaton holds every token sequence that occurs in some template. Streaming a file through it gives, at each
word, the longest template passage that ends there; passages of MIN_MATCH words or more are chained, in the order
of file and template alike, into covered spans of one template. Numpy finds the runs of template words first, so
that only those go through the automaton: a word of no template would reset it.
"""

from __future__ import annotations

from bisect import bisect
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from liveindex.llm import common as C

# Phrases that give a label wherever their words stand together.
PHRASES = {"under the mit license": "mit", "apache license version 2": "apache-2", "cc by nc": "cc-by-nc"}

# Openings and notices of public licences, by label.
TEMPLATES = [
    ("mit", "released under the mit license"),
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software"),
    ("apache-2", "licensed under the apache license version 2 0"),
    ("apache-2", "you may not use this file except in compliance with the license you may obtain a copy of the license at http www apache org licenses license 2 0"),
    ("gpl-3", "licensed under the gnu general public license version 3"),
    ("gpl", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation"),
    ("lgpl", "under the terms of the gnu lesser general public license as published by the free software foundation"),
    ("agpl", "under the terms of the gnu affero general public license as published by the free software foundation"),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met"),
    ("mpl-2", "this source code form is subject to the terms of the mozilla public license v 2 0"),
    ("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies"),
    ("cc-by-nc", "licensed under cc by nc 4 0"),
    ("cc-by-sa", "licensed under cc by sa 4 0"),
    ("cc-by", "this work is licensed under a creative commons attribution 4 0 international license"),
    ("cc0", "to the extent possible under law the author has waived all copyright and related or neighboring rights to this work"),
    ("unlicense", "this is free and unencumbered software released into the public domain"),
]

#: Shortest passage that counts, in words; words of the file that a chain may skip; share of a template that a
#: chain must cover to give its label.
MIN_MATCH, MOST_SKIPPED, LEAST_COVERED = 4, 24, 0.75

#: Bytes of words once A-Z are lower-cased: digits, letters, and all of UTF-8 above ASCII.
INSIDE = np.zeros(256, bool)
INSIDE[0x30:0x3A] = INSIDE[0x61:0x7B] = INSIDE[0x80:] = True


class SuffixAutomaton:
    """All passages of several token sequences. A state is a set of passages with the same ends."""

    def __init__(self, sequences: list[list[int]]) -> None:
        self.next: list[dict[int, int]] = [{}]
        self.length, self.link = [0], [-1]
        ends: list[set[tuple[int, int]]] = [set()]
        for which, sequence in enumerate(sequences):
            last = 0
            for at, token in enumerate(sequence):
                last = self._extend(last, token, ends)
                ends[last].add((which, at + 1))
        for state in sorted(range(1, len(self.length)), key=lambda s: -self.length[s]):
            ends[self.link[state]] |= ends[state]
        self.ends = [sorted(e) for e in ends]

    def _state(self, length: int, link: int, out: dict[int, int], ends: list) -> int:
        self.next.append(out)
        self.length.append(length)
        self.link.append(link)
        ends.append(set())
        return len(self.next) - 1

    def _split(self, p: int, token: int, ends: list) -> int:
        """The state of the passages of p followed by token, apart from longer ones that share it."""
        q = self.next[p][token]
        if self.length[q] == self.length[p] + 1:
            return q
        copy = self._state(self.length[p] + 1, self.link[q], dict(self.next[q]), ends)
        self.link[q] = copy
        while p >= 0 and self.next[p].get(token) == q:
            self.next[p][token] = copy
            p = self.link[p]
        return copy

    def _extend(self, last: int, token: int, ends: list) -> int:
        if token in self.next[last]:
            return self._split(last, token, ends)
        new, p = self._state(self.length[last] + 1, 0, {}, ends), last
        while p >= 0 and token not in self.next[p]:
            self.next[p][token] = new
            p = self.link[p]
        if p >= 0:
            self.link[new] = self._split(p, token, ends)
        return new

    def matches(self, tokens: list[int], least: int) -> Iterator[tuple[int, int, int]]:
        """(end in tokens, length, state) of each match that the next token does not lengthen."""
        state = length = 0
        for at, token in enumerate(tokens):
            before, was = state, length
            while state and token not in self.next[state]:
                state = self.link[state]
                length = self.length[state]
            if token in self.next[state]:
                state, length = self.next[state][token], length + 1
            if length != was + 1 and was >= least:
                yield at, was, before
        if length >= least:
            yield len(tokens), length, state


def _hashes(text: str) -> np.ndarray:
    raw, off = C.flat(pa.array([text]))
    starts, ends, _ = C.spans(INSIDE[raw], off)
    return C.span_hashes(raw, starts, ends)


@lru_cache(4)
def _compiled(templates: tuple[tuple[str, str], ...]) -> tuple[SuffixAutomaton, np.ndarray, list[int]]:
    """Automaton over word numbers, the sorted hashes that those number, and the lengths of the templates."""
    rows = [_hashes(text) for _, text in templates]
    vocabulary = np.unique(np.concatenate(rows))
    return SuffixAutomaton([np.searchsorted(vocabulary, r).tolist() for r in rows]), vocabulary, [len(r) for r in rows]


def _chains(found: list[tuple[int, int, int, int]]) -> Iterator[tuple[int, int, int]]:
    """(first word, word after the last, template words covered) of the chains of one template's matches, best first.

    found: (file begin, file end, template begin, template end). A chain goes on with a match that ends later in the
    file and in the template, and begins at most MOST_SKIPPED words after the chain's end; what two matches share of
    either counts once. Each match takes the predecessor that covers most; of the chains, those that share no words of
    the file are given, the one that covers most first. Matches are maximal, so only those of the words behind, as many
    as a match has and may be skipped, can be predecessors."""
    found = sorted(set(found), key=lambda m: (m[1], m[3], m[0]))
    covered, begin, oldest = [], [], 0
    for j, (f0, f1, t0, t1) in enumerate(found):
        best, start = t1 - t0, f0
        while found[oldest][1] < f0 - MOST_SKIPPED:
            oldest += 1
        for i in range(oldest, j):
            _, e1, _, u1 = found[i]
            if e1 < f1 and u1 < t1 and e1 >= f0 - MOST_SKIPPED:
                both = max(0, e1 - f0, u1 - t0)
                if both < t1 - t0 and covered[i] + t1 - t0 - both > best:
                    best, start = covered[i] + t1 - t0 - both, begin[i]
        covered.append(best)
        begin.append(start)
    taken: list[tuple[int, int]] = []  # in file order, none of which meet
    for j in sorted(range(len(found)), key=lambda j: (-covered[j], found[j][1], begin[j])):
        span = (begin[j], found[j][1])
        at = bisect(taken, span)
        if (at == 0 or taken[at - 1][1] <= span[0]) and (at == len(taken) or taken[at][0] >= span[1]):
            taken.insert(at, span)
            yield *span, covered[j]


SPAN = T.StructType([T.StructField("label", T.StringType()), T.StructField("template", T.IntegerType()), T.StructField("first_word", T.LongType()), T.StructField("end_word", T.LongType()), T.StructField("covered", T.DoubleType())])
COLUMNS = T.StructType([
    T.StructField("n_words", T.LongType()), T.StructField("n_base", T.LongType()), T.StructField("first_word", T.LongType()), T.StructField("last_word", T.LongType()),
    T.StructField("base_labels", T.StringType()), T.StructField("labels", T.StringType()), T.StructField("score", T.DoubleType()), T.StructField("licence_spans", T.ArrayType(SPAN))])


def scan(texts: pa.Array, templates: tuple[tuple[str, str], ...]) -> list[dict]:
    """The columns of COLUMNS for each text."""
    automaton, vocabulary, lengths = _compiled(templates)
    raw, off = C.flat(texts)
    raw = C.LOWER[raw]
    starts, ends, first = C.spans(INSIDE[raw], off)
    words, doc = C.span_hashes(raw, starts, ends), C.owner(first)
    out = [{"n_words": int(n), "n_base": 0, "first_word": None, "last_word": None, "base": set(), "more": set(), "score": 0.0, "licence_spans": []} for n in np.diff(first)]

    for phrase, label in PHRASES.items():
        wanted = _hashes(phrase)
        if words.size < wanted.size:
            continue
        here = np.ones(words.size - wanted.size + 1, bool)
        for k, w in enumerate(wanted):
            here &= words[k : k + here.size] == w
        at = np.flatnonzero(here)
        for i in at[doc[at] == doc[at + wanted.size - 1]]:
            row, place = out[doc[i]], int(i - first[doc[i]])
            row["n_base"] += 1
            row["base"].add(label)
            row["first_word"] = place if row["first_word"] is None else min(place, row["first_word"])
            row["last_word"] = place if row["last_word"] is None else max(place, row["last_word"])

    number = np.searchsorted(vocabulary, words)
    known = vocabulary[np.minimum(number, vocabulary.size - 1)] == words
    begin, end, _ = C.spans(known, first)
    found: dict[tuple[int, int], list] = {}
    for b, e in zip(begin[(long := end - begin >= MIN_MATCH)].tolist(), end[long].tolist(), strict=True):
        d = int(doc[b])
        place = b - int(first[d])
        for stop, length, state in automaton.matches(number[b:e].tolist(), MIN_MATCH):
            for which, t_end in automaton.ends[state]:
                found.setdefault((d, which), []).append((place + stop - length, place + stop, t_end - length, t_end))
    for (d, which), passages in found.items():
        for b, e, covered in _chains(passages):
            share = min(1.0, covered / lengths[which])
            out[d]["score"] = max(out[d]["score"], share)
            if share >= LEAST_COVERED:
                out[d]["more"].add(templates[which][0])
                out[d]["licence_spans"].append({"label": templates[which][0], "template": which, "first_word": b, "end_word": e, "covered": share})
    for row in out:
        base, more = row.pop("base"), row.pop("more")
        row |= {"base_labels": ",".join(sorted(base)), "labels": ",".join(sorted(base | more)), "score": 1.0 if base else row["score"]}
        row["licence_spans"].sort(key=lambda s: (s["first_word"], s["template"]))
    return out


def scan_licences(df: DataFrame, text: str = "text", templates=TEMPLATES) -> DataFrame:
    """df with word count, phrase places, labels, score and covered template spans of each text.

    Null and empty texts have no words, no places (null first and last) and empty labels. Rows are judged one by
    one: repeated rows get equal results, an empty table gives an empty result. Columns of df named like an added
    one are replaced.
    """
    df = df.drop(*[c for c in df.columns if c.lower() in COLUMNS.names and c != text])
    schema = T.StructType([*df.schema, *COLUMNS])
    templates = tuple((str(a), str(b)) for a, b in templates)

    def scanned(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark.sql.pandas.types import to_arrow_schema

        added = to_arrow_schema(COLUMNS)
        for batch in batches:
            for part in C.pieces(batch, text):
                rows = scan(part.column(text), templates)
                yield pa.RecordBatch.from_arrays([*part.columns, *[pa.array([r[f.name] for r in rows], f.type) for f in added]], schema=pa.schema([*part.schema, *added]))

    return df.mapInArrow(scanned, schema)
