"""Licence scan: a generalised suffix automaton over the words of licence templates.

Files stream through the automaton, which gives at every word the length of the
longest template passage that ends there. Passages that cannot grow further and
are long enough are chained, in order, per template; the chained words over the
template's length is its coverage. Short phrases are templates that must occur
whole; each place where one ends is read off the automaton's suffix links.
"""

from __future__ import annotations

from collections.abc import Mapping, Sequence
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from . import bytescan
from .common import map_text

#: Phrases that name a licence wherever they stand.
PHRASES = {
    "under the mit license": "mit",
    "apache license version 2": "apache-2",
    "cc by nc": "cc-by-nc",
}

#: Passages of public licence notices, by label.
TEMPLATES = {
    "apache-2": "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License. You may obtain a copy of the License at",
    "bsd": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met",
    "cc0": "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work",
    "gpl-3": "This work is licensed under the GNU General Public License, version 3",
    "gpl": "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation",
    "mit": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files",
    "mpl-2": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at",
}

#: Words of the shortest passage that is chained, share of a template that makes its label, largest gap in a chain.
MIN_MATCH, MIN_COVER, MAX_GAP = 4, 0.6, 8

#: Most template words that are compiled and broadcast.
MAX_TEMPLATE_WORDS = 2_000_000

SPAN = T.StructType(
    [
        T.StructField("label", T.StringType()),
        T.StructField("first", T.LongType()),
        T.StructField("last", T.LongType()),
        T.StructField("coverage", T.DoubleType()),
    ]
)


@dataclass
class SuffixAutomaton:
    """Minimal automaton of all passages of several word sequences."""

    next: list[dict[int, int]] = field(default_factory=lambda: [{}])
    link: list[int] = field(default_factory=lambda: [-1])
    length: list[int] = field(default_factory=lambda: [0])
    #: per state, template to the first position where the state's passages end in it
    ends: list[dict[int, int]] = field(default_factory=lambda: [{}])

    def _state(self, length: int, moves: dict[int, int], link: int) -> int:
        self.next.append(moves)
        self.link.append(link)
        self.length.append(length)
        self.ends.append({})
        return len(self.next) - 1

    def _split(self, p: int, word: int, q: int) -> int:
        twin = self._state(self.length[p] + 1, dict(self.next[q]), self.link[q])
        self.link[q] = twin
        while p >= 0 and self.next[p].get(word) == q:
            self.next[p][word] = twin
            p = self.link[p]
        return twin

    def add(self, template: int, words: Sequence[int]) -> None:
        last, trail = 0, []
        for word in words:
            q = self.next[last].get(word)
            if q is not None:
                last = q if self.length[q] == self.length[last] + 1 else self._split(last, word, q)
            else:
                new, p = self._state(self.length[last] + 1, {}, 0), last
                while p >= 0 and word not in self.next[p]:
                    self.next[p][word] = new
                    p = self.link[p]
                if p >= 0:
                    q = self.next[p][word]
                    self.link[new] = q if self.length[q] == self.length[p] + 1 else self._split(p, word, q)
                last = new
            trail.append(last)
        for at, state in enumerate(trail):
            self.ends[state].setdefault(template, at)

    def close(self) -> None:
        """Hand end positions down the suffix links."""
        for state in sorted(range(1, len(self.next)), key=self.length.__getitem__, reverse=True):
            up = self.ends[self.link[state]]
            for template, at in self.ends[state].items():
                up[template] = min(up.get(template, at), at)

    def statistics(self, words: Sequence[int]) -> tuple[list[int], list[int]]:
        """(length, state) of the longest passage ending at each word."""
        state = size = 0
        lengths, states = [], []
        for word in words:
            while state and word not in self.next[state]:
                state = self.link[state]
                size = self.length[state]
            if word in self.next[state]:
                state, size = self.next[state][word], size + 1
            lengths.append(size)
            states.append(state)
        return lengths, states


class LicenceIndex:
    """Phrases and templates compiled into one automaton, with the word table that feeds it."""

    def __init__(self, phrases: Mapping[str, str], templates: Mapping[str, str]) -> None:
        rows = [(label, text, True) for text, label in phrases.items()] + [(label, text, False) for label, text in templates.items()]
        texts = pa.array([text for _, text, _ in rows], pa.large_string())
        sequences: list[list[bytes]] = []
        hashes: dict[bytes, int] = {}
        for part in bytescan.slices(texts):
            words, data = bytescan.scan(part, bytescan.ALNUM), bytescan.LOWER[part.data]
            raw = [data[a:b].tobytes() for a, b in zip(words.start.tolist(), words.end.tolist())]
            hashes.update(zip(raw, words.hash.tolist()))
            sequences += [raw[a:b] for a, b in zip(words.bounds[:-1].tolist(), words.bounds[1:].tolist())]
        if sum(map(len, sequences)) > MAX_TEMPLATE_WORDS:
            raise ValueError("more template words than may be broadcast; scan with parts of the templates")
        vocabulary = sorted(hashes)
        ids = {word: i for i, word in enumerate(vocabulary)}
        self.labels = [label for label, _, _ in rows]
        self.sizes = [len(s) for s in sequences]
        self.whole = [phrase for *_, phrase in rows]
        self.automaton = SuffixAutomaton()
        for k, sequence in enumerate(sequences):
            self.automaton.add(k, [ids[w] for w in sequence])
        self.automaton.close()
        #: per state, phrases that end wherever the state's longest passages end: (phrase, its size)
        self.phrases_at = self._phrases(sequences, ids)
        self.shortest = min([MIN_MATCH, *(n for n, phrase in zip(self.sizes, self.whole) if phrase)])
        by_hash = sorted(range(len(vocabulary)), key=lambda i: hashes[vocabulary[i]])
        self.hash = np.array([hashes[vocabulary[i]] for i in by_hash], np.uint64)
        self.id = np.array(by_hash, np.int64)
        self.filter = np.zeros(1 << max(16, int(16 * len(vocabulary)).bit_length()), bool)
        self.filter[self._slot(self.hash)] = True

    def _slot(self, hashes: np.ndarray) -> np.ndarray:
        return (hashes & np.uint64(len(self.filter) - 1)).astype(np.int64)

    def _phrases(self, sequences: list[list[bytes]], ids: dict[bytes, int]) -> list[tuple[tuple[int, int], ...]]:
        a = self.automaton
        own: dict[int, list[tuple[int, int]]] = {}
        for k, sequence in enumerate(sequences):
            if self.whole[k]:
                _, states = a.statistics([ids[w] for w in sequence])
                own.setdefault(states[-1], []).append((k, len(sequence)))
        found: list[tuple[tuple[int, int], ...]] = [()] * len(a.next)
        for state in sorted(range(len(a.next)), key=a.length.__getitem__):
            above = found[a.link[state]] if state else ()
            found[state] = (*above, *own.get(state, ()))
        return found

    def words(self, hashes: np.ndarray) -> np.ndarray:
        """Word ids in the templates' vocabulary; -1 for other words."""
        out = np.full(len(hashes), -1, np.int64)
        if len(self.hash):
            maybe = np.flatnonzero(self.filter[self._slot(hashes)])
            at = np.minimum(np.searchsorted(self.hash, hashes[maybe]), len(self.hash) - 1)
            same = self.hash[at] == hashes[maybe]
            out[maybe[same]] = self.id[at[same]]
        return out


@dataclass
class Found:
    """What one text holds: phrase places (start, phrase) and template spans."""

    places: list[tuple[int, int]] = field(default_factory=list)
    #: (text end, length, template, template end) of passages that cannot grow
    passages: list[tuple[int, int, int, int]] = field(default_factory=list)


def chain(passages: list[tuple[int, int, int, int]], sizes: Sequence[int]) -> dict[int, tuple[float, int, int]]:
    """Best chain per template: (coverage, first word, last word).

    A chain takes passages in text order whose template positions also rise,
    with at most ``MAX_GAP`` words between neighbours; words are counted once.
    """
    best: dict[int, tuple[float, int, int]] = {}
    open_chains: dict[int, list[tuple[int, int, int, int]]] = {}
    for end, size, template, at in sorted(passages):
        grown = (size, end - size + 1, end, at)
        # a later passage starts no earlier than this, so other chains are out of reach for good
        near = [c for c in open_chains.get(template, ()) if c[2] >= end - sizes[template] - MAX_GAP]
        for covered, first, last, upto in near:
            # words that overlap the chain, in text or template, count once
            start, fresh = end - size + 1, min(size, at - upto, end - last)
            if start - last - 1 <= MAX_GAP and fresh > 0 and covered + fresh > grown[0]:
                grown = (covered + fresh, first, end, at)
        open_chains[template] = [*near, grown]
        share = (min(1.0, grown[0] / sizes[template]), grown[1], grown[2])
        if template not in best or share[0] > best[template][0]:
            best[template] = share
    return best


def _scan_run(index: LicenceIndex, ids: list[int], start: int, out: Found) -> None:
    a = index.automaton
    lengths, states = a.statistics(ids)
    for i, (size, state) in enumerate(zip(lengths, states)):
        for phrase, n in index.phrases_at[state]:
            if n <= size:
                out.places.append((start + i - n + 1, phrase))
        last = i + 1 == len(ids) or lengths[i + 1] != size + 1
        if last and size >= MIN_MATCH:
            for template, at in a.ends[state].items():
                if not index.whole[template]:
                    out.passages.append((start + i, size, template, at))


def scan_column(text: pa.Array, index: LicenceIndex) -> list[pa.Array]:
    """Per row: word count, phrase places, first and last start, phrase labels, all labels, best coverage, spans."""
    rows: list[tuple] = []
    for part in bytescan.slices(text):
        words = bytescan.scan(part, bytescan.ALNUM)
        ids = index.words(words.hash)
        n = len(ids)
        known = np.r_[False, ids >= 0, False]
        edge = np.zeros(n + 1, bool)
        edge[words.bounds] = True
        begin = np.flatnonzero(known[1:-1] & (~known[:-2] | edge[:-1]))
        stop = np.flatnonzero(known[1:-1] & (~known[2:] | edge[1:])) + 1
        long = stop - begin >= index.shortest
        begin, stop = begin[long], stop[long]
        found: dict[int, Found] = {}
        for b, e, row in zip(begin.tolist(), stop.tolist(), (np.searchsorted(words.bounds, begin, "right") - 1).tolist()):
            _scan_run(index, ids[b:e].tolist(), b - int(words.bounds[row]), found.setdefault(row, Found()))
        for row, count in enumerate(words.counts.tolist()):
            rows.append((count, *_summary(index, found[row])) if row in found else (count, 0, None, None, [], [], 0.0, []))
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.string()), pa.list_(pa.string()), pa.float64()]
    span = pa.struct([("label", pa.string()), ("first", pa.int64()), ("last", pa.int64()), ("coverage", pa.float64())])
    columns = list(zip(*rows)) if rows else [()] * 8
    return [pa.array(c, kind) for c, kind in zip(columns, [*kinds, pa.list_(span)])]


def _summary(index: LicenceIndex, found: Found) -> tuple:
    base = sorted({index.labels[p] for _, p in found.places})
    chains = chain(found.passages, index.sizes)
    spans = [(index.labels[t], first, last, c) for t, (c, first, last) in chains.items() if c >= MIN_COVER]
    spans += [(index.labels[p], s, s + index.sizes[p] - 1, 1.0) for s, p in found.places]
    labels = sorted({*base, *(s[0] for s in spans)})
    starts = [s for s, _ in found.places]
    score = max([0.0, *(c for c, _, _ in chains.values()), *([1.0] if base else [])])
    dicts = [dict(zip(("label", "first", "last", "coverage"), s)) for s in sorted(spans, key=lambda s: (s[1], s[2], s[0]))]
    return len(starts), min(starts, default=None), max(starts, default=None), base, labels, score, dicts


def scan_licences(docs: DataFrame, text: str = "text", phrases: Mapping[str, str] = PHRASES, templates: Mapping[str, str] = TEMPLATES) -> DataFrame:
    """``docs`` with n_words, n_places, first_word, last_word, phrase_labels, labels, coverage and spans.

    Columns of those names are replaced. Texts are scanned whole where they lie;
    a null or empty text has no words, no labels and coverage 0. Repeated rows
    are scanned alike, an empty table gives an empty result. Ties between chains
    of one template go to the earlier one. The automaton of the (bounded)
    templates is broadcast.
    """
    index = docs.sparkSession.sparkContext.broadcast(LicenceIndex(phrases, templates))
    text_list = T.ArrayType(T.StringType())
    fields = [
        *(T.StructField(n, T.LongType()) for n in ("n_words", "n_places", "first_word", "last_word")),
        T.StructField("phrase_labels", text_list),
        T.StructField("labels", text_list),
        T.StructField("coverage", T.DoubleType()),
        T.StructField("spans", T.ArrayType(SPAN)),
    ]
    return map_text(docs, text, fields, lambda: lambda column: scan_column(column, index.value))
