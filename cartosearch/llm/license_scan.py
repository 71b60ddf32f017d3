"""License scans with a generalised suffix automaton of licence tokens.

The automaton accepts every run of tokens of the phrases and notices below. A file streams through it once
and gives matching statistics: the longest run ending at each word that occurs in some template. Phrases are
read off the automaton (a phrase ends where its state lies on the suffix links of the current one). Long
matches are chained in order along each notice, the best chain by dynamic programming; a chain that covers enough of
the notice gives its label and span.

Null or empty text: no words, counts 0, first_word and last_word null, empty labels and spans, score 0. Rows are
independent, so ties, repeated rows and an empty table need no rule.
"""

from __future__ import annotations

from bisect import bisect_left
from collections import defaultdict

import numpy as np
from pyspark.sql import DataFrame

from . import textblocks as tb

# The phrases of the base labels, and the opening notices of common licences.
PHRASES = {
    "gnu general public license": "gpl",
    "apache license": "apache",
    "cc by": "cc-by",
    "mit license": "mit",
}
NOTICES = {
    "mit-notice": "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software",
    "bsd-notice": "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met",
    "isc-notice": "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies",
    "gpl-notice": "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation",
    "apache-notice": "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license",
    "mpl-notice": "this source code form is subject to the terms of the mozilla public license v 2 0",
    "apache-line": "licensed under the apache license version 2 0",
    "mit-line": "released under the mit license",
    "gpl-line": "this work is licensed under the gnu general public license version 3",
    "cc-by-nc-line": "licensed under cc by nc 4 0",
}

#: Word bytes map to themselves, lower-cased; all others to a space.
_FOLD = bytes(b + 32 if 0x41 <= b <= 0x5A else b if 0x30 <= b <= 0x39 or 0x61 <= b <= 0x7A or b >= 0x80 else 0x20 for b in range(256))


class LicenceAutomaton:
    """States of all token runs of the templates; `where` gives the template ends of each state."""

    def __init__(self, phrases: dict[str, str], notices: dict[str, str]):
        self.phrases = [(p.encode().split(), label) for p, label in phrases.items()]
        self.notices = [(t.encode().split(), label) for label, t in notices.items()]
        strings = [w for w, _ in self.phrases + self.notices]
        self.ids = {w: i for i, w in enumerate(dict.fromkeys(w for s in strings for w in s))}
        self.next, self.link, self.length, self.where = [{}], [-1], [0], [[]]
        for t, words in enumerate(strings):
            last = 0
            for j, w in enumerate(words):
                last = self._extend(last, self.ids[w])
                self.where[last].append((t, j))
        for s in sorted(range(1, len(self.next)), key=self.length.__getitem__, reverse=True):
            if self.link[s] > 0:
                self.where[self.link[s]] += self.where[s]
        self.ends = [tuple(sorted(set(w))) for w in self.where]
        states = [self._run(w) for w, _ in self.phrases]
        self.phrase_ends: list[tuple[int, ...]] = []
        for s in range(len(self.next)):
            chain = set()
            while s > 0:
                chain.add(s)
                s = self.link[s]
            self.phrase_ends.append(tuple(i for i, p in enumerate(states) if p in chain))

    def _new(self, length: int, like: int | None = None) -> int:
        self.next.append(dict(self.next[like]) if like is not None else {})
        self.link.append(self.link[like] if like is not None else 0)
        self.length.append(length)
        self.where.append([])
        return len(self.next) - 1

    def _split(self, p: int, q: int, token: int) -> int:
        """The state of the longest run through p and token, cut out of q where q has longer ones."""
        if self.length[q] == self.length[p] + 1:
            return q
        twin = self._new(self.length[p] + 1, q)
        self.link[q] = twin
        while p >= 0 and self.next[p].get(token) == q:
            self.next[p][token] = twin
            p = self.link[p]
        return twin

    def _extend(self, last: int, token: int) -> int:
        if token in self.next[last]:
            return self._split(last, self.next[last][token], token)
        state, p = self._new(self.length[last] + 1), last
        while p >= 0 and token not in self.next[p]:
            self.next[p][token] = state
            p = self.link[p]
        self.link[state] = self._split(p, self.next[p][token], token) if p >= 0 else 0
        return state

    def _run(self, words: list[bytes]) -> int:
        s = 0
        for w in words:
            s = self.next[s][self.ids[w]]
        return s

    def scan(self, tokens: list[int], least: int) -> tuple[list[tuple[int, int]], list[tuple[int, int, int]]]:
        """Phrase hits (start, phrase), and maximal matches (start, end, state) of `least` tokens or more."""
        hits, matches, state, size = [], [], 0, 0
        follow, link, length, ends = self.next, self.link, self.length, self.phrase_ends
        for j, token in enumerate([*tokens, -1]):
            before, kept = size, state
            while state > 0 and token not in follow[state]:
                state = link[state]
                size = length[state]
            if token in follow[state]:
                state, size = follow[state][token], size + 1
            else:
                state, size = 0, 0
            if size <= before and before >= least:
                matches.append((j - before, j, kept))
            for i in ends[state]:
                n = len(self.phrases[i][0])
                if size >= n:
                    hits.append((j - n + 1, i))
        return hits, matches

    def chains(self, matches: list[tuple[int, int, int]], gap: int) -> dict[int, list[tuple[float, int, int]]]:
        """For each notice its chains as (share of the notice that is covered, first word, word after the last), the best first.

        A chain is a row of matches whose places grow in the text and in the notice, with at most `gap` words between two;
        the best chain that ends in a match follows the best one of those in reach of its start. Chains of a notice that
        are listed share no word.
        """
        by: dict[int, list[tuple[int, int, int]]] = defaultdict(list)
        for start, end, state in matches:
            for t, j in self.ends[state]:
                if t >= len(self.phrases):
                    by[t].append((start, j - (end - start) + 1, end - start))
        out = {}
        for t, found in by.items():
            n = len(self.notices[t - len(self.phrases)][0])
            found.sort()
            best: list[tuple[int, int]] = []  # words covered, where the chain begins
            low = 0
            for i, (start, place, size) in enumerate(found):
                while found[low][0] + n + gap < start:  # no match is longer than the notice
                    low += 1
                top = (size, start)
                for j in range(low, i):
                    s, p, m = found[j]
                    if p < place and start <= s + m + gap:
                        more = min(size, place + size - p - m, start + size - s - m)
                        if more > 0 and best[j][0] + more > top[0]:
                            top = (best[j][0] + more, best[j][1])
                best.append(top)
            listed: list[tuple[float, int, int]] = []
            taken: list[tuple[int, int]] = []
            for (covered, begin), (start, _, size) in sorted(zip(best, found), key=lambda x: (-x[0][0], x[0][1], x[1])):
                at = bisect_left(taken, (begin, 0))
                before, behind = taken[at - 1][1] if at else -1, taken[at][0] if at < len(taken) else start + size
                if before <= begin and start + size <= behind:
                    listed.append((min(1.0, covered / n), begin, start + size))
                    taken.insert(at, (begin, start + size))
            out[t - len(self.phrases)] = listed
        return out


AUTOMATON = LicenceAutomaton(PHRASES, NOTICES)
SCHEMA = "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, spans string"


def scan_words(words: list[bytes], least_match: int = 4, gap: int = 12, cover: float = 0.7, a: LicenceAutomaton = AUTOMATON) -> tuple[list[tuple[int, int]], dict[int, list[tuple[float, int, int]]], list[tuple[int, int, str]]]:
    """(phrase hits, chains of notices, spans) of lower-cased words; spans are (first word, word after the last, label) of
    the phrases and of the chains that cover their notice."""
    shortest = min(len(p) for p, _ in a.phrases)
    ids = np.fromiter((a.ids.get(w, -1) for w in words), np.int32, len(words))
    known = np.concatenate(([False], ids >= 0, [False]))
    edges = np.flatnonzero(known[1:] != known[:-1])
    hits, matches = [], []
    for start, end in zip(edges[::2].tolist(), edges[1::2].tolist()):
        if end - start >= shortest:
            h, m = a.scan(ids[start:end].tolist(), least_match)
            hits += [(start + s, i) for s, i in h]
            matches += [(start + s, start + e, state) for s, e, state in m]
    chains = a.chains(matches, gap) if matches else {}
    spans = [(s, s + len(a.phrases[i][0]), a.phrases[i][1]) for s, i in hits]
    spans += [(begin, end, a.notices[t][1]) for t, listed in chains.items() for share, begin, end in listed if share >= cover]
    return hits, chains, sorted(spans)


def scan(docs: DataFrame, least_match: int = 4, gap: int = 12, cover: float = 0.7) -> DataFrame:
    """One row per document. least_match: tokens of a match that counts towards a chain; gap: words between
    two matches of a chain; cover: share of a notice that gives its label. score: the largest share of any
    notice that a chain covers, 1 where a phrase stands whole. spans: label:first:end in words, end exclusive, of all
    phrases and covered notices, in order."""
    a = AUTOMATON

    def one(words: list[bytes]) -> tuple:
        hits, chains, spans = scan_words(words, least_match, gap, cover)
        base = {a.phrases[i][1] for _, i in hits}
        starts = [s for s, _ in hits]
        score = 1.0 if hits else max((x[0][0] for x in chains.values()), default=0.0)
        return len(words), len(hits), min(starts, default=None), max(starts, default=None), ",".join(sorted(base)), ",".join(sorted({x for _, _, x in spans})), score, ",".join(f"{x}:{s}:{e}" for s, e, x in spans)

    def make(part):
        data, offsets = tb.flat_bytes(part)
        folded = data.tobytes().translate(_FOLD)
        rows = [one(folded[s:e].split()) for s, e in zip(offsets[:-1].tolist(), offsets[1:].tolist())]
        names = [x.split()[0] for x in SCHEMA.split(", ")][1:]
        return {"doc_id": tb.column(part, "doc_id")} | dict(zip(names, map(list, zip(*rows))))

    return tb.per_slice(docs, make, SCHEMA)
