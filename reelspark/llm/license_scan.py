"""Licence scan: exact phrases, and short notices with a few edits.

The fuzzy part splits each notice into ``k + 1`` pieces of its normal form (k: errors allowed).
By pigeonhole any occurrence with at most k edits holds one piece unchanged, so an Aho-Corasick pass
over the pieces finds every candidate place; the regex library's bounded-error matching then verifies
the notice in the reach of each seed and reports its span.

What is reported: spans of one notice don't overlap, each begins and ends at words' borders and lies within k edits of
the notice; and any such stretch of a text that is not reported overlaps a reported span of no more edits. Windows are those of single
seeds (a notice and 2 k characters), so the work is linear in a text's length.

Notices are a table (notice, label) that a user can give; ``NOTICES`` is the default.

Defined results: null and empty texts have no words, no labels and score 0; equal spans found from
several seeds count once; whole texts are read, whatever their length.
"""

from __future__ import annotations

import functools
import heapq
import itertools
from bisect import bisect_left, bisect_right

import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reelspark.llm.common import per_document

#: Phrase (its words) and label.
PHRASES = {"gnu general public license": "gpl", "apache license": "apache", "cc by": "cc-by", "mit license": "mit"}
#: Own list of short notices in normal form, and their labels.
NOTICES = {
    "licensed under the apache license version 2 0": "apache",
    "licensed under the gnu general public license version": "gpl",
    "released under the mit license": "mit",
    "licensed under cc by nc 4 0": "cc-by",
    "gnu lesser general public license": "lgpl",
    "gnu affero general public license": "agpl",
    "mozilla public license version 2 0": "mpl",
    "eclipse public license version": "epl",
    "creative commons attribution": "cc-by",
    "permission is hereby granted free of charge to any person obtaining a copy": "mit",
    "redistribution and use in source and binary forms with or without modification": "bsd",
    "permission to use copy modify and or distribute this software for any purpose": "isc",
    "all rights reserved": "reserved",
}
ERROR_RATE = 0.12  # edits allowed per character of a notice
#: One table for bytes: A-Z folded, every byte that is no word's becomes a space; UTF-8's other bytes belong to words.
_NORMAL = bytes(b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256))


def errors(notice: str) -> int:
    return max(1, int(len(notice) * ERROR_RATE))


def pieces(notice: str) -> list[tuple[int, str]]:
    """(offset, piece): k + 1 pieces of even length."""
    k, n = errors(notice) + 1, len(notice)
    cuts = [n * i // k for i in range(k + 1)]
    return [(a, notice[a:b]) for a, b in itertools.pairwise(cuts)]


def normal(notice: str) -> str:
    return b" ".join(notice.encode().translate(_NORMAL).split()).decode("utf-8", "replace")


class Notice:
    def __init__(self, text: str, label: str):
        self.text, self.label, self.size, self.k = text, label, len(text), errors(text)
        self.grams = [text[i : i + 3] for i in range(len(text) - 2)]
        self.patterns: dict[int, regex.Pattern] = {}

    def within(self, stretch: str, most: int) -> int | None:
        """Edits between the notice and a whole stretch, if at most ``most``. (The library's search tries no insertion in
        front of its first character, so stretches are matched whole.)"""
        if most not in self.patterns:
            self.patterns[most] = regex.compile(f"(?:{regex.escape(self.text)}){{e<={most}}}", regex.BESTMATCH)
        m = self.patterns[most].fullmatch(stretch)
        return sum(m.fuzzy_counts) if m else None

    def plausible(self, window: str) -> bool:
        """Cheap necessary condition: an edit spoils at most three of the notice's runs of three characters."""
        return sum([g in window for g in self.grams]) >= len(self.grams) - 3 * self.k

    def best(self, flat: str, lo: int, hi: int) -> tuple[int, int, int] | None:
        """(edits, start, end) of the best stretch from a word's first to a word's last character, or None; of equals the
        one nearest to the notice's length, then the first."""
        if hi - lo < self.size - self.k or not self.plausible(flat[lo:hi]):
            return None
        begins, ends, at = [lo], [], lo - 1
        while (at := flat.find(" ", at + 1, hi)) >= 0:
            begins.append(at + 1)
            ends.append(at)
        ends.append(hi)
        pairs = sorted((abs(b - a - self.size), a, b) for a in begins for b in ends if abs(b - a - self.size) <= self.k)
        for differ, a, b in pairs:  # an unchanged notice is the best there can be, and cheap to see
            if differ == 0 and self.within(flat[a:b], 0) == 0:
                return 0, a, b
        found, most = None, self.k
        for differ, a, b in pairs:
            if differ > most:
                break
            if (e := self.within(flat[a:b], most)) is not None:
                found, most = (e, a, b), e - 1
        return found


@functools.cache
def machine(notices: tuple[tuple[str, str], ...] = tuple(NOTICES.items())):
    """The automaton of all pieces, and the notices by number."""
    import ahocorasick

    known = [Notice(n, label) for n, label in ((normal(n), label) for n, label in notices) if n]
    found: dict[str, list[tuple[int, int]]] = {}
    for k, notice in enumerate(known):
        for at, piece in pieces(notice.text):
            if piece:
                found.setdefault(piece, []).append((k, at))
    a = ahocorasick.Automaton()
    for piece, where in found.items():
        a.add_word(piece, (len(piece), where))
    if found:
        a.make_automaton()
    return a, known


def windows(flat: str, notices: tuple[tuple[str, str], ...]) -> dict[int, list[tuple[int, int]]]:
    """Per notice the reach of every seed, cut back to words' borders: any occurrence that holds the seed lies inside."""
    automaton, known = machine(notices)
    begins: dict[int, set[int]] = {}
    if known:
        for end, (length, where) in automaton.iter(flat):
            for notice, at in where:
                begins.setdefault(notice, set()).add(end + 1 - length - at)
    out = {}
    for notice, starts in begins.items():
        reach, spans = known[notice].k, set()
        for s in starts:
            lo, hi = s - reach, s + known[notice].size + reach
            if lo > 0 and flat[lo - 1] != " ":
                lo = flat.find(" ", lo, hi) + 1 or hi
            if hi < len(flat) and flat[hi] != " ":
                hi = flat.rfind(" ", max(0, lo), hi)
            if hi > lo:
                spans.add((max(0, lo), min(hi, len(flat))))
        out[notice] = sorted(spans)
    return out


def places(notice: Notice, flat: str, spans: list[tuple[int, int]]) -> list[tuple[int, int, int]]:
    """(edits, start, end): the best place first; what overlaps one that stands is searched again beside it."""
    todo = [(*found, lo, hi) for lo, hi in spans if (found := notice.best(flat, lo, hi))]
    heapq.heapify(todo)
    starts: list[int] = []
    taken: dict[int, tuple[int, int]] = {}  # start -> (end, edits)
    while todo:
        k, a, b, lo, hi = heapq.heappop(todo)
        at = bisect_right(starts, a)
        near = [starts[i] for i in (at - 1, at) if 0 <= i < len(starts) and starts[i] < b and taken[starts[i]][0] > a]
        if not near:
            starts.insert(at, a)
            taken[a] = (b, k)
            continue
        if taken.get(a) == (b, k) and (lo, hi) == (a, b):
            continue
        # the parts of the window that no standing place covers
        at, left = max(0, bisect_right(starts, lo) - 1), lo
        for s in itertools.takewhile(lambda x: x < hi, itertools.islice(starts, at, None)):
            if taken[s][0] > lo:
                if s > left and (found := notice.best(flat, left, s - 1 if flat[s - 1] == " " else s)):
                    heapq.heappush(todo, (*found, left, s - 1 if flat[s - 1] == " " else s))
                left = taken[s][0] + 1
        if left < hi and (found := notice.best(flat, left, hi)):
            heapq.heappush(todo, (*found, left, hi))
    return [(taken[s][1], s, taken[s][0]) for s in starts]


def fuzzy(flat: str, notices: tuple[tuple[str, str], ...] = tuple(NOTICES.items())) -> list[tuple[int, int, str, int]]:
    """(start, end, label, edits) in the normal form."""
    known = machine(notices)[1]
    return sorted({(a, b, known[n].label, k) for n, spans in windows(flat, notices).items() for k, a, b in places(known[n], flat, spans)})


def scan(text: str | None, notices: tuple[tuple[str, str], ...] = tuple(NOTICES.items())) -> dict:
    """n_words, the exact places (first word, label), the fuzzy spans (first word, last word, label, edits)."""
    words = (text or "").encode().translate(_NORMAL).split()
    flat_b = b" ".join(words)
    exact, spans, starts = [], [], None
    padded = b" " + flat_b + b" "
    for phrase, label in PHRASES.items():
        want = b" " + phrase.encode() + b" "
        at = padded.find(want)
        while at >= 0:
            if starts is None:
                starts = [0, *itertools.accumulate(len(w) + 1 for w in words)]
            exact.append((bisect_left(starts, at), label))
            at = padded.find(want, at + 1)
    flat = flat_b.decode("utf-8", "replace")
    if found := fuzzy(flat, notices):
        if starts is None or len(flat) != len(flat_b):
            starts = [0, *itertools.accumulate(len(w) + 1 for w in flat.split(" "))]
        spans = [(bisect_right(starts, s) - 1, bisect_right(starts, e - 1) - 1, label, k, e - s) for s, e, label, k in found]
    return {"n_words": len(words), "exact": sorted(exact), "fuzzy": spans}


SPANS = "doc_id bigint, n_words bigint, exact array<struct<word:bigint,label:string>>, fuzzy array<struct<first:bigint,last:bigint,label:string,edits:int,chars:int>>"


def spans(docs: DataFrame, text: str = "text", notices: dict[str, str] | None = None) -> DataFrame:
    """doc_id, n_words, exact places and fuzzy spans, by word index from 0. ``notices``: notice -> label (short notices; the list is shipped to the tasks)."""
    own = tuple((NOTICES if notices is None else notices).items())

    def run(cols: list[list]) -> list[list]:
        found = [scan(t, own) for t in cols[1]]
        exact = [[{"word": w, "label": x} for w, x in f["exact"]] for f in found]
        near = [[dict(zip(("first", "last", "label", "edits", "chars"), s, strict=True)) for s in f["fuzzy"]] for f in found]
        return [cols[0], [f["n_words"] for f in found], exact, near]

    return per_document(docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col(text)), ["doc_id", text], SPANS, run)


def digest(docs: DataFrame) -> DataFrame:
    """The columns that op4 returns; score is 1 for an exact place, else 1 - edits / characters of the best fuzzy span.
    ``spans`` lists the fuzzy spans: first-last:label:edits, by place."""
    exact, near = F.col("exact"), F.col("fuzzy")
    word = exact["word"]
    best = F.array_max(F.transform(near, lambda s: F.lit(1.0) - s["edits"] / F.greatest(s["chars"], F.lit(1))))
    score = F.when(F.size(exact) > 0, F.lit(1.0)).otherwise(F.greatest(F.lit(0.0), F.coalesce(best, F.lit(0.0))))
    listed = F.array_join(F.transform(near, lambda s: F.concat(s["first"].cast("string"), F.lit("-"), s["last"].cast("string"), F.lit(":"), s["label"], F.lit(":"), s["edits"].cast("string"))), ";")
    return spans(docs).select(
        "doc_id", "n_words", F.size(exact).cast("bigint").alias("n_base"), F.array_min(word).alias("first_word"), F.array_max(word).alias("last_word"),
        F.array_join(F.array_sort(F.array_distinct(exact["label"])), ",").alias("base_labels"), F.array_join(F.array_sort(F.array_union(exact["label"], near["label"])), ",").alias("labels"), score.cast("double").alias("score"),
        F.size(near).cast("bigint").alias("n_spans"), listed.alias("spans"),
    )
