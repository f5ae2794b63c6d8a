"""License scan: exact set-similarity join of text blocks with license templates, beside exact phrases.

A template is found where a stretch of words holds at least the threshold's share of its words. Line ends don't matter, as
notices are wrapped. A stretch has ``STRETCH`` words, or twice as many as the longest template. The text is read in blocks
that overlap so far that every stretch lies in one. A template's words are ordered by how many documents of the whole
table hold them, rarest first. A block that holds at least the threshold's share of a template holds one of the template's
first words (prefix), has at least as many words as are needed (length), and after its first common word both sides still
have enough (position); what passes is compared in full, and its densest stretch counts.

Cases: a null or empty text has no words, no places and no labels; repeated rows are scanned one by one; texts are read
whole; an empty table gives an empty result.
"""

from __future__ import annotations

from bisect import bisect_right
from collections import Counter
from collections.abc import Iterator, Sequence
from itertools import accumulate
from math import ceil

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

STRETCH = 64
#: More templates than this are refused: they go to every executor.
MAX_TEMPLATES = 10_000
# Notices as public licenses word them, and the label of each.
TEMPLATES = (
    ("mit", "Released under the MIT License."),
    ("mit", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files"),
    ("apache", "Licensed under the Apache License, Version 2.0."),
    ("apache", "you may not use this file except in compliance with the License. You may obtain a copy of the License at"),
    ("gpl", "This work is licensed under the GNU General Public License, version 3."),
    ("gpl", "you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation"),
    ("bsd", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"),
    ("mpl", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("cc-by-nc", "Licensed under CC BY-NC 4.0."),
    ("cc-by", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
)
#: Non-word bytes become spaces, but line ends stay, as places are given by line; A-Z become small. Bytes from 0x80 up belong to words.
TABLE = bytes(10 if c == 10 else c + 32 if 65 <= c <= 90 else c if c >= 128 or 48 <= c <= 57 or 97 <= c <= 122 else 32 for c in range(256))


def clean(text: str | None) -> bytes:
    return (text or "").encode("utf-8", "surrogatepass").translate(TABLE)


class Templates:
    def __init__(self, templates: Sequence[tuple[str, str]], frequency: dict[bytes, int], threshold: float):
        if len(templates) > MAX_TEMPLATES:
            raise ValueError(f"more than {MAX_TEMPLATES} templates")
        self.rank = {w: i for i, w in enumerate(sorted({w for _, t in templates for w in clean(t).split()}, key=lambda w: (frequency.get(w, 0), w)))}
        self.sets, self.index = [], {}
        for k, (label, text) in enumerate(templates):
            ranks = sorted({self.rank[w] for w in clean(text).split()})
            need = max(1, ceil(threshold * len(ranks) - 1e-9))
            self.sets.append((label, ranks, frozenset(ranks), need))
            for at, r in enumerate(ranks[: len(ranks) - need + 1]):
                self.index.setdefault(r, []).append((k, at))
        self.first = {w for w, r in self.rank.items() if r in self.index}
        self.stretch = max(STRETCH, *(2 * len(clean(t).split()) for _, t in templates)) if templates else STRETCH

    def match(self, words: list[bytes]) -> dict[int, float]:
        """Share of every template that the block holds enough of."""
        ranks = sorted({r for w in words if (r := self.rank.get(w)) is not None})
        out, met = {}, set()
        for j, r in enumerate(ranks):
            for k, i in self.index.get(r, ()):
                if k in met:
                    continue
                met.add(k)
                _, order, whole, need = self.sets[k]
                if len(ranks) >= need and 1 + min(len(order) - i, len(ranks) - j) - 1 >= need and (n := len(whole.intersection(ranks))) >= need:
                    out[k] = n / len(whole)
        return out


    def densest(self, k: int, words: list[bytes]) -> tuple[int, int]:
        """Most words of a template that a stretch of the block holds, and where the first of them is."""
        whole, held, left, best = self.sets[k][2], Counter(), 0, (0, 0)
        at = [(i, r) for i, w in enumerate(words) if (r := self.rank.get(w)) in whole]
        for i, r in at:
            held[r] += 1
            while i - at[left][0] >= self.stretch:
                held[at[left][1]] -= 1
                if not held[at[left][1]]:
                    del held[at[left][1]]
                left += 1
            best = max(best, (len(held), -at[left][0]))
        return best[0], -best[1]

    def find(self, words: list[bytes]) -> dict[tuple[int, int], float]:
        """Share of every template that a stretch of the text holds enough of, by (template, place of the first word)."""
        out, step = {}, self.stretch // 2
        for i in range(0, max(1, len(words) - self.stretch + 1), step):
            block = words[i : i + self.stretch + step - 1]
            if self.first.isdisjoint(block):
                continue
            for k in self.match(block):
                _, _, whole, need = self.sets[k]
                n, at = self.densest(k, block)
                if n >= need:
                    out[k, i + at] = n / len(whole)
        return out


def word_frequency(df: DataFrame, text_col: str, templates: Sequence[tuple[str, str]]) -> dict[bytes, int]:
    """How many documents hold each word of the templates, over all documents."""
    words = frozenset(w for _, t in templates for w in clean(t).split())

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        n: Counter[bytes] = Counter()
        for b in batches:
            for text in b.iloc[:, 0]:
                n.update(words.intersection(clean(text).split()))
        yield pd.DataFrame({"word": list(n), "n": list(n.values())})

    got = df.select(text_col).mapInPandas(count, "word binary, n long").groupBy("word").agg(F.sum("n").alias("n")).collect()
    return {bytes(r.word): r.n for r in got}


def places(words: list[bytes], phrase: list[bytes]) -> list[int]:
    out, at, last = [], -1, phrase[-1]
    try:
        while True:
            at = words.index(last, at + 1)
            start = at - len(phrase) + 1
            if start >= 0 and words[start : at + 1] == phrase:
                out.append(start)
    except ValueError:
        return out


def scan(df: DataFrame, id_col: str, text_col: str, phrases: Sequence[tuple[str, str]], templates: Sequence[tuple[str, str]] = TEMPLATES, threshold: float = 0.8) -> DataFrame:
    """(id, n_words, n_base, first_word, last_word, base_labels, labels, score, matches). ``matches`` has the text's
    matching stretches: label, number of the line they begin in, share of the template."""
    known = Templates(templates, word_frequency(df, text_col, templates), threshold)
    wanted = [(clean(p).split(), label) for p, label in phrases]
    kind = "n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, matches array<struct<label:string,line:int,share:double>>"

    def one(text: str | None) -> tuple:
        data = clean(text)
        words = data.split()
        held, base, labels, found, score = set(words), [], set(), [], 0.0
        for phrase, label in wanted:
            if held.issuperset(phrase) and (got := places(words, phrase)):
                base += got
                labels.add(label)
        named = ",".join(sorted(labels))
        if not held.isdisjoint(known.first):
            if got := known.find(words):
                ends = list(accumulate(len(line.split()) for line in data.split(b"\n")))
                found = [(known.sets[k][0], bisect_right(ends, at), share) for (k, at), share in got.items()]
                score = max(got.values())
        labels.update(x[0] for x in found)
        return len(words), len(base), min(base, default=None), max(base, default=None), named, ",".join(sorted(labels)), 1.0 if base else score, found

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        names = [x.split()[0] for x in kind.split(", ")]
        for b in batches:
            got = pd.DataFrame([one(t) for t in b["_text"]], columns=names)
            got["first_word"], got["last_word"] = got["first_word"].astype("Int64"), got["last_word"].astype("Int64")
            got["matches"] = [[{"label": a, "line": n, "share": s} for a, n, s in m] for m in got["matches"]]
            got.insert(0, id_col, b["_id"].to_numpy())
            yield got

    id_type = df.schema[id_col].dataType.simpleString()
    return df.select(F.col(id_col).alias("_id"), F.col(text_col).alias("_text")).mapInPandas(run, f"`{id_col}` {id_type}, {kind}")
