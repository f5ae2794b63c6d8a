"""Greedy word-piece token counts by a linear longest-match automaton.

The vocabulary stands in one trie: pieces that begin a word under one root, pieces that go on under another. A node's
failure link leads to the node of what is left after the longest pieces have been taken off the front of its string, and
the node holds how many were taken. So a word's number of pieces comes from one walk over its characters, and no piece is
ever built.

Cases: a null or empty text has no words and no tokens; a word that greedy matching can't finish is one unknown token;
repeated rows are counted one by one; texts are read whole.
"""

from __future__ import annotations

import re
from collections import deque
from collections.abc import Iterable, Iterator
from functools import cache

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

WORD = re.compile(r"\w+|[^\w\s]")
#: Counted words that a worker remembers.
MEMO = 200_000
MARK = "▁"  # what a piece that begins a word starts with in the vocabulary file


class Automaton:
    def __init__(self, starts: Iterable[str], inner: Iterable[str]):
        self.step: dict[tuple[int, str], int] = {}
        ends = [False, False]  # root of words, root of rests
        order: list[tuple[int, int, str]] = []
        for root, words in ((0, starts), (1, inner)):
            for w in words:
                at = root
                for c in w:
                    nxt = self.step.get((at, c))
                    if nxt is None:
                        nxt = self.step[at, c] = len(ends)
                        ends.append(False)
                        order.append((at, nxt, c))
                    at = nxt
                if w:
                    ends[at] = True
        self.fail, self.popped = [-1] * len(ends), [0] * len(ends)
        below: dict[int, list[tuple[int, str]]] = {}
        for parent, child, c in order:
            below.setdefault(parent, []).append((child, c))
        todo = deque([0, 1])
        while todo:
            parent = todo.popleft()
            for child, c in below.get(parent, ()):
                if ends[child]:
                    self.fail[child], self.popped[child] = 1, 1
                else:
                    z, n = self.fail[parent], self.popped[parent]
                    while z != -1 and (z, c) not in self.step:
                        n, z = n + self.popped[z], self.fail[z]
                    if z != -1:
                        self.fail[child], self.popped[child] = self.step[z, c], n
                todo.append(child)

    def count(self, word: str) -> int:
        """Pieces of the word, or 0 if greedy matching can't finish it."""
        step, at, n = self.step, 0, 0
        for c in word:
            while (nxt := step.get((at, c))) is None:
                n, at = n + self.popped[at], self.fail[at]
                if at == -1:
                    return 0
            at = nxt
        while at != 1:
            n, at = n + self.popped[at], self.fail[at]
            if at == -1:
                return 0
        return n


@cache
def automaton(path: str) -> Automaton:
    """From a sentencepiece model's pieces: those with the mark begin words, the others go on."""
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    pieces = [sp.id_to_piece(i) for i in range(sp.get_piece_size()) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i))]
    return Automaton([p[1:] for p in pieces if p[:1] == MARK and len(p) > 1], [p for p in pieces if MARK not in p])


class Memo(dict):
    def __init__(self, auto: Automaton):
        self.auto = auto

    def __missing__(self, word: str) -> int:
        if len(self) >= MEMO:
            self.clear()
        n = self[word] = self.auto.count(word)
        return n


def count_tokens(df: DataFrame, id_col: str, text_col: str, vocabulary: str) -> DataFrame:
    """(id, n_words, n_tokens, n_unknown). ``vocabulary``: path of a sentencepiece model that every executor can read."""

    @F.pandas_udf("n_words long, n_tokens long, n_unknown long")
    def counted(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        memo = Memo(automaton(vocabulary))
        for b in batches:
            out = []
            for text in b:
                ns = [memo[w] for w in WORD.findall(text)] if text else []
                none = ns.count(0)
                out.append((len(ns), sum(ns) + none, none))
            yield pd.DataFrame(out, columns=["n_words", "n_tokens", "n_unknown"])

    return df.select(F.col(id_col), counted(F.col(text_col)).alias("_c")).select(id_col, "_c.*")
