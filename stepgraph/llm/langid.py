"""Language identification by interpolated Kneser-Ney character models.

The n-grams of all languages stand in one sorted array of 64-bit hashes per order, each with its finished log
probability in every language, so one binary search serves all of them; only n-grams that no language has seen take the
back-off weights of their context and go on to the next lower order.

Cases: a null text, or one without letters, is ``und`` with score 0 and is rejected; empty tables give empty results;
rows without a language are never trained on; repeated rows are judged one by one. Texts are read whole: a text of over
``PIECE`` characters is scored in pieces whose sums are added. Languages that tie go to the smaller name.
"""

from __future__ import annotations

import math
from collections import Counter, defaultdict
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field
from functools import cache

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import small_batches, whole_rows

ORDER, PIECE, CHUNK = 4, 1_000_000, 500_000
#: About so many labelled documents of each language are fitted on, and a quarter as many calibrate the rejection.
DOCS_PER_LANG = 400
#: More languages than this are refused.
MAX_LANGS = 500
GAP = 0  # code of the boundary in front of a text


@cache
def classes() -> np.ndarray:
    """Code points below 2**16: a letter maps to its lower case, anything else to a space."""
    out = np.full(1 << 16, 32, np.uint32)
    for c in range(1 << 16):
        s = chr(c)
        if s.isalpha():
            low = s.lower()
            out[c] = ord(low) if len(low) == 1 else c
    out[GAP] = GAP
    return out


def normal(texts: Iterable[str]) -> tuple[np.ndarray, np.ndarray]:
    """Codes of the texts behind ORDER-1 gaps each, runs of non-letters as one space; and where each text begins."""
    gap = "\0" * (ORDER - 1)
    codes = np.frombuffer("".join(gap + t.replace("\0", " ") for t in texts).encode("utf-32-le", "surrogatepass"), np.uint32)
    wide = codes >= 1 << 16
    out = classes()[np.where(wide, 32, codes)]
    if wide.any():
        out[wide] = [ord(chr(c).lower()) if chr(c).isalpha() else 32 for c in codes[wide]]
    before = np.concatenate([[32], out[:-1]])
    out = out[~((out == 32) & ((before == 32) | (before == GAP)))]
    return out, np.flatnonzero(out == GAP)[:: ORDER - 1]


def rolled(codes: np.ndarray) -> list[np.ndarray]:
    """Hash of the n-gram that ends at each place, for n from 1 to ORDER (index n)."""
    c = codes.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    c ^= c >> np.uint64(31)
    out, h = [np.zeros(0, np.uint64)], c
    for n in range(1, ORDER + 1):
        if n > 1:
            back = np.concatenate([np.zeros(min(n - 1, len(c)), np.uint64), c[: max(len(c) - n + 1, 0)]])
            h = h + back * np.uint64(pow(0xD1B54A32D192ED03, n, 1 << 64))
        out.append(h)
    return out


def hashed(gram: str) -> int:
    return int(rolled(np.array([ord(c) for c in gram], np.uint32))[len(gram)][-1])


def find(keys: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places of h in the sorted keys, and which are really there."""
    if not len(keys):
        return np.zeros(len(h), np.int64), np.zeros(len(h), bool)
    at = np.searchsorted(keys, h)
    at[at == len(keys)] = 0
    return at, keys[at] == h


@dataclass
class LangModel:
    langs: list[str]
    grams: list[np.ndarray] = field(default_factory=list)  # by order: sorted hashes
    logp: list[np.ndarray] = field(default_factory=list)  # their log probabilities, one column a language
    contexts: list[np.ndarray] = field(default_factory=list)
    backoff: list[np.ndarray] = field(default_factory=list)
    floor: float = math.log(1e-6)
    centre: np.ndarray | None = None  # usual cross-entropy
    limit: np.ndarray | None = None  # most that a text may exceed it by, times the root of its letters

    def sums(self, codes: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Per text: summed log probability in every language, and how many characters were scored."""
        hs = rolled(codes)
        todo = np.flatnonzero(codes != GAP)
        out = np.zeros((len(codes), len(self.langs)), np.float32)
        carried = np.zeros((len(todo), len(self.langs)), np.float32)
        for n in range(ORDER, 0, -1):
            at, ok = find(self.grams[n], hs[n][todo])
            out[todo[ok]] = carried[ok] + self.logp[n][at[ok]]
            todo, carried = todo[~ok], carried[~ok]
            if not len(todo):
                break
            if n > 1:
                at, ok = find(self.contexts[n], hs[n - 1][todo - 1])
                carried[ok] += self.backoff[n][at[ok]]
        else:
            out[todo] = carried + self.floor
        sums = np.add.reduceat(out.astype(np.float64), starts, axis=0) if len(starts) else np.zeros((0, len(self.langs)))
        return sums, np.add.reduceat((codes > 32).astype(np.int64), starts) if len(starts) else np.zeros(0, np.int64)

    def judge(self, texts: list[str | None]) -> tuple[list[str], np.ndarray, np.ndarray, np.ndarray]:
        """Language, score, cross-entropy a letter and whether it is rejected."""
        pieces, owner = [], []
        for i, t in enumerate(texts):
            for k in range(0, max(len(t or ""), 1), PIECE):
                pieces.append((t or "")[k : k + PIECE])
                owner.append(i)
        total, letters = np.zeros((len(texts), len(self.langs))), np.zeros(len(texts), np.int64)
        i = 0
        while i < len(pieces):
            j, size = i, 0
            while j < len(pieces) and (j == i or size + len(pieces[j]) <= CHUNK):
                size += len(pieces[j])
                j += 1
            s, n = self.sums(*normal(pieces[i:j]))
            np.add.at(total, owner[i:j], s)
            np.add.at(letters, owner[i:j], n)
            i = j
        if not self.langs:
            return ["und"] * len(texts), np.zeros(len(texts)), np.zeros(len(texts)), np.ones(len(texts), bool)
        ce = -total / np.maximum(letters, 1)[:, None]
        best = ce.argmin(1)
        low = ce[np.arange(len(best)), best]
        score = 1 / np.exp(-(ce - low[:, None]) * np.minimum(letters, 50)[:, None]).sum(1)
        none = letters == 0
        rejected = none.copy()
        if self.limit is not None:
            rejected |= (low - self.centre[best]) * np.sqrt(np.minimum(letters, 200)) > self.limit[best]
        return ["und" if z else self.langs[b] for b, z in zip(best, none, strict=True)], np.where(none, 0.0, score), low, rejected


def kneser_ney(counts: dict[str, dict[str, int]], discount: float = 0.75) -> LangModel:
    """counts: language -> n-gram of ORDER characters (GAP in front of a text's begin) -> how often."""
    langs = sorted(counts)
    model = LangModel(langs, [np.zeros(0, np.uint64)] * (ORDER + 1), [None] * (ORDER + 1), [np.zeros(0, np.uint64)] * (ORDER + 1), [None] * (ORDER + 1))
    levels = {}  # language -> order -> n-gram -> raw count at the top, number of left neighbours below
    for lang in langs:
        by = {ORDER: dict(counts[lang])}
        for n in range(ORDER - 1, 0, -1):
            by[n] = Counter(g[1:] for g in by[n + 1])
        levels[lang] = by
    symbols = len({g[-1] for lang in langs for g in counts[lang]}) + 1
    prob = {lang: {} for lang in langs}
    for n in range(1, ORDER + 1):
        every = sorted({g for lang in langs for g in levels[lang][n]})
        ctxs = sorted({g[:-1] for g in every})
        logp, back = np.zeros((len(every), len(langs)), np.float32), np.zeros((len(ctxs), len(langs)), np.float32)
        for k, lang in enumerate(langs):
            total, kinds = defaultdict(int), defaultdict(int)
            for g, c in levels[lang][n].items():
                total[g[:-1]] += c
                kinds[g[:-1]] += 1
            keep = {c: discount * kinds[c] / total[c] for c in total}
            now = {}
            for i, g in enumerate(every):
                h = g[:-1]
                lower = prob[lang].get(g[1:], 1e-9) if n > 1 else 1 / symbols
                p = keep.get(h, 1.0) * lower
                if c := levels[lang][n].get(g):
                    p += (c - discount) / total[h]
                now[g] = p
                logp[i, k] = math.log(p)
            for i, h in enumerate(ctxs):
                back[i, k] = math.log(keep.get(h, 1.0))
            prob[lang] = now
        for names, keys, values, rows in ((every, model.grams, model.logp, logp), (ctxs, model.contexts, model.backoff, back)):
            h = np.array([hashed(g) if g else 0 for g in names], np.uint64)
            order = np.argsort(h, kind="stable")
            keys[n], values[n] = h[order], rows[order]
    return model


def training_sample(df: DataFrame, id_col: str, lang_col: str, per_lang: int) -> DataFrame:
    """About ``per_lang`` rows of each language, chosen by a hash of the id; with ``u`` in 0..99 for splitting."""
    known = df.where(F.col(lang_col).isNotNull())
    sizes = known.groupBy(lang_col).count().limit(MAX_LANGS + 1).collect()
    if len(sizes) > MAX_LANGS:
        raise ValueError(f"more than {MAX_LANGS} languages")
    share = F.create_map(*[x for r in sizes for x in (F.lit(r[0]), F.lit(min(1.0, per_lang / r[1])))]) if sizes else F.create_map(F.lit(""), F.lit(0.0))
    draw = F.xxhash64(F.col(id_col).cast("string"), F.lit("sample"))
    return known.where(F.pmod(draw, F.lit(1_000_000)) < share[F.col(lang_col)] * 1_000_000).withColumn("u", F.pmod(F.shiftright(draw, 24), F.lit(100)))


def train(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", per_lang: int = DOCS_PER_LANG, slack: float = 1.5) -> LangModel:
    """Counts run on the executors over a bounded sample of labelled rows; what comes back is a table of n-grams."""
    small_batches(df.sparkSession)
    rows = training_sample(df.select(id_col, text_col, lang_col), id_col, lang_col, per_lang * 5 // 4).select(F.col(lang_col).alias("lang"), F.col(text_col).alias("text"), "u").where(F.col("text").isNotNull())

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            by: dict[str, Counter] = defaultdict(Counter)
            for lang, text in zip(b.lang, b.text, strict=True):
                codes, _ = normal([text])
                s = "".join(map(chr, codes))
                by[lang].update(map("".join, zip(*(s[i:] for i in range(ORDER)), strict=False)))
            for lang, c in by.items():
                if c:  # a text of few letters has none
                    yield pd.DataFrame({"lang": lang, "gram": list(c), "n": list(c.values())})

    got = rows.where("u < 80").select("lang", "text").mapInPandas(count, "lang string, gram string, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n")).toPandas()
    counts = {lang: dict(zip(g.gram, map(int, g.n), strict=True)) for lang, g in got.groupby("lang")}
    model = kneser_ney(counts)
    if not counts:
        return model

    def held(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            name, _, ce, _ = model.judge(list(b.text))
            n = [sum(map(str.isalpha, t)) for t in b.text]
            yield pd.DataFrame({"lang": b.lang, "same": np.array(name) == b.lang.to_numpy(), "ce": ce, "n": n})

    seen = rows.where("u >= 80").select("lang", "text").mapInPandas(held, "lang string, same boolean, ce double, n long").where("same and n > 0").toPandas()
    model.centre, model.limit = np.zeros(len(model.langs)), np.full(len(model.langs), np.inf)
    for k, lang in enumerate(model.langs):
        x = seen[seen.lang == lang]
        if len(x) >= 5:  # else nothing is known of its spread, and nothing is rejected
            model.centre[k] = x.ce.median()
            model.limit[k] = slack * max(float(((x.ce - model.centre[k]) * np.sqrt(np.minimum(x.n, 200))).max()), 5.0)
    return model


def identify(df: DataFrame, model: LangModel, text_col: str = "text") -> DataFrame:
    """Adds lang_pred, score, cross_entropy and rejected; a column of the input that has such a name is replaced."""

    @F.pandas_udf("lang_pred string, score double, cross_entropy double, rejected boolean")
    def judged(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        for b in batches:
            name, score, ce, rejected = model.judge([None if t is None else t for t in b])
            yield pd.DataFrame({"lang_pred": name, "score": score, "cross_entropy": ce, "rejected": rejected})

    small_batches(df.sparkSession)
    names = ["lang_pred", "score", "cross_entropy", "rejected"]
    out = df.select(whole_rows(df), judged(F.col(text_col)).alias("_judged"))
    return out.select(*[F.col("_all").getField(c).alias(c) for c in df.columns if c not in names], *[F.col(f"_judged.{n}").alias(n) for n in names])


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2, F.lit(False))
