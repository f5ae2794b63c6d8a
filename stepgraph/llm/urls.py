"""URL filter: rules by host suffix and path prefix, then logistic regression on hashed character n-grams.

Cases: a null URL, or one without ``://``, has an empty host and path, meets no rule and is judged by the model on the
empty text (its bias). Repeated rows are judged one by one; an empty table gives an empty result; other columns of the
input play no part.
"""

from __future__ import annotations

import random
from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import LOWER, UPPER, broadcast_small

DIMS, ORDERS = 1 << 16, (3, 4, 5)
#: A labelled table beyond this many rows is refused: it is meant to be small and is trained on the driver.
MAX_LABELLED = 20_000
#: Beyond this many rules they are joined as a table, below it they are one expression.
MAX_INLINE_RULES = 200
#: Terms of the built-in labelled table. Hosts to block sell or track something in general terms, two of them joined by a hyphen
#: or run together; hosts to allow have everyday names, or names of syllables that mean nothing.
SOLD = "casino poker bingo slots betting bet jackpot lottery bonus loan credit pills pharma viagra replica adult xxx porn cams escort dating spam ads adserver click track popunder warez crack torrent malware phish free cheap discount".split()
HOOKS = "win bets online sale store zone club party deals best big super hot real fast now king world vip x farm tracker click pills".split()
PLAIN = "library university museum weather recipes encyclopedia parliament gazette astronomy gardening school village bakery football music travel science history theatre hospital council railway harbour forest kitchen painting grammar poetry".split()
SYLLABLES = "an ar be ce da el en fi ga he in ka la le ma mi ne no on or pa ra re sa se ta th ti to un ver wen".split()
SUBS, ZONES = ("", "www.", "blog.", "m.", "news."), ("example.com", "example.net", "example.org", "com", "org", "net")
PATHS = ("/", "", "/en/1", "/fr/3.html", "/about", "/a/b/c.html", "/index.php", "/de/20/", "/es/444")
ROWS_EACH = 600


def labelled_urls() -> list[tuple[str, int]]:
    """(url, bad): as many to block as to allow, drawn by a fixed seed from the terms above."""
    rnd = random.Random(17)
    rows = []
    for _ in range(ROWS_EACH):
        spam = rnd.choice(("-", "-", "-", "")).join((rnd.choice(SOLD), rnd.choice(HOOKS)) if rnd.random() < 0.7 else (rnd.choice(HOOKS), rnd.choice(SOLD)))
        kind = rnd.random()
        plain = "".join(rnd.choices(SYLLABLES, k=rnd.randint(2, 4))) if kind < 0.6 else rnd.choice(PLAIN) if kind < 0.8 else "-".join(rnd.sample(PLAIN, 2)) if kind < 0.9 else "".join(rnd.sample(PLAIN, 2))
        rows += [(f"https://{rnd.choice(SUBS)}{name}.{rnd.choice(ZONES)}{rnd.choice(PATHS)}", bad) for name, bad in ((spam, 1), (plain, 0))]
    return rows


def labelled_table(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(labelled_urls(), "url string, bad int")


def host_of(url: Column) -> Column:
    return F.translate(F.coalesce(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)([^?#]*)", 1), F.lit("")), UPPER, LOWER)


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)([^?#]*)", 2), F.lit(""))


def grams(hosts: Sequence[str], paths: Sequence[str]) -> tuple[np.ndarray, np.ndarray]:
    """Row number and hashed feature of every n-gram; host and path have features of their own."""
    rows, feats = [], []
    for part, seed in ((hosts, 0x9E3779B1), (paths, 0x85EBCA77)):
        raw = [b"^" + s.encode("utf-8", "surrogatepass") + b"$" for s in part]
        size = np.fromiter(map(len, raw), np.int64, len(raw))
        data = np.frombuffer(b"".join(raw), np.uint8).astype(np.uint64)
        row, left = np.repeat(np.arange(len(raw)), size), np.repeat(np.cumsum(size), size) - np.arange(len(data))
        h = np.full(len(data), seed, np.uint64)
        for n in range(1, max(ORDERS) + 1):
            m = len(data) - n + 1
            if m <= 0:
                break
            h = (h[:m] ^ data[n - 1 :]) * np.uint64(0x100000001B3)
            if n in ORDERS:
                ok = left[:m] >= n
                mixed = h[ok] ^ (h[ok] >> np.uint64(29))
                feats.append(((mixed * np.uint64(0xBF58476D1CE4E5B9)) >> np.uint64(48)) % np.uint64(DIMS))
                rows.append(row[:m][ok])
    if not rows:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    return np.concatenate(rows), np.concatenate(feats).astype(np.int64)


@dataclass
class UrlModel:
    weights: np.ndarray
    bias: float

    def score(self, hosts: Sequence[str], paths: Sequence[str]) -> np.ndarray:
        row, feat = grams(hosts, paths)
        n = np.bincount(row, minlength=len(hosts))
        z = np.bincount(row, self.weights[feat], len(hosts)) / np.sqrt(np.maximum(n, 1)) + self.bias
        return 1 / (1 + np.exp(-z))


def train(labelled: DataFrame, steps: int = 300, rate: float = 20.0, ridge: float = 1e-4) -> UrlModel:
    """Full-batch gradient descent; the same rows in any order give the same model."""
    parts = labelled.select(host_of(F.col("url")).alias("h"), path_of(F.col("url")).alias("p"), F.col("bad").cast("double").alias("y")).dropna().limit(MAX_LABELLED + 1).toPandas()
    if len(parts) > MAX_LABELLED:
        raise ValueError(f"more than {MAX_LABELLED} labelled URLs")
    parts = parts.sort_values(["h", "p", "y"])
    y, w, bias = parts.y.to_numpy(), np.zeros(DIMS), 0.0
    if not len(y):
        return UrlModel(w, 0.0)
    row, feat = grams(list(parts.h), list(parts.p))
    x = 1 / np.sqrt(np.maximum(np.bincount(row, minlength=len(y)), 1))[row]
    for _ in range(steps):
        p = 1 / (1 + np.exp(-(np.bincount(row, w[feat] * x, len(y)) + bias)))
        e = (p - y) / len(y)
        w -= rate * (np.bincount(feat, e[row] * x, DIMS) + ridge * w)
        bias -= rate * e.sum()
    return UrlModel(w, float(bias))


def split_rule(rule: str) -> tuple[str, str]:
    host, slash, path = rule.partition("/")
    return host.translate(str.maketrans(UPPER, LOWER)), slash + path


def by_rules(df: DataFrame, rules: Sequence[tuple[str, str]]) -> DataFrame:
    """Adds rule and rule_verdict for a short list of (rule, verdict): one expression, the longest rule first. Of rules of one
    length, that of the longer host wins; of one rule with two verdicts, block."""
    host, path, fits = F.col("host"), F.col("path"), []
    for rule, verdict in sorted(rules, key=lambda r: (len(r[0]), len(split_rule(r[0])[0]), r[1], r[0]), reverse=True):
        h, p = split_rule(rule)
        fits.append((((host == h) | host.endswith("." + h)) & path.startswith(p), rule, verdict))
    rule = out = F.lit(None).cast("string")
    for test, name, verdict in reversed(fits):
        rule, out = F.when(test, F.lit(name)).otherwise(rule), F.when(test, F.lit(verdict)).otherwise(out)
    return df.withColumn("rule", rule).withColumn("rule_verdict", out)


def by_rule_table(df: DataFrame, rules: DataFrame) -> DataFrame:
    """The same for any number of rules (rule, verdict): the distinct (host, path) pairs meet rules on the host's suffixes."""
    pairs = df.select("host", "path").distinct()
    labels = F.split("host", r"\.")
    tails = pairs.withColumn("tail", F.explode(F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))))
    own = F.substring_index("rule", "/", 1)
    r = rules.select("rule", F.col("verdict").alias("rule_verdict"), F.translate(own, UPPER, LOWER).alias("tail"), F.expr("substring(rule, length(substring_index(rule, '/', 1)) + 1)").alias("rule_path"))
    order = F.struct(F.length("rule").alias("n"), F.length("tail").alias("h"), "rule_verdict", "rule")
    met = tails.join(broadcast_small(r, rules.count()), "tail").where(F.col("path").startswith(F.col("rule_path")))
    best = met.groupBy("host", "path").agg(F.max(order).alias("b"))
    return df.join(best.select("host", "path", "b.rule", "b.rule_verdict"), ["host", "path"], "left")


def judge_urls(df: DataFrame, id_col: str, url_col: str, rules: Sequence[tuple[str, str]] | DataFrame, model: UrlModel, threshold: float = 0.5) -> DataFrame:
    """(id, host, path, rule, verdict, score): a fitting rule decides, else the model blocks from ``threshold`` up."""

    @F.pandas_udf("double")
    def score(batches: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        for h, p in batches:
            yield pd.Series(model.score(list(h), list(p)))

    parts = df.select(F.col(id_col).alias("_id"), host_of(F.col(url_col)).alias("host"), path_of(F.col(url_col)).alias("path"))
    if isinstance(rules, DataFrame) or len(rules) > MAX_INLINE_RULES:
        table = rules if isinstance(rules, DataFrame) else df.sparkSession.createDataFrame(list(rules), "rule string, verdict string")
        ruled = by_rule_table(parts, table)
    else:
        ruled = by_rules(parts, rules)
    scored = ruled.withColumn("score", score("host", "path"))
    return scored.select(F.col("_id").alias(id_col), "host", "path", "rule", F.coalesce("rule_verdict", F.when(F.col("score") >= threshold, "block").otherwise("allow")).alias("verdict"), "score")
