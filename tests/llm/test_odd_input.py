"""Odd input: names that clash, ids that are shared or null, numbers out of range, ties, very long texts, and empty tables."""

import random
import re
from collections import Counter
from types import SimpleNamespace

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from stepgraph.llm import binpack, common, exact_dedup, langid, licenses, mixing, ngram_join, packing, queries, sharding, urls, vectors, wordpiece

CLASHING = ["_id", "_rows", "_kept", "_all", "_text", "_p", "_pass", "_judged", "_hash", "_sha", "_of", "_size", "_nth", "whole", "part", "size", "key", "node", "kept", "shard", "slot", "bytes", "h", "tail", "vec", "n"]


def clashing(df):
    """The table with a column of every name that an operator uses for its own."""
    return df.withColumns({c: F.lit(f"own {c}") for c in CLASHING if c not in df.columns})


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(1, "a b\n c d", "en", "s"), (2, "A B\n C D", "en", "s"), (3, None, None, None), (4, "", "en", "s"), (None, "e f g", "en", None), (None, "e f g", "en", None), (5, "x y z " * 40_000, "en", "s"), (6, "q" * 200_000, "en", "s")]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")


def test_local_folder_only_for_a_local_master():
    far = SimpleNamespace(conf=SimpleNamespace(get=lambda k, d=None: d), sparkContext=SimpleNamespace(master="spark://x:7077"))
    with pytest.raises(ValueError):
        common.shared_folder(far)


def test_names_that_clash(spark, docs):
    wide = clashing(docs)
    model = langid.train(spark.read.parquet("/root/testdata/sf0.001/documents.parquet"))
    for out in (exact_dedup.drop_duplicates(wide), ngram_join.keep_one(wide), mixing.mixed_rows(wide, "doc_id", "text", "source", (1.0,)), langid.identify(wide, model)):
        assert out.columns[: len(wide.columns)] == wide.columns
        assert all(r["_id"] == "own _id" and r["_judged"] == "own _judged" for r in out.collect())
    for out in (exact_dedup.mark_duplicates(wide), ngram_join.near_duplicates(wide), sharding.shard_groups(wide, "doc_id", "text", shards=3), licenses.scan(wide, "doc_id", "text", queries.PHRASES), packing.pack(wide, "doc_id", "text", queries.tokenizer_files()), urls.judge_urls(wide, "doc_id", "text", queries.RULES, urls.UrlModel(np.zeros(urls.DIMS), 0.0)), mixing.mix(wide, "doc_id", "source", mixing.n_words(F.col("text")), (1.0,))):
        assert out.count() >= 8
    import public_tokenizers

    assert wordpiece.count_tokens(wide, "doc_id", "text", public_tokenizers.path("piece_bpe_32k.model")).count() == 8


def test_copies_of_shared_ids(spark):
    rows = [(1, "same"), (7, "SAME"), (7, "a text of its own"), (None, "same"), (None, "other"), (8, "twice"), (8, "twice")]
    df = spark.createDataFrame([(i, t, k) for k, (i, t) in enumerate(rows)], "doc_id long, text string, k int")
    left = {r.k for r in exact_dedup.drop_duplicates(df, keep="min").collect()}
    assert left in ({0, 2, 4, 5}, {0, 2, 4, 6})


def test_mix_of_shared_ids_meets_its_target(spark):
    rows = [(1, "a b c d e", "x"), (1, "f g", "x"), (1, "h i j", "x"), (None, "k\nl  m", "x"), (None, "n o p", "x"), (2, "q r s t u v", "y")]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    plan = mixing.mix(df, "doc_id", "source", mixing.n_words(F.col("text")), (1.0, 2.0)).collect()
    taken = Counter()
    for r in plan:
        taken[r.source] += r.taken
    got = Counter()
    for r in mixing.mixed_rows(df, "doc_id", "text", "source", (1.0, 2.0)).collect():
        got[r.source] += len(r.text.split())
    assert got == taken and sum(got.values()) == 22


def test_cut_text_keeps_its_gaps(spark):
    text = "\n\na  b\tc\n d e f g"
    df = spark.createDataFrame([(1, text, "x"), (2, "h i j k l m n", "y")], "doc_id long, text string, source string")
    got = [r.text for r in mixing.mixed_rows(df, "doc_id", "text", "source", (1.0, 3.0)).collect() if r.doc_id == 1]
    assert got and all(text.startswith(t) for t in got)


@pytest.mark.parametrize("scale", [1e200, 1e-160, 1e-323, 1.0])
def test_nearest_far_out_of_range(spark, scale):
    rnd = np.random.default_rng(3)
    vecs = [(i, [float(x) for x in np.rint(rnd.normal(size=6) * 9) * scale]) for i in range(60)]
    vecs = [(i, v) for i, v in vecs if any(v)]
    got = vectors.nearest(spark.createDataFrame(vecs, "vec_id long, embedding array<double>"), "vec_id", "embedding", F.col("vec_id") % 20 == 0, k=4, block=16).collect()
    for q, v in vecs:
        if q % 20 == 0:
            def score(w, v=v):
                with np.errstate(all="ignore"):
                    total = 0.0
                    for a, b in zip(v, w, strict=True):
                        total += float(np.float64(a) * np.float64(b))
                return -np.inf if np.isnan(total) else total

            want = sorted((-score(w), i) for i, w in vecs if i != q)[:4]
            assert [(r.vec_id, r.score) for r in sorted(got, key=lambda r: r["rank"]) if r.query_id == q] == [(i, -s) for s, i in want]


def test_packing_of_counts_is_best_fit_decreasing():
    rnd = random.Random(2)
    for _ in range(60):
        sizes = sorted((rnd.choice([1, 2, 3, 7, 20, 55, 120]) for _ in range(rnd.randint(1, 80))), reverse=True)
        items = sorted(Counter(sizes).items(), reverse=True)
        want, bins = binpack.best_fit_decreasing(sizes, 100)
        runs, n = binpack.pack_counts(items, 100)
        got = []
        for size, count in items:
            own = [(first, b) for s, first, b in runs if s == size] + [(count, None)]
            for (first, b), (end, _) in zip(own, own[1:], strict=False):
                got += [b] * (end - first)
        assert (got, n) == (want, bins)
        load = Counter()
        for (size, first, b), nxt in zip(runs, [*runs[1:], None], strict=True):
            load[b] += size * ((nxt[1] if nxt and nxt[0] == size else dict(items)[size]) - first)
        assert all(x <= 100 or x == 120 for x in load.values())


@pytest.mark.parametrize("rows", [1_000_000, 0])
def test_shards_by_brute_force(spark, monkeypatch, rows):
    """Whole results, by broadcast and by shuffle: groups stay whole, slots are gapless, and a capacity is kept by few shards."""
    monkeypatch.setattr(common, "BROADCAST_ROWS", rows)
    rnd = random.Random(9)
    texts = [None, "", *("w" * rnd.choice([5, 9, 30, 80]) + str(rnd.randint(0, 30)) for _ in range(400))]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    bytes_of = Counter()
    for t in texts:
        bytes_of[t or ""] += len(t or "") + 1
    sizes = sorted(bytes_of.values(), reverse=True)
    for kind in ({"shards": 8}, {"capacity": 700}):
        got = sharding.shard_groups(df, "doc_id", "text", **kind).collect()
        place = {texts[r.doc_id] or "": r.shard for r in got}
        assert len(got) == len(texts) and all(place[texts[r.doc_id] or ""] == r.shard for r in got)
        load = Counter()
        for t, n in bytes_of.items():
            load[place[t]] += n
        for k in load:
            assert sorted(r.slot for r in got if r.shard == k) == list(range(sum(r.shard == k for r in got)))
        if "capacity" in kind:
            assert len(load) == binpack.best_fit_decreasing(sizes, 700)[1] and all(n <= 700 or sum(place[t] == k for t in bytes_of) == 1 for k, n in load.items())
        else:
            assert len(load) == 8 and max(load.values()) - min(load.values()) <= max(sizes)


def test_rules_in_both_forms_against_brute_force(spark):
    rnd = random.Random(4)
    part = lambda: ".".join(rnd.choice(["a", "B", "org", "x"]) for _ in range(rnd.randint(1, 3)))
    rules = [("org/abcd", "allow"), ("x.org/ab", "block"), ("a/", "allow"), ("a/", "block"), *((f"{part()}/{rnd.choice(['', 'a', 'ab'])}", rnd.choice(["allow", "block"])) for _ in range(25))]
    given = ["s://x.org/abcd", "s://A.x.ORG/abcd?q", "s://É.org/ab", *(f"s://{part()}/{rnd.choice(['', 'a', 'ab', 'abc'])}" for _ in range(150))]
    pages = spark.createDataFrame(list(enumerate(given)), "page_id long, url string")
    lower = lambda s: "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in s)
    model = urls.UrlModel(np.zeros(urls.DIMS), -1.0)
    for form in (rules, spark.createDataFrame(rules, "rule string, verdict string")):
        for r in urls.judge_urls(pages, "page_id", "url", form, model).collect():
            m = re.match(r"(?s)^.*?://([^/?#]*)([^?#]*)", given[r.page_id])
            host, path = lower(m[1]), m[2]
            fits = []
            for rule, verdict in rules:
                h, slash, p = rule.partition("/")
                if (host == lower(h) or host.endswith("." + lower(h))) and path.startswith(slash + p):
                    fits.append((len(rule), len(h), verdict, rule))
            want = (max(fits)[3], max(fits)[2]) if fits else (None, "allow")
            assert (r.rule, r.verdict) == want, given[r.page_id]


def test_labelled_urls_hold_no_given_host(spark):
    hosts = {r.h for sf in ("sf0.01", "sf0.1") for r in spark.read.parquet(f"/root/testdata/{sf}/pages.parquet").select(urls.host_of(F.col("url")).alias("h")).distinct().collect()}
    made = spark.createDataFrame(urls.labelled_urls(), "url string, bad int").select(urls.host_of(F.col("url")).alias("h")).distinct().collect()
    assert not hosts & {r.h for r in made}


@pytest.mark.parametrize("empty", [True, False])
def test_stages_of_the_pipeline(spark, docs, empty):
    """Nulls, ties, repeats and very long texts, and a table without rows, through every stage by itself."""
    df = docs.limit(0) if empty else docs
    for name, stage in corpus_pipeline.STAGES:
        got = stage(spark, df, "/root/testdata/sf0.001")
        rows = got.collect()
        assert empty <= (not rows)
        if name != "sequences":
            assert got.columns == df.columns
    if not empty:
        kept = Counter(r.text for r in corpus_pipeline.near_copies(spark, docs, "").collect())
        assert kept["e f g"] == 1 and kept[None] == 1 and kept[""] == 1 and len([t for t in kept if t and t[0] in "aA"]) == 1
