"""Each operator on small cases: brute force, round trips, held-out accuracy, and the defined results of odd input."""

import hashlib
import itertools
import random
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from stepgraph.llm import binpack, common, exact_dedup, langid, licenses, mixing, ngram_join, packing, prefix_index, queries, sharding, shingles, urls, vectors, wordpiece

SF = "/root/testdata/sf0.001"
DOC = "doc_id long, text string, lang string, source string, score double"
ODD = [(1, None, None, None, 0.5), (2, "", "en", "a", 0.5), (3, "Ab c", "en", "a", 0.5), (3, "Ab c", "en", "a", 0.5), (4, "aB C", "de", "b", None), (5, "x " * 5000, "de", "b", 1.0)]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ODD, DOC)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOC)


def test_urls(spark):
    given = ["https://A.Example.org/en/12?q", "http://x.com/de/1", "http://x.com/fr", "no scheme", None, "x://Y.com", "http://www.casino-win.example.net/en/1"]
    pages = spark.createDataFrame(list(enumerate(given)), "page_id long, url string")
    model = urls.train(urls.labelled_table(spark))
    got = {r.page_id: r for r in urls.judge_urls(pages, "page_id", "url", queries.RULES, model).collect()}
    assert [(got[i].host, got[i].path, got[i].rule) for i in range(6)] == [("a.example.org", "/en/12", "example.org/en/1"), ("x.com", "/de/1", "com/de/"), ("x.com", "/fr", None), ("", "", None), ("", "", None), ("y.com", "", None)]
    assert got[0].verdict == "block" and got[6].verdict == "block"
    table = spark.createDataFrame(list(queries.RULES), "rule string, verdict string")
    again = {r.page_id: r for r in urls.judge_urls(pages, "page_id", "url", table, model).collect()}
    assert again == got
    assert urls.judge_urls(pages.limit(0), "page_id", "url", queries.RULES, model).count() == 0


def test_languages(spark, odd, none):
    got = queries.op2_language_id(spark, "/root/testdata/sf0.01").join(spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert np.mean([r.lang_pred == r.lang for r in got]) > 0.98 and all(0 <= r.score <= 1 for r in got)
    assert np.mean([r.rejected for r in got]) < 0.01  # a text that changes its language half-way, and one of secrets
    model = langid.train(spark.read.parquet(f"{SF}/documents.parquet"))
    out = {r.doc_id: r for r in langid.identify(odd, model).collect()}
    assert out[1].lang_pred == out[2].lang_pred == "und" and out[1].rejected and out[4].lang_pred in model.langs
    assert langid.identify(none, model).count() == 0 and langid.identify(odd, langid.train(none)).where("lang_pred <> 'und'").count() == 0


def test_kneser_ney_sums_to_one():
    counts = {"a": Counter("".join(x) for x in zip(*(("abcabdab" * 3)[i:] for i in range(langid.ORDER)), strict=False))}
    model = langid.kneser_ney(counts)
    letters = sorted({g[-1] for g in counts["a"]})
    logp = lambda t: model.sums(*langid.normal([t]))[0][0, 0]  # noqa: E731  a text stands behind its gaps
    total = sum(np.exp(logp("abc" + x) - logp("abc")) for x in letters)
    assert 0.9 < total <= 1.0001


def test_best_fit_decreasing():
    rnd = random.Random(1)
    sizes = [rnd.randint(1, 60) for _ in range(300)]
    got, bins = binpack.best_fit_decreasing(sizes, 100)
    room = [100] * bins
    want_room: list[int] = []
    for i in sorted(range(300), key=lambda i: (-sizes[i], i)):
        fits = [(r, b) for b, r in enumerate(want_room) if r >= sizes[i]]
        b = min(fits)[1] if fits else len(want_room)
        if not fits:
            want_room.append(100)
        want_room[b] -= sizes[i]
        assert got[i] == b
        room[b] -= sizes[i]
    assert min(room) >= 0 and bins == len(want_room)


def test_shards(spark, odd, none):
    got = queries.op3_sharding(spark, SF).collect()
    load = Counter()
    for r in got:
        load[r.shard] += r["size"]
    assert set(load) == set(range(8)) and max(load.values()) < 1.02 * min(load.values())
    for k in range(8):
        assert sorted(r.slot for r in got if r.shard == k) == list(range(sum(r.shard == k for r in got)))
    groups = {}
    for r in sharding.shard_groups(odd, "doc_id", "text", capacity=1000).collect():
        groups.setdefault(r.group_key, set()).add(r.shard)
    assert all(len(x) == 1 for x in groups.values()) and sharding.shard_groups(none, "doc_id", "text", shards=8).count() == 0


def test_nearest(spark):
    rnd = np.random.default_rng(2)
    vecs = [(i, [float(x) for x in rnd.normal(size=8)]) for i in range(120)] + [(200, None), (201, [0.0] * 8), (202, [float("nan")] * 8), (203, []), (204, None)]
    vecs += [(140, vecs[3][1]), (141, vecs[3][1]), (160, [None, *vecs[3][1][1:]])]
    df = spark.createDataFrame(vecs, "vec_id long, embedding array<double>")
    got = vectors.nearest(df, "vec_id", "embedding", F.col("vec_id") % 20 == 0, k=5, block=32).collect()
    good = {i: np.array(v) for i, v in vecs if v and None not in v and np.isfinite(v).all() and any(v)}
    for q in (i for i in good if i % 20 == 0):
        want = sorted(((-sum(a * b for a, b in zip(good[q], v, strict=True)), i) for i, v in good.items() if i != q))[:5]
        assert [r.vec_id for r in sorted(got, key=lambda r: r["rank"]) if r.query_id == q] == [i for _, i in want]
    assert vectors.nearest(df.limit(0), "vec_id", "embedding", F.lit(True)).count() == 0


def test_word_pieces(odd, none):
    from tokenizers import Tokenizer, models

    rnd, letters = random.Random(3), "abc"
    vocab = {"a", "b", "ab", "abc", "ca"} | {"##" + x for x in ("a", "b", "bc", "cab", "abca")}
    auto = wordpiece.Automaton([v for v in vocab if v[0] != "#"], [v[2:] for v in vocab if v[0] == "#"])
    slow = Tokenizer(models.WordPiece({v: i for i, v in enumerate([*sorted(vocab), "[UNK]"])}, unk_token="[UNK]"))
    for _ in range(3000):
        w = "".join(rnd.choice(letters) for _ in range(rnd.randint(1, 9)))
        want = slow.encode(w).tokens
        assert auto.count(w) == (0 if want == ["[UNK]"] else len(want)), w
    import public_tokenizers

    got = {r.doc_id: r for r in wordpiece.count_tokens(odd, "doc_id", "text", public_tokenizers.path("piece_bpe_32k.model")).collect()}
    assert got[1].n_tokens == got[2].n_words == 0 and got[3].n_words == 2 and got[5].n_words == 5000


def test_exact_copies(odd, none):
    for weak in (None, lambda t: F.unhex(F.lpad(F.hex(F.length(t) % 2), 2, "0"))):
        got = {(r.doc_id, r.keep_id, r.group_size, r.kept) for r in exact_dedup.mark_duplicates(odd, keep="max", content_hash=weak).collect()}
        assert got == {(1, 2, 2, False), (2, 2, 2, True), (3, 4, 3, False), (4, 4, 3, True), (5, 5, 1, True)}
    r = exact_dedup.mark_duplicates(odd).where("doc_id = 4").first()
    assert r.text_sha256 == hashlib.sha256(b"ab c").hexdigest() and r.keep_id == 3
    kept = exact_dedup.drop_duplicates(odd, keep="min")
    assert sorted(r.doc_id for r in kept.collect()) == [1, 3, 5] and kept.columns == odd.columns
    assert exact_dedup.mark_duplicates(none).count() == 0


def test_licenses(spark, none):
    texts = ["The MIT License. See mit  license", "Released under an MIT License.", None, "", "x " * 90 + "Licensed under CC BY-NC 4.0." + " y" * 90, "general public\nLICENSE apache license"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = [tuple(r)[1:8] for r in licenses.scan(df, "doc_id", "text", queries.PHRASES).orderBy("doc_id").collect()]
    assert got[0][:6] == (6, 2, 1, 4, "mit", "mit") and got[1][5] == "mit" and got[2] == got[3] == (0, 0, None, None, "", "", 0.0)
    assert got[4][5] == "cc-by-nc" and got[4][1] == 0 and got[5][:6] == (5, 2, 0, 3, "apache,gpl", "apache,gpl")
    assert licenses.scan(none, "doc_id", "text", queries.PHRASES).count() == 0


def test_license_join_finds_every_block():
    rnd, words = random.Random(4), [f"w{i}" for i in range(12)]
    temps = [(str(k), " ".join(rnd.choices(words, k=rnd.randint(2, 8)))) for k in range(15)]
    known = licenses.Templates(temps, {w.encode(): rnd.randint(0, 9) for w in words}, 0.7)
    for _ in range(500):
        block = [w.encode() for w in rnd.choices([*words, "z"], k=rnd.randint(0, 9))]
        want = {k for k, (_, t) in enumerate(temps) if len(set(t.encode().split()) & set(block)) >= 0.7 * len(set(t.split())) - 1e-9}
        assert set(known.match(block)) == want


def test_wrapped_notices_are_found(spark):
    rnd = random.Random(6)
    filler, texts, want = ["zig", "zag", "the", "of", "license", "software"], [], []
    share = lambda words, t: len(set(words) & set(t)) / len(set(t))
    temps = [(label, licenses.clean(t).split()) for label, t in licenses.TEMPLATES]
    for _ in range(150):
        words = [rnd.choice(filler) for _ in range(rnd.randint(0, 150))]
        for _, notice in rnd.sample(licenses.TEMPLATES, 2):
            at = rnd.randrange(len(words) + 1)
            words[at:at] = [w for w in notice.split() if rnd.random() < 0.85]
        texts.append("".join(w + rnd.choice(" \n") for w in words))
        words = licenses.clean(texts[-1]).split()
        stretches = [words[i : i + 64] for i in range(max(1, len(words) - 63))]
        shares = sorted((max(share(x, t) for x in stretches), label) for label, t in temps)
        want.append({label: s for s, label in shares if s >= 0.8 - 1e-9})
    texts.append("x\nThis work is licensed under a Creative Commons\nAttribution 4.0 International License.")
    want.append({"cc-by": 1.0})
    got = licenses.scan(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), "doc_id", "text", ()).orderBy("doc_id").collect()
    for r, labels in zip(got, want, strict=True):
        best = {}
        for m in r.matches:
            best[m.label] = max(best.get(m.label, 0), m.share)
        assert best == pytest.approx(labels) and r.labels == ",".join(sorted(labels)) and r.score == pytest.approx(max(labels.values(), default=0))
    assert [m.line for m in got[-1].matches] == [1]


def test_mix(spark, odd, none):
    got = queries.op8_source_mix(spark, SF).collect()
    total = sum(r["size"] for r in got)
    targets = {}
    for r in got:
        assert 0 <= r.taken <= 3 * r["size"]
        targets[r.source_size, r.target] = 0
    assert abs(sum(r.taken for r in got) - total) < 30
    rows = mixing.mixed_rows(odd.dropDuplicates(["doc_id"]), "doc_id", "text", "source", (1.0,))
    assert rows.columns == odd.columns and sum(len((r.text or "").split()) for r in rows.collect()) == 5004
    assert mixing.mix(none, "doc_id", "source", mixing.n_words(F.col("text")), (1.0,)).count() == 0


def test_mixed_rows_leave_texts_in_place(spark):
    """However large the table: what the last pass takes of a row is known by its source's end."""
    rows = [(k % 7 if k % 3 else None, " ".join(f"w{i}" for i in range(k % 5 + 2)), "xyz"[k % 3]) for k in range(120)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(4)
    plan = mixing.mix(df, "doc_id", "source", mixing.n_words(F.col("text")), (5.0, 2.0, 1.0))
    want = {r.source: r.n for r in plan.groupBy("source").agg(F.sum("taken").alias("n")).collect()}
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        unique = df.withColumn("doc_id", F.monotonically_increasing_id())
        steps = mixing.mixed_rows(unique, "doc_id", "text", "source", (5.0, 2.0, 1.0))._jdf.queryExecution().executedPlan().toString()
        got = mixing.mixed_rows(df, "doc_id", "text", "source", (5.0, 2.0, 1.0))
        assert "SortMergeJoin" not in steps
        assert {r.source: r.n for r in got.groupBy("source").agg(F.sum(mixing.n_words(F.col("text"))).alias("n")).collect()} == want
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_whole_texts_go_to_the_tokenizer(monkeypatch):
    enc, calls = packing.Encoder(*queries.tokenizer_files()), []
    monkeypatch.setattr(enc, "fast", type("Fast", (), {"encode_ordinary": lambda self, text: calls.append(text) or [7]})())
    assert enc.ids("several rare words") == b"\7\0\0\0" and calls == ["several rare words"]


def test_packing_round_trip(spark, odd, none):
    from tokenizers import Tokenizer

    files, docs = queries.tokenizer_files(), spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text").limit(60)
    extra = spark.createDataFrame([(9001, None), (9002, ""), (9003, " a  b\n\n c\t<|endoftext|> d "), (9004, "don't stop  ")], "doc_id long, text string")
    docs = docs.union(extra)
    got, slow, bins = packing.pack(docs, "doc_id", "text", files).collect(), Tokenizer.from_file(files[0]), {}
    for d in docs.collect():
        ids = [*(slow.encode(d.text, add_special_tokens=False).ids if d.text else []), 1]
        at = 0
        for r in sorted((r for r in got if r.doc_id == d.doc_id), key=lambda r: r.start):
            assert r.start == at and r.doc_tokens == len(ids)
            assert r.ids_crc32 == zlib.crc32(np.array(ids[at : at + r.length], "<u4").tobytes())
            at += r.length
        assert at == len(ids)
    for r in got:
        bins.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for b in bins.values():
        at = 0
        for o, n in sorted(b):
            assert o == at
            at += n
        assert at <= 2048
    assert packing.pack(none, "doc_id", "text", files).count() == 0


@pytest.mark.parametrize("broadcast", [1_000_000, 0])
def test_join_against_brute_force(spark, none, monkeypatch, broadcast):
    """By broadcast joins and by shuffled ones; with limits so small that hubs and pairs of frequent tokens are needed."""
    monkeypatch.setattr(prefix_index, "FREQUENT", 3)
    monkeypatch.setattr(ngram_join, "BIG", 6)
    monkeypatch.setattr(common, "BROADCAST_ROWS", broadcast)
    rnd = random.Random(5)
    base = [" ".join(rnd.choice("abcdefghijklmnop") for _ in range(rnd.choice([3, 6, 12, 30, 90]))) for _ in range(20)]
    passage, docs = " ".join(rnd.choice("qrstuvw") for _ in range(30)), []
    for i in range(250):
        w = rnd.choice(base).split()
        for _ in range(rnd.choice([0, 1, 2, 4])):
            k = rnd.randrange(len(w) + 1)
            w[k : k + rnd.choice([0, 1])] = [rnd.choice("xyz")] * rnd.choice([0, 1])
        docs.append((i, " ".join(w) + (" " + passage if rnd.random() < 0.3 else "")))
    docs += [(400, None), (401, ""), (402, "a"), (403, "A"), (403, "A")]
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in ngram_join.near_duplicates(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    sets = [(i, set(shingles.token_set(t, 5, shingles.Memo()).tolist())) for i, t in docs]
    up = {i: i for i, _ in docs}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for (i, a), (j, b) in itertools.combinations(sets, 2):
        if a and b and 100 * len(a & b) >= 80 * len(a | b) and root(i) != root(j):
            up[max(root(i), root(j))] = min(root(i), root(j))
    assert got == {i: (len(s), root(i)) for i, s in sets}
    assert ngram_join.near_duplicates(none).count() == 0


def test_entries_of_large_groups_are_labelled_once_a_round(spark, monkeypatch):
    monkeypatch.setattr(ngram_join, "BIG", 6)
    rnd, made, wanted = random.Random(3), spark.sparkContext.accumulator(0), []
    label = ngram_join._Links.label

    def counted(self, entries):
        out = label(self, entries)
        if self.comps is None:
            return out
        wanted.append(entries.count())
        made_ = made

        def seen(batches):
            for b in batches:
                made_.add(b.num_rows)
                yield b

        return out.mapInArrow(seen, out.schema)

    monkeypatch.setattr(ngram_join._Links, "label", counted)
    passage = [f"p{i}" for i in range(80)]
    docs = [(i, " ".join([*passage, *(rnd.choice("abcdefgh") * 3 for _ in range(rnd.choice([2, 4, 20])))])) for i in range(80)]
    assert ngram_join.near_duplicates(spark.createDataFrame(docs, "doc_id long, text string")).count() == 80
    assert wanted and made.value == sum(wanted)


def test_join_of_null_and_shared_ids(spark):
    t, u, v = (" ".join(f"{x}{i}" for i in range(60)) for x in "tuv")
    near = lambda text, k: f"{text} more{k}"  # noqa: E731  linked with the text
    docs = [(None, t), (5, t), (9, t), (None, near(u, 1)), (7, near(u, 2)), (8, near(u, 3)), (7, "a text of its own"), (1, v), (1, near(v, 1)), (1, v), (None, "x y"), (None, "x y"), (None, None), (None, "")]
    df = spark.createDataFrame([(i, x, k) for k, (i, x) in enumerate(docs)], "doc_id long, text string, k int")
    got = Counter((r.doc_id, r.n_shingles, r.component_id) for r in ngram_join.near_duplicates(df).collect())
    assert got == Counter([(None, 56, 5), (5, 56, 5), (9, 56, 5), (None, 57, 7), (7, 57, 7), (8, 57, 7), (7, 1, 7), (1, 56, 1), (1, 57, 1), (1, 56, 1), (None, 1, None), (None, 1, None), (None, 0, None), (None, 0, None)])
    kept = ngram_join.keep_one(df)
    assert kept.columns == df.columns
    left = [r.k for r in kept.collect()]
    assert len(left) == 7 and {1, 4, 6, 12, 13} <= set(left) and len({7, 8, 9} & set(left)) == 1 == len({10, 11} & set(left))


def test_pipeline(spark):
    import corpus_pipeline

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    text = {r.doc_id: r.text for r in docs.collect()}
    got = corpus_pipeline.run(spark, SF).collect()
    kept = {r.doc_id for r in got}
    lowered = [exact for exact in (text[i].encode().translate(shingles.LOWER) for i in kept)]
    assert kept and len(set(lowered)) == len(lowered)
