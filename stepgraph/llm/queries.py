"""The ten operators as queries over the given tables, and the SQL that says the same where SQL can."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import exact_dedup, langid, licenses, mixing, ngram_join, packing, sharding, urls, vectors, wordpiece
from .common import documents

RULES = (("org/", "allow"), ("example.org/es/", "block"), ("example.org/en/1", "block"), ("com/fr/", "allow"), ("com/de/", "block"))
PHRASES = (("mit license", "mit"), ("apache license", "apache"), ("general public license", "gpl"))
WEIGHTS, EPOCHS, SEED, CAPACITY = (5.0, 2.0, 1.0), 3, 7, 2048


def tokenizer_files() -> tuple[str, str, str]:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN


def op1_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    return urls.judge_urls(pages, "page_id", "url", RULES, urls.train(urls.labelled_table(spark)))


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    out = langid.held_out(F.col("doc_id"))
    model = langid.train(docs.where(~out))
    return langid.identify(docs.select("doc_id", "text", out.alias("held_out")), model).drop("text")


def op3_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    put = sharding.shard_groups(documents(spark, sf_dir), "doc_id", "text", shards=8)
    return put.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def op4_nearest_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    vecs = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    return vectors.nearest(vecs, "vec_id", "embedding", F.col("vec_id") % 20 == 0, k=20)


def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return wordpiece.count_tokens(documents(spark, sf_dir), "doc_id", "text", public_tokenizers.path("piece_bpe_32k.model"))


def op6_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.mark_duplicates(documents(spark, sf_dir), keep="max")


def op7_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan(documents(spark, sf_dir), "doc_id", "text", PHRASES).drop("matches")


def op8_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = mixing.mix(documents(spark, sf_dir), "doc_id", "source", mixing.n_words(F.col("text")), WEIGHTS, EPOCHS, SEED)
    return got.select("doc_id", "size", "source_size", "target", "taken")


def op9_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(documents(spark, sf_dir), "doc_id", "text", tokenizer_files(), end_id=1, capacity=CAPACITY)


def op10_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.near_duplicates(documents(spark, sf_dir))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_url_filter, op2_language_id, op3_sharding, op4_nearest_vectors, op5_token_counts, op6_exact_dedup, op7_license_scan, op8_source_mix, op9_packing, op10_ngram_join)}


LOWERED = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

NEAREST_SQL = """
with v as (
  select vec_id, list_transform(embedding, lambda x: x::double) as e from embeddings
  where embedding is not null and len(embedding) > 0 and len(list_filter(embedding, lambda x: x is null or isnan(x) or isinf(x))) = 0
    and len(list_filter(embedding, lambda x: x <> 0)) > 0),
pairs as (
  select q.vec_id as query_id, c.vec_id,
    list_reduce(list_transform(range(1, len(q.e) + 1), lambda i: q.e[i] * c.e[i]), lambda a, b: a + b) as score
  from v q join v c on c.vec_id <> q.vec_id and len(c.e) = len(q.e) where q.vec_id % 20 = 0)
select query_id, rank::int as rank, vec_id, score from (
  select *, row_number() over (partition by query_id order by score desc, vec_id) as rank from pairs) where rank <= 20"""

DEDUP_SQL = f"""
with t as (select doc_id, {LOWERED} as n from documents),
g as (select n, max(doc_id) as keep_id, count(*) as group_size from t group by n)
select doc_id, keep_id, group_size, doc_id = keep_id as kept, sha256(t.n) as text_sha256 from t join g on t.n = g.n"""

MIX_SQL = r"""
with d as (
  select doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::bigint as size from documents),
s as (
  select source, sum(size)::bigint as source_size, row_number() over (order by source nulls last) as place from d group by source),
w as (
  select *, case (place - 1) % 3 when 0 then 5.0::double when 1 then 2.0::double else 1.0::double end as weight, source_size::double * 3 as cap from s),
o as (
  select *, coalesce(sum(cap) over before, 0.0) as capped, sum(weight) over () - coalesce(sum(weight) over before, 0.0) as open,
    (sum(source_size) over ())::double as total, row_number() over (order by cap / weight, source nulls last) as nth
  from w window before as (order by cap / weight, source nulls last rows between unbounded preceding and 1 preceding)),
l as (select *, (total - capped) / open as level from o),
f as (select *, (select level from l x where x.level * x.weight <= x.cap order by nth limit 1) as fits from l),
t as (select source, source_size, case when fits is null then cap else least(cap, fits * weight) end as target from f),
x as (
  select doc_id, d.size, source_size, target,
    case when source_size = 0 then 0 else floor(target / source_size) end::bigint as whole,
    coalesce(sum(d.size) over (partition by d.source order by md5('7:' || coalesce(doc_id::varchar, '') || ':' || d.size::varchar), d.size rows between unbounded preceding and 1 preceding), 0)::bigint as ahead
  from d join t on d.source is not distinct from t.source)
select doc_id, size, source_size, target,
  (whole * size + greatest(0, least(size, floor(target + 0.5)::bigint - whole * source_size - ahead)))::bigint as taken from x"""

JOIN_SQL = rf"""
with recursive w as (
  select row_number() over () as r, doc_id, regexp_extract_all({LOWERED}, '[^\x20\x09-\x0D]+') as ws from documents),
g as (
  select r, doc_id, case when len(ws) = 0 then []::varchar[] when len(ws) < 5 then [array_to_string(ws, ' ')]
    else list_distinct(list_transform(range(1, len(ws) - 3), lambda i: array_to_string(ws[i:i + 4], ' '))) end as gs from w),
e as (select r, doc_id, len(gs) as n, unnest(gs) as s from g),
c as (select a.doc_id as x, b.doc_id as y, count(*) as k, any_value(a.n) as nx, any_value(b.n) as ny from e a join e b on a.s = b.s and a.r < b.r group by a.r, b.r, a.doc_id, b.doc_id),
k as (select x, y from c where 100 * k >= 80 * (nx + ny - k)),
u as (select x, y from k union select y, x from k),
reach(x, m) as (select doc_id, doc_id from documents union select reach.x, u.y from reach join u on reach.m = u.x)
select g.doc_id, len(gs)::bigint as n_shingles, m.m as component_id from g join (select x, min(m) as m from reach group by x) m on m.x = g.doc_id"""


def oracle_sql() -> dict[str, str]:
    return {"op4_nearest_vectors": NEAREST_SQL, "op6_exact_dedup": DEDUP_SQL, "op8_source_mix": MIX_SQL, "op10_ngram_join": JOIN_SQL}
