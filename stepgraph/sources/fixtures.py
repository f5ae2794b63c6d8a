"""Graphs derived from the given tables. One SQL text serves Spark and, as an oracle's input, DuckDB."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import Graph
from ..operators.neighbours import knn_edges

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")

SUPPLY = "select l_suppkey as src, l_partkey + 1000000 as dst, min(l_extendedprice) as w from {lineitem} {where} group by l_suppkey, l_partkey"
HOP = "select distinct src, dst from (select user_id as src, lead(user_id) over (partition by props order by ts, event_id) as dst from {{events}} where {where}) as h where dst is not null and src <> dst"
CHAIN = "select src, dst from (select event_id as src, lead(event_id) over (partition by user_id order by ts, event_id) as dst from {events}) as c where dst is not null"
LINKS = "select distinct page_id, href from (select page_id, {explode}(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) as href from {pages}) as l"
KEYED = " union all ".join((
    "select cast(0 as bigint) as src, cast(r_regionkey + 1 as bigint) as dst from {region}",
    "select cast(n_regionkey + 1 as bigint), cast(n_nationkey + 10 as bigint) from {nation}",
    "select cast(s_nationkey + 10 as bigint), s_suppkey + 100 from {supplier}",
    "select cast(c_nationkey + 10 as bigint), c_custkey + 1000000 from {customer}",
))
SQL = {
    "supply": SUPPLY.replace("{where}", ""),
    "supply_thin": SUPPLY.replace("{where}", "where l_returnflag = 'R' and l_quantity >= 48"),
    "supply_forest": SUPPLY.replace("{where}", "where l_returnflag = 'R' and l_quantity >= 50"),
    "basket_thin": "select distinct l_orderkey as src, l_partkey + 100000000 as dst from {lineitem} where l_quantity >= 46",
    "event_chain": CHAIN,
    "user_hop": HOP.format(where="event_type = 'error'"),
    "hop_sparse": HOP.format(where="event_type = 'click' and value > 110"),
    "page_link": f"with l as ({LINKS}), p as (select href, 1000000 + cast(row_number() over (order by href) as bigint) as pid from (select distinct href from l) as d) select l.page_id as src, p.pid as dst from l join p on l.href = p.href",
    "page_host": "with h as (select page_id, split_part(url, '/', 3) as host from {pages}), d as (select host, 1000000 + cast(row_number() over (order by host) as bigint) as hid from (select distinct host from h) as x) select h.page_id as src, d.hid as dst from h join d on h.host = d.host",
    "geo_tree": KEYED,
    "order_stars": "select o_custkey as src, o_orderkey + 10000000000 as dst from {orders}",
    "trade": "select least(a, b) as src, greatest(a, b) as dst, cast(count(*) as double) as w from (select cast(c_nationkey as bigint) as a, cast(s_nationkey as bigint) as b from {orders} join {customer} on o_custkey = c_custkey join {lineitem} on l_orderkey = o_orderkey join {supplier} on l_suppkey = s_suppkey) as t where a <> b group by 1, 2",
    "doc_overlap": "with l as (select distinct doc_id, line from (select doc_id, {explode}({lines}) as line from {documents}) as x where length(line) >= 30), k as (select line, 1000000000 + cast(row_number() over (order by md5(line)) as bigint) as lid from l group by line having count(*) > 1) select l.doc_id as src, k.lid as dst from l join k on l.line = k.line",
    "turns": "select src, dst from (select conv_id * 1000 + turn as src, lead(conv_id * 1000 + turn) over (partition by conv_id order by turn) as dst from {conversations}) as t where dst is not null",
    "turn_labels": "select conv_id * 1000 + turn as id, role as label from {conversations}",
    "entity_chain": "select distinct o_custkey + 10000000000 as src, o_orderkey + 20000000000 as dst from {orders} join {lineitem} on l_orderkey = o_orderkey where l_quantity >= 46 union select distinct l_orderkey + 20000000000, l_partkey + 30000000000 from {lineitem} where l_quantity >= 46",
    # for DuckDB; Spark has knn_edges for it
    "embed_knn": "select src, dst, min(w) as w from (select least(q, c) as src, greatest(q, c) as dst, round(1 - cosine, 9) as w from (select q, c, cosine, row_number() over (partition by q order by cosine desc, c) as nth from (select a.vec_id as q, b.vec_id as c, round(list_cosine_similarity(a.embedding::double[], b.embedding::double[]), 9) as cosine from {embeddings} as a join {embeddings} as b on a.vec_id <> b.vec_id) as p) as r where nth <= 5) as n group by src, dst",
    "entity_labels": "select c_custkey + 10000000000 as id, c_mktsegment as label from {customer} union all select o_orderkey + 20000000000, o_orderpriority from {orders} union all select p_partkey + 30000000000, p_type from {part}",
}


class _Names(dict):
    def __missing__(self, key: str) -> str:
        return key


def duck(name: str) -> str:
    """The graph's SQL for DuckDB."""
    return SQL[name].format_map(_Names(explode="unnest", lines="string_split(text, chr(10))"))


def frame(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    if name == "embed_knn":
        return knn_edges(spark.read.parquet(f"{sf_dir}/embeddings.parquet").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec")))
    text = SQL[name].replace("{explode}", "explode").replace("{lines}", "split(text, '\\n')")
    return spark.sql(text, **{t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in TABLES if "{" + t + "}" in text})


def graph(spark: SparkSession, sf_dir: str, name: str, directed: bool = False) -> Graph:
    return Graph.from_edges(frame(spark, sf_dir, name), directed)


def labelled(spark: SparkSession, sf_dir: str, edges: str, labels: str) -> Graph:
    return Graph(frame(spark, sf_dir, labels), frame(spark, sf_dir, edges), True)
