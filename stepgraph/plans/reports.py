"""Reports over graphs: degrees, flows, gaps, shared passages, targeted paths, spread, and how costs grow."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..baselines import sequential as seq
from ..cost import Ledger, more_work, time_processor_product
from ..engine import Rounds
from ..model import Graph
from ..operators import components, flood, rank, subgraph, trees
from ..sources import generators
from ..sources.fixtures import duck, graph
from ..streaming import edges as streams
from . import oracles

ALL: dict[str, tuple] = {}
THIN, FOREST = duck("supply_thin"), duck("supply_forest")
GRAM = 8


def add(name: str, sql: str | None = None):
    def put(f):
        ALL[name] = (f, sql)
        return f

    return put


def table(s: SparkSession, d: str, name: str) -> DataFrame:
    return s.read.parquet(f"{d}/{name}.parquet")


def first_id(g: Graph) -> DataFrame:
    return g.vertices.agg(F.min("id").alias("id"))


# Degrees and flows ---------------------------------------------------------------------------------------------------
@add("degree_stats", f"with {oracles.sym('supply_thin')}, x as (select src as id, count(*) as k from e group by src) select count(*) as n, min(k) as low, max(k) as high, round(avg(k), 9) as mean, round(stddev_pop(k), 9) as spread, min(id) filter (where k = (select max(k) from x)) as hub from x")
def degree_stats(s, d):
    g = graph(s, d, "supply_thin").symmetrized().degrees()
    k = F.col("degree")
    hub = F.min_by("id", F.struct(-k, F.col("id")))
    return g.agg(F.count("*").alias("n"), F.min(k).alias("low"), F.max(k).alias("high"), F.round(F.avg(k), 9).alias("mean"), F.round(F.stddev_pop(k), 9).alias("spread"), hub.alias("hub"))


def gini(value: pd.Series, times: pd.Series) -> float:
    """Gini coefficient of values that occur so many times each."""
    x = pd.DataFrame({"v": value, "c": times}).sort_values("v")
    before = x.c.cumsum() - x.c
    n, total = x.c.sum(), (x.v * x.c).sum()
    placed = (x.v * (x.c * before + x.c * (x.c + 1) / 2)).sum()
    return float(2 * placed / (n * total) - (n + 1) / n)


@add("udaf_gini_degree", f"with x as (select 'src' as side, src as id, count(*) as k from ({THIN}) as a group by src union all select 'dst', dst, count(*) from ({THIN}) as b group by dst), r as (select *, row_number() over (partition by side order by k, id) as i from x) select side, round(2.0 * sum(i * k) / (count(*) * sum(k)) - (count(*) + 1.0) / count(*), 9)::double as gini from r group by side")
def gini_degree(s, d):
    """Inequality of degrees by side. The histogram is made first, so a group has as many rows as there are distinct degrees."""
    e = graph(s, d, "supply_thin").edges
    ends = e.select(F.lit("src").alias("side"), F.col("src").alias("id")).union(e.select(F.lit("dst"), F.col("dst")))
    hist = ends.groupBy("side", "id").agg(F.count("*").alias("k")).groupBy("side", "k").agg(F.count("*").alias("c"))
    return hist.groupBy("side").agg(F.round(F.pandas_udf(gini, "double")("k", "c"), 9).alias("gini"))


FLOWS = "select c.n_regionkey as buyer, s.n_regionkey as seller, count(*) as n, sum(l_quantity)::double as quantity from {lineitem} join {orders} on l_orderkey = o_orderkey join {customer} on o_custkey = c_custkey join {supplier} on l_suppkey = s_suppkey join {nation} c on c.n_nationkey = c_nationkey join {nation} s on s.n_nationkey = s_nationkey group by grouping sets ((c.n_regionkey, s.n_regionkey), (c.n_regionkey), ())"
NAMES = ("lineitem", "orders", "customer", "supplier", "nation")


@add("grouping_sets_trade", FLOWS.format_map({t: t for t in NAMES}))
def trade_flows(s, d):
    return s.sql(FLOWS, **{t: table(s, d, t) for t in NAMES})


KINDS = ("click", "error", "view")


@add("pivot_events", "select user_id, " + ", ".join(f"nullif(count(*) filter (where event_type = '{k}'), 0) as {k}" for k in KINDS) + " from events group by user_id")
def pivot_events(s, d):
    """Events of each user by kind. The kinds are given, so no job is needed to find them."""
    return table(s, d, "events").groupBy("user_id").pivot("event_type", list(KINDS)).agg(F.count("event_id"))


# Windows, order and functions ----------------------------------------------------------------------------------------
@add("hop_gap", "select user_id, count(gap) as hops, max(gap) as longest from (select user_id, date_diff('second', lag(ts) over (partition by user_id order by ts, event_id), ts) as gap from (select user_id, event_id, date_trunc('second', ts) as ts from events) as q) as g group by user_id")
def hop_gap(s, d):
    """Seconds between successive events of a user."""
    w = Window.partitionBy("user_id").orderBy("at", "event_id")
    x = table(s, d, "events").select("user_id", "event_id", F.unix_timestamp(F.date_trunc("second", "ts")).alias("at"))
    x = x.select("user_id", (F.col("at") - F.lag("at").over(w)).alias("gap"))
    return x.groupBy("user_id").agg(F.count("gap").alias("hops"), F.max("gap").alias("longest"))


@add("top_rank", f"select * from ({oracles.pagerank('page_link', 10, True)}) as r order by rank desc, id limit 10")
def top_rank(s, d):
    r = rank.pagerank(graph(s, d, "page_link", True), iters=10).select("id", F.round("rank", 10).alias("rank"))
    return r.orderBy(F.desc("rank"), "id").limit(10)


@add("fn_math", f"select src, dst, round(log2(w), 9) as bits, greatest(src, dst) as high, least(src, dst) as low, (dst % 7)::bigint as slot from ({THIN}) as g")
def fn_math(s, d):
    return graph(s, d, "supply_thin").edges.select("src", "dst", F.round(F.log2("w"), 9).alias("bits"), F.greatest("src", "dst").alias("high"), F.least("src", "dst").alias("low"), F.pmod("dst", F.lit(7)).alias("slot"))


# Documents as graphs -------------------------------------------------------------------------------------------------
@add("component_quality", f"with c as ({oracles.components('doc_overlap')}) select component, count(*) as labelled, sum(quality)::bigint as good, sum(toxic)::bigint as toxic from c join labels on doc_id = id group by component")
def component_quality(s, d):
    """Labels of documents by the component that shared lines put them in."""
    c = components.hook_shortcut(graph(s, d, "doc_overlap"))
    x = c.join(table(s, d, "labels"), F.col("id") == F.col("doc_id"))
    return x.groupBy("component").agg(F.count("*").alias("labelled"), F.sum("quality").cast("long").alias("good"), F.sum("toxic").cast("long").alias("toxic"))


def _grams(df: DataFrame, key: str) -> DataFrame:
    words = F.transform(F.regexp_extract_all("text", F.lit("([A-Za-z]+)"), F.lit(1)), F.lower)
    x = df.select(F.col(key).alias("_key"), words.alias("w")).where(F.size("w") >= GRAM)
    at = F.explode(F.sequence(F.lit(1), F.size("w") - GRAM + 1))
    return x.select("_key", "w", at.alias("at")).select(F.col("_key").alias(key), F.array_join(F.slice("w", F.col("at"), GRAM), " ").alias("gram"))


DUCK_GRAMS = "select distinct {key}, gram from (select {key}, unnest(list_transform(range(1, len(w) - 6), lambda i: array_to_string(w[i:i + 7], ' '))) as gram from (select {key}, list_transform(regexp_extract_all(text, '[A-Za-z]+'), lambda x: lower(x)) as w from {table}) as q) as g"


@add("doc_benchmark_edges", f"with a as ({DUCK_GRAMS.format(key='doc_id', table='documents')}), b as ({DUCK_GRAMS.format(key='item_id', table='benchmark')}) select doc_id as src, item_id + 1000000000 as dst, count(*) as shared from a join b using (gram) group by 1, 2")
def doc_benchmark_edges(s, d):
    """Documents and benchmark items that share runs of eight words. Only runs that an item has are shuffled on."""
    asked = _grams(table(s, d, "benchmark"), "item_id").distinct()
    hits = _grams(table(s, d, "documents"), "doc_id").join(asked, "gram").distinct()
    return hits.groupBy(F.col("doc_id").alias("src"), (F.col("item_id") + 1000000000).alias("dst")).agg(F.count("*").alias("shared"))


# Streams -------------------------------------------------------------------------------------------------------------
@add("stream_degree_sliding", "with w as (select user_id, date_trunc('day', ts)::timestamp - interval (k) day as start from events, range(0, 2) as r(k)) select user_id, start, count(*) as n from w where start + interval 2 day <= (select max(ts) - interval 1 hour from events) group by 1, 2")
def sliding(s, d):
    """Events of each user in windows of two days that start daily; windows that the watermark has not closed stay out."""
    x = streams.events(s, d).withWatermark("ts", "1 hour").groupBy(F.window("ts", "2 days", "1 day").alias("w"), "user_id").agg(F.count("*").alias("n"))
    return streams.drained(x.select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), "n"), Rounds(s))


# Paths ---------------------------------------------------------------------------------------------------------------
@add("sssp_target_supply_thin", f"select * from ({oracles.sssp('supply_thin')}) as p where id = (select max(dst) from ({THIN}) as g)")
def sssp_target(s, d):
    """The distance of the largest id from the smallest; the flood ends once nothing on its way is nearer."""
    g = graph(s, d, "supply_thin")
    there = g.vertices.agg(F.max("id")).first()[0]
    got = flood.shortest_paths(g, first_id(g), target=there)
    return got.where(F.col("id") == there).select("id", F.round("dist", 6).alias("dist"))


@add("sssp_within_supply_thin", f"select * from ({oracles.sssp('supply_thin')}) as p where dist <= 300000")
def sssp_within(s, d):
    g = graph(s, d, "supply_thin")
    return flood.shortest_paths(g, first_id(g), max_dist=300000.0).select("id", F.round("dist", 6).alias("dist"))


@add("reachable_supply_thin", f"with c as ({oracles.components('supply_thin')}) select (select component from c order by id limit 1) = (select component from c order by id desc limit 1) as yes")
def reachable(s, d):
    g = graph(s, d, "supply_thin")
    low, high = g.vertices.agg(F.min("id"), F.max("id")).first()
    return s.createDataFrame([(flood.reachable(g, low, high),)], "yes boolean")


# Spread and communities ----------------------------------------------------------------------------------------------
@add("influence_certain_supply_forest", f"with c as ({oracles.components('supply_forest')}) select seed, row_number() over (order by n desc, seed) as place from (select min(id) as seed, count(*) as n from c group by component order by n desc, seed limit 5) as t")
def influence(s, d):
    """Five seeds where every edge is live: then the largest components' smallest ids are best."""
    seeds = subgraph.influence_greedy(graph(s, d, "supply_forest"), 5, chance=1.0, samples=1)
    return s.createDataFrame([(x, k + 1) for k, x in enumerate(seeds)], "seed long, place long")


@add("modularity_supply_thin", f"with g as ({THIN}), x as (select src % 4 as a, dst % 4 as b from g), m as (select count(*)::double as m from x), k as (select part, count(*) as k from (select a as part from x union all select b from x) as u group by part), i as (select a as part, count(*) as e from x where a = b group by a) select round(sum(coalesce(e, 0) / m - (k / (2 * m)) ** 2), 9) as modularity from k left join i using (part) cross join m")
def modularity(s, d):
    g = graph(s, d, "supply_thin")
    parts = g.vertices.select("id", F.pmod("id", F.lit(4)).alias("community"))
    return subgraph.modularity(g, parts).select(F.round("modularity", 9).alias("modularity"))


# Growth of costs -----------------------------------------------------------------------------------------------------
def growth_points(s: SparkSession) -> DataFrame:
    """(algo, n, product, sequential) on paths: the method's time-processor product and its counterpart's operations."""
    rows = []
    for algo, sizes, run, base in (
        ("flood", (4, 8, 16), flood.min_label, seq.components),
        ("tour", (64, 256, 1024), trees.euler_tour, seq.tree_orders),
    ):
        for n in sizes:
            g, led = generators.path(s, n), Ledger(algo)
            run(g, ledger=led)
            ops = seq.run(g, base).agg(F.max("ops")).first()[0]
            rows.append((algo, n, float(time_processor_product(led.table(s)).first().product), float(ops)))
    return s.createDataFrame(rows, "algo string, n long, product double, sequential double")


@add("more_work_verdicts", "select * from (values ('flood', true), ('tour', false)) as t(algo, more_work)")
def verdicts(s, d):
    """Whether a method's product grows faster than its sequential counterpart's operations do, on paths. The SQL has the two
    verdicts that the reference states."""
    return more_work(growth_points(s)).select("algo", "more_work")
