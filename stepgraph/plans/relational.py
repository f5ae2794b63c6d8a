"""Relational operators around graphs: profiles, joins, aggregates, windows, set operations, functions, streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..engine import Rounds
from ..operators.components import hook_shortcut
from ..sources.fixtures import TABLES, duck, frame, graph
from ..streaming import edges as streams
from . import oracles

ALL: dict[str, tuple] = {}


def add(name: str, sql: str | None = None):
    def put(f):
        ALL[name] = (f, sql)
        return f

    return put


def table(s: SparkSession, d: str, name: str) -> DataFrame:
    return s.read.parquet(f"{d}/{name}.parquet")


THIN, HOPS = duck("supply_thin"), duck("user_hop")


@add("scan_all_counts", " union all ".join(f"select '{t}' as name, count(*) as n from {t}" for t in TABLES))
def scan(s, d):
    out = [table(s, d, t).agg(F.count("*").alias("n")).select(F.lit(t).alias("name"), "n") for t in TABLES]
    head = out[0]
    for x in out[1:]:
        head = head.union(x)
    return head


@add("graph_profile", f"with {oracles.sym('supply_thin')}, x as (select src, count(*) as k from e group by src) select count(*) as vertices, (sum(k) / 2)::bigint as edges, max(k) as max_degree from x")
def profile(s, d):
    g = graph(s, d, "supply_thin")
    return g.symmetrized().degrees().agg(F.count("*").alias("vertices"), (F.sum("degree") / 2).cast("long").alias("edges"), F.max("degree").alias("max_degree"))


@add("page_edges", duck("page_link"))
def page_edges(s, d):
    return frame(s, d, "page_link").select("src", F.col("dst").cast("long").alias("dst"))


@add("doc_edges", duck("doc_overlap"))
def doc_edges(s, d):
    return frame(s, d, "doc_overlap").select("src", F.col("dst").cast("long").alias("dst"))


@add("relabel_dense", f"with v as (select src as id from ({THIN}) as a union select dst from ({THIN}) as b) select id, row_number() over (order by id) - 1 as dense from v")
def dense(s, d):
    """Ids to 0..n-1 in order, by range stretches and their sizes: no window over all rows."""
    r = Rounds(s)
    v, _ = r.cut(graph(s, d, "supply_thin").vertices.select("id"))
    cuts = v.approxQuantile("id", [k / 8 for k in range(1, 8)], 0.01)
    part = sum((F.when(F.col("id") > F.lit(int(c)), 1).otherwise(0) for c in cuts), F.lit(0))
    v = v.withColumn("part", part)
    sizes = v.groupBy("part").agg(F.count("*").alias("n"))
    start = sizes.select("part", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("first"))
    nth = F.row_number().over(Window.partitionBy("part").orderBy("id")) - 1
    return v.withColumn("nth", nth).join(F.broadcast(start), "part").select("id", (F.col("first") + F.col("nth")).cast("long").alias("dense"))


@add("subgraph_edges", f"select src, dst from ({THIN}) as g where w between 20000 and 60000 and src is not null")
def subgraph_edges(s, d):
    return graph(s, d, "supply_thin").subgraph(edge=F.col("w").between(20000, 60000) & F.col("src").isNotNull()).edges.select("src", "dst")


@add("degree_join", f"with {oracles.sym('supply_thin')} select s_suppkey as id, s_name as name, count(*) as degree from e join supplier on s_suppkey = e.src group by 1, 2")
def degree_join(s, d):
    return graph(s, d, "supply_thin").degrees().join(table(s, d, "supplier"), F.col("id") == F.col("s_suppkey")).select("id", F.col("s_name").alias("name"), "degree")


@add("common_neighbours", f"with {oracles.sym('user_hop')} select a.dst as x, b.dst as y, count(*) as n from e a join e b on a.src = b.src where a.dst < b.dst group by 1, 2")
def common(s, d):
    a = graph(s, d, "user_hop").symmetrized().arcs().select("src", "dst")
    return a.select("src", F.col("dst").alias("x")).join(a.select("src", F.col("dst").alias("y")), "src").where("x < y").groupBy("x", "y").agg(F.count("*").alias("n"))


@add("isolated_anti", f"select s_suppkey as id from supplier where s_suppkey not in (select src from ({THIN}) as g)")
def isolated(s, d):
    return table(s, d, "supplier").select(F.col("s_suppkey").alias("id")).join(frame(s, d, "supply_thin").select(F.col("src").alias("id")), "id", "left_anti")


@add("semi_hubs", f"select s_suppkey as id from supplier where s_suppkey in (select src from ({THIN}) as g group by src having count(*) > 12)")
def hubs(s, d):
    many = frame(s, d, "supply_thin").groupBy("src").count().where("count > 12")
    return table(s, d, "supplier").select(F.col("s_suppkey").alias("id")).join(many, F.col("id") == F.col("src"), "left_semi")


@add("asof_label", "select e.event_id as id, (select max(f.event_id) from events f where f.user_id = e.user_id and f.event_type = 'click' and (f.ts, f.event_id) < (e.ts, e.event_id) and not exists (select 1 from events h where h.user_id = f.user_id and h.event_type = 'click' and (h.ts, h.event_id) > (f.ts, f.event_id) and (h.ts, h.event_id) < (e.ts, e.event_id))) as click from events e where e.event_type = 'error'")
def asof(s, d):
    """For each error the user's last click before it, by one window instead of a range join."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    e = table(s, d, "events")
    last = F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("click", last).where("event_type = 'error'").select(F.col("event_id").alias("id"), "click")


@add("ancestor_pairs", f"with o as ({oracles.tree_orders('geo_tree')}) select a.id as up, b.id as down from o a join o b on b.pre > a.pre and b.pre < a.pre + a.size where a.depth = 1")
def ancestors(s, d):
    """Interval containment of pre-orders, as an equi-join on the level-one ancestor that a running window carries along."""
    from ..operators.trees import tree_orders

    o = tree_orders(graph(s, d, "geo_tree"))
    w = Window.partitionBy("root").orderBy("pre").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    up = F.last(F.when(F.col("depth") == 1, F.col("id")), ignorenulls=True).over(w)
    return o.withColumn("up", up).where("depth > 1").select("up", F.col("id").alias("down"))


@add("degree_hist", f"with {oracles.sym('supply_thin')}, x as (select src, count(*) as k from e group by src) select k as degree, count(*) as n from x group by k")
def hist(s, d):
    return graph(s, d, "supply_thin").symmetrized().degrees().groupBy("degree").agg(F.count("*").alias("n"))


NATIONS = "select r_name, n_name, count(*) as n from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by {by}"


def nations(s, d):
    c = table(s, d, "customer").join(F.broadcast(table(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))
    return c.join(F.broadcast(table(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))


@add("geo_rollup", NATIONS.format(by="rollup(r_name, n_name)"))
def rollup(s, d):
    return nations(s, d).rollup("r_name", "n_name").agg(F.count("*").alias("n"))


@add("geo_cube", NATIONS.format(by="cube(r_name, n_name)"))
def cube(s, d):
    return nations(s, d).cube("r_name", "n_name").agg(F.count("*").alias("n"))


@add("grouping_sets_segment", "select c_mktsegment as segment, c_nationkey as nation, count(*) as n from customer group by grouping sets ((c_mktsegment), (c_nationkey), ())")
def grouping(s, d):
    return s.sql("select c_mktsegment as segment, c_nationkey as nation, count(*) as n from {customer} group by grouping sets ((c_mktsegment), (c_nationkey), ())", customer=table(s, d, "customer"))


@add("approx_neighbours")
def approx(s, d):
    return graph(s, d, "supply").symmetrized().arcs().groupBy(F.col("src").alias("id")).agg(F.approx_count_distinct("dst").alias("about"))


@add("adjacency_next", f"with {oracles.sym('user_hop')} select src, dst, lead(dst) over (partition by src order by dst) as nxt from e")
def adjacency(s, d):
    a = graph(s, d, "user_hop").symmetrized().arcs().select("src", "dst")
    return a.withColumn("nxt", F.lead("dst").over(Window.partitionBy("src").orderBy("dst")))


@add("topk_neighbours", f"select src, dst, w, k::int as k from (select *, row_number() over (partition by src order by w desc, dst) as k from ({THIN}) as g) as t where k <= 3")
def topk(s, d):
    w = Window.partitionBy("src").orderBy(F.desc("w"), "dst")
    return frame(s, d, "supply_thin").withColumn("k", F.row_number().over(w)).where("k <= 3")


@add("top_components", f"with c as ({oracles.components('supply_forest')}) select component, count(*) as n from c group by component order by n desc, component limit 10")
def top(s, d):
    return hook_shortcut(graph(s, d, "supply_forest")).groupBy("component").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "component").limit(10)


A, B = f"select src, dst from ({THIN}) as a", f"select src, dst from ({duck('supply_forest')}) as b"


def both(s, d):
    return frame(s, d, "supply_thin").select("src", "dst"), frame(s, d, "supply_forest").select("src", "dst")


@add("edge_union", f"{A} union all {B}")
def union(s, d):
    a, b = both(s, d)
    return a.unionByName(b)


@add("edge_intersect", f"{A} intersect {B}")
def intersect(s, d):
    a, b = both(s, d)
    return a.intersect(b)


@add("edge_except", f"{A} except {B}")
def minus(s, d):
    a, b = both(s, d)
    return a.exceptAll(b)


@add("fn_string", "select page_id as id, split_part(url, '/', 3) as host, md5(url) as digest, length(url) as n from pages")
def strings(s, d):
    return table(s, d, "pages").select(F.col("page_id").alias("id"), F.split_part("url", F.lit("/"), F.lit(3)).alias("host"), F.md5(F.col("url").cast("binary")).alias("digest"), F.length("url").cast("long").alias("n"))


@add("fn_json", "select event_id as id, json_extract_string(props, '$.k') as k from events")
def js(s, d):
    return table(s, d, "events").select(F.col("event_id").alias("id"), F.get_json_object("props", "$.k").alias("k"))


@add("fn_array", f"with {oracles.sym('user_hop')} select src as id, array_to_string(list_sort(list(dst)), ',') as near, count(*) as n from e group by src")
def arrays(s, d):
    a = graph(s, d, "user_hop").symmetrized().arcs().groupBy(F.col("src").alias("id")).agg(F.array_sort(F.collect_list("dst")).alias("l"))
    return a.select("id", F.array_join(F.transform("l", lambda x: x.cast("string")), ",").alias("near"), F.size("l").cast("long").alias("n"))


@add("fn_map", f"with {oracles.sym('user_hop')}, m as (select src, min(dst) as a, max(dst) as b from e group by src) select src as id, a as first, b as last from m")
def maps(s, d):
    a = graph(s, d, "user_hop").symmetrized().arcs().groupBy(F.col("src").alias("id")).agg(F.map_from_arrays(F.array(F.lit("a"), F.lit("b")), F.array(F.min("dst"), F.max("dst"))).alias("m"))
    return a.select("id", F.element_at("m", "a").alias("first"), F.element_at("m", "b").alias("last"))


@add("fn_date", "select event_id as id, date_trunc('hour', ts)::timestamp as hour, day(ts)::int as day from events")
def dates(s, d):
    return table(s, d, "events").select(F.col("event_id").alias("id"), F.date_trunc("hour", "ts").cast("timestamp_ntz").alias("hour"), F.dayofmonth("ts").alias("day"))


@add("sql_recursive_ancestors", f"with recursive t as ({duck('geo_tree')}), w(id, up, n) as (select dst, src, 1 from t where dst >= 10 and dst < 100 union all select w.id, t.src, n + 1 from w join t on t.dst = w.up) select id, up, n from w")
def recursive(s, d):
    return s.sql("with recursive w(id, up, n) as (select dst, src, 1 from {t} where dst >= 10 and dst < 100 union all select w.id, t.src, n + 1 from w join {t} t on t.dst = w.up) select id, up, n from w", t=frame(s, d, "geo_tree"))


@add("edges_csv_roundtrip", f"select src, dst from ({THIN}) as g")
def csv(s, d):
    r = Rounds(s)
    path = f"{r.root}/edges-csv"
    frame(s, d, "supply_thin").select("src", "dst").write.option("header", True).csv(path)
    return s.read.schema("src long, dst long").option("header", True).csv(path)


@add("adjacency_text", f"with {oracles.sym('user_hop')} select src, dst from e")
def adjacency_text(s, d):
    """Written as lines ``id: n1 n2 ...`` and read back."""
    r = Rounds(s)
    path = f"{r.root}/adjacency"
    a = graph(s, d, "user_hop").symmetrized().arcs().groupBy("src").agg(F.collect_list("dst").alias("l"))
    a.select(F.concat_ws(": ", F.col("src").cast("string"), F.concat_ws(" ", F.transform("l", lambda x: x.cast("string"))))).write.text(path)
    x = s.read.text(path).select(F.split("value", ": ").alias("p"))
    return x.select(F.col("p")[0].cast("long").alias("src"), F.explode(F.split(F.col("p")[1], " ").cast("array<long>")).alias("dst"))


@add("stream_degree_tumbling", "select user_id, date_trunc('day', ts)::timestamp as day, count(*) as n from events where ts < (select date_trunc('day', max(ts) - interval 1 hour) from events) group by 1, 2")
def tumbling(s, d):
    x = streams.events(s, d).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day").alias("w"), "user_id").agg(F.count("*").alias("n"))
    return streams.drained(x.select("user_id", F.col("w.start").cast("timestamp_ntz").alias("day"), "n"), Rounds(s))


@add("stream_sessions", "with a as (select user_id, ts, coalesce(ts - lag(ts) over (partition by user_id order by ts) > interval 6 hour, true) as new from events), b as (select *, sum(new::int) over (partition by user_id order by ts rows unbounded preceding) as k from a) select user_id, date_trunc('milliseconds', min(ts))::timestamp as start, count(*) as n from b group by user_id, k having max(ts) + interval 6 hour <= (select max(ts) - interval 1 hour from events)")
def sessions(s, d):
    x = streams.events(s, d).withWatermark("ts", "1 hour").groupBy(F.session_window("ts", "6 hours").alias("w"), "user_id").agg(F.count("*").alias("n"))
    return streams.drained(x.select("user_id", F.date_trunc("millisecond", "w.start").cast("timestamp_ntz").alias("start"), "n"), Rounds(s))


@add("stream_dedup", "select user_id, event_type, count(distinct event_id) as n from events group by 1, 2")
def dedup(s, d):
    x = streams.events(s, d).withWatermark("ts", "1 day").dropDuplicatesWithinWatermark(["event_id"])
    return streams.drained(x.select("event_id", "user_id", "event_type"), Rounds(s)).groupBy("user_id", "event_type").agg(F.count("*").alias("n"))


TYPES = "select distinct user_id as src, 1000000 + length(event_type) as dst from events where value > 100"


@add("stream_components", f"with recursive e as (select src, dst from ({TYPES}) as a union select dst, src from ({TYPES}) as b), v as (select distinct src as id from e), " + oracles.components("", over="x as (select 1)").split("x as (select 1),", 1)[1])
def stream_components(s, d):
    e = streams.events(s, d).where("value > 100").select(F.col("user_id").alias("src"), (F.length("event_type") + 1000000).cast("long").alias("dst"))
    return streams.Components(s).follow(e)
