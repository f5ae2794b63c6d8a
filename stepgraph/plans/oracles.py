"""SQL for DuckDB that gives the same rows as the queries of ``workloads``."""

from __future__ import annotations

from ..sources.fixtures import duck


def sym(name: str) -> str:
    return f"e as (select src, dst from ({duck(name)}) as q0 union select dst, src from ({duck(name)}) as q1), v as (select distinct src as id from e)"


def hops(name: str, directed: bool = False, sources: str = "") -> str:
    """CTE r(src, dst, hops) by breadth-first floods with keyed state."""
    e = f"e as (select distinct src, dst from ({duck(name)}) as q0 where src <> dst), v as (select src as id from e union select dst from e)" if directed else sym(name)
    return f"""with recursive {e},
r(src, dst, hops) using key (src, dst) as (
  select id, id, 0 from v {sources}
  union
  select p.src, e.dst, min(p.hops) + 1 from r p join e on e.src = p.dst
  where not exists (select 1 from recurring.r o where o.src = p.src and o.dst = e.dst) group by p.src, e.dst)
"""


def components(name: str, out: str = "component", over: str | None = None) -> str:
    e = over or sym(name)
    return f"""with recursive {e},
c(id, m) using key (id) as (
  select id, id from v
  union
  select e.dst, min(p.m) from c p join e on e.src = p.id join recurring.c o on o.id = e.dst where p.m < o.m group by e.dst)
select id, m as {out} from c"""


def chain_components(limit: str = "") -> str:
    return f"select event_id as id, min(event_id) over (partition by user_id) as component from (select *, row_number() over (partition by user_id order by ts, event_id) as nth, count(*) over (partition by user_id) as n from events) as q where n > 1 {limit}"


def pagerank(name: str, iters: int, directed: bool, spread: bool = False) -> str:
    e = f"e as (select distinct src, dst from ({duck(name)}) as q0 where src <> dst), v as (select src as id from e union select dst from e)" if directed else sym(name)
    out = f"with {e}, d as (select src, count(*) as deg from e group by src), n as (select count(*)::double as n from v), r0 as (select id, 1.0 / n as rank from v, n)"
    for k in range(iters):
        lost = f"(select coalesce(sum(rank), 0.0) from r{k} where id not in (select src from d)) / n" if spread else "0.0"
        out += f", r{k + 1} as (select v.id, (1 - 0.85) / n + 0.85 * (coalesce(s, 0.0) + {lost}) as rank from v cross join n left join (select e.dst, sum(r.rank / d.deg) as s from e join d on d.src = e.src join r{k} r on r.id = e.src group by e.dst) g on g.dst = v.id)"
    return out + f" select id, round(rank, 10) as rank from r{iters}"


def scc(name: str) -> str:
    return hops(name, True) + "select a.src as id, min(a.dst) as scc from r a join r b on a.src = b.dst and a.dst = b.src group by a.src"


TOUR = """with e as (select src, dst from ({t}) as q0 union select dst, src from ({t}) as q1),
n as (select src as v, dst as u, coalesce(lead(dst) over (partition by src order by dst), first_value(dst) over (partition by src order by dst)) as w from e)
select u as src, v as dst, v as next_src, w as next_dst from n"""


def tree_orders(name: str) -> str:
    return f"""with recursive t as ({duck(name)}),
p as (select cast(0 as bigint) as id, cast(null as bigint) as parent, [cast(0 as bigint)] as path, cast(0 as bigint) as depth
  union all select t.dst, t.src, list_append(p.path, t.dst), p.depth + 1 from p join t on t.src = p.id),
o as (select id, parent, depth, path, row_number() over (order by path) - 1 as pre from p),
up as (select unnest(path) as id from p),
s as (select id, count(*) as size from up group by id)
select o.id, o.parent, o.pre, o.pre + s.size - o.depth as post, o.depth, s.size from o join s on s.id = o.id"""


RANK = "select event_id as id, cast(sum(cast(round(value * 100) as bigint)) over (partition by user_id order by ts, event_id) as bigint) as sum_val from events"


def fold_forest(name: str) -> str:
    """Sorted edges folded one by one: the root of each vertex is kept in a map."""
    return f"""with recursive q as (select least(src, dst) as a, greatest(src, dst) as b, min(w) as w from ({duck(name)}) as q0 group by 1, 2),
o as (select *, row_number() over (order by w, a, b) as n from q),
v as (select list(id order by id) as ids from (select a as id from q union select b from q)),
f(n, roots, used) as (
  select cast(0 as bigint), ids, false from v
  union all
  select o.n, case when ra = rb then roots else list_transform(roots, lambda x: case when x = greatest(ra, rb) then least(ra, rb) else x end) end, ra <> rb
  from (select f.n, f.roots, o.n as m, f.roots[list_position(v.ids, o.a)] as ra, f.roots[list_position(v.ids, o.b)] as rb from f join o on o.n = f.n + 1 cross join v) as x join o on o.n = x.m)
select a as src, b as dst, w from f join o on o.n = f.n where used"""


def fold_matching(name: str) -> str:
    return f"""with recursive q as (select least(src, dst) as a, greatest(src, dst) as b, min(w) as w from ({duck(name)}) as q0 group by 1, 2),
o as (select *, row_number() over (order by w desc, a, b) as n from q),
f(n, taken, used) as (
  select cast(0 as bigint), []::bigint[], false
  union all
  select o.n, case when free then list_concat(taken, [o.a, o.b]) else taken end, free
  from (select f.taken, o.n as m, not list_contains(f.taken, o.a) and not list_contains(f.taken, o.b) as free from f join o on o.n = f.n + 1) as x join o on o.n = x.m)
select a as src, b as dst, w from f join o on o.n = f.n where used"""


def fold_colours(name: str) -> str:
    return f"""with recursive {sym(name)},
o as (select id, row_number() over (order by id) as n from v),
b as (select y.n, list(x.n) filter (where x.n < y.n) as near from e join o x on x.id = e.src join o y on y.id = e.dst group by y.n),
f(n, colours) as (
  select cast(0 as bigint), []::int[]
  union all
  select b.n, list_append(f.colours, (select min(k)::int from range(0, 1000) as t(k) where not list_contains(list_transform(coalesce(b.near, []), lambda i: f.colours[i]), k::int)))
  from f join b on b.n = f.n + 1)
select o.id, l.colours[o.n] as color from o cross join (select colours from f order by n desc limit 1) as l"""


def lexi_bipartite(name: str, rounds: int = 12) -> str:
    out = f"with e0 as (select distinct src, dst from ({duck(name)}) as q0)"
    for k in range(rounds):
        out += f", g{k} as (select dst, min(src) as src from e{k} group by dst), m{k} as (select src, min(dst) as dst from g{k} group by src), e{k + 1} as (select * from e{k} where src not in (select src from m{k}) and dst not in (select dst from m{k}))"
    return out + " " + " union all ".join(f'select src as "left", dst as "right" from m{k}' for k in range(rounds))


def betweenness(name: str, directed: bool = False) -> str:
    return hops(name, directed) + f""", lv as (select max(hops) as top from r),
c(src, dst, hops, n) as (
  select src, dst, 0, 1.0::double from r where hops = 0
  union all
  select c.src, e.dst, c.hops + 1, sum(c.n) from c join e on e.src = c.dst join r on r.src = c.src and r.dst = e.dst and r.hops = c.hops + 1 group by c.src, e.dst, c.hops)
select v.id, round(coalesce(s, 0) * 0.5, 6) as score from v left join (
  select a.dst as id, sum(a.n * b.n / t.n) as s from c a join c b on a.dst = b.src join c t on t.src = a.src and t.dst = b.dst
  where a.hops + b.hops = t.hops and a.dst <> a.src and a.dst <> b.dst group by a.dst) as x on x.id = v.id"""


def weighted_betweenness(name: str) -> str:
    return f"""with recursive q as (select least(src, dst) as a, greatest(src, dst) as b, min(w) as w from ({duck(name)}) as q0 group by 1, 2),
e as (select a as src, b as dst, w from q union all select b, a, w from q),
d(src, dst, dist) using key (src, dst) as (
  select distinct src, src, 0.0::double from e
  union
  select p.src, e.dst, min(p.dist + e.w) from d p join e on e.src = p.dst left join recurring.d o on o.src = p.src and o.dst = e.dst where o.dist is null or p.dist + e.w < o.dist group by p.src, e.dst),
c(src, dst) as (
  select distinct src, src from e
  union all
  select c.src, e.dst from c join e on e.src = c.dst join d x on x.src = c.src and x.dst = c.dst join d y on y.src = c.src and y.dst = e.dst where round(x.dist + e.w - y.dist, 9) = 0),
n as (select src, dst, count(*)::double as n, any_value(dist) as dist from c join d using (src, dst) group by src, dst)
select v.id, round(coalesce(s, 0) * 0.5, 6) as score from (select distinct src as id from e) as v left join (
  select a.dst as id, sum(a.n * b.n / t.n) as s from n a join n b on a.dst = b.src join n t on t.src = a.src and t.dst = b.dst
  where round(a.dist + b.dist - t.dist, 9) = 0 and a.dst <> a.src and a.dst <> b.dst group by a.dst) as x on x.id = v.id"""


def breadth_tree(name: str) -> str:
    """Edges to the least neighbour that is nearer to the component's least vertex."""
    return hops(name, sources=f"where id in (select component from ({components(name)}) as k)") + "select least(min(e.src), e.dst) as src, greatest(min(e.src), e.dst) as dst from r a join e on e.src = a.dst join r b on b.src = a.src and b.dst = e.dst and b.hops = a.hops + 1 group by e.dst"


def sssp(name: str) -> str:
    return f"""with recursive e as (select src, dst, w from ({duck(name)}) as q0 union all select dst, src, w from ({duck(name)}) as q1),
d(id, dist) using key (id) as (
  select min(src), 0.0::double from e
  union
  select e.dst, min(p.dist + e.w) from d p join e on e.src = p.id left join recurring.d o on o.id = e.dst where o.dist is null or p.dist + e.w < o.dist group by e.dst)
select id, round(dist, 6) as dist from d"""


def simulation(edges: str, labels: str, q_labels: dict[int, str], q_edges: list, rounds: int = 3, dual: bool = False) -> str:
    """Rounds of pruning, written out; enough of them for the query graph's depth on these graphs."""
    out = f"with g as ({duck(edges)}), l as ({duck(labels)}), m0 as (" + " union all ".join(f"select {q} as q, id from l where label = '{x}'" for q, x in q_labels.items()) + ")"
    for k in range(rounds):
        tests = []
        for a, b in q_edges:
            tests.append(f"(q <> {a} or exists (select 1 from g join m{k} y on y.id = g.dst and y.q = {b} where g.src = x.id))")
            if dual:
                tests.append(f"(q <> {b} or exists (select 1 from g join m{k} y on y.id = g.src and y.q = {a} where g.dst = x.id))")
        out += f", m{k + 1} as (select q, id from m{k} x where {' and '.join(tests)})"
    return out + f" select q, id from m{rounds} where (select count(distinct q) from m{rounds}) = {len(q_labels)}"


def strong_chain(edges: str, labels: str, q_labels: dict[int, str], q_edges: list, rounds: int = 3) -> str:
    """For a query that is a directed path 0 - 1 - 2: every centre's ball of radius 2."""
    inner = simulation(edges, labels, q_labels, q_edges, rounds, True)
    out = f"with recursive g as ({duck(edges)}), b as (select src, dst from g union select dst, src from g), w as ({inner}), ball as (select distinct id as center, id from w), b1 as (select center, id from ball union select center, b.dst from ball join b on b.src = ball.id), b2 as (select center, id from b1 union select center, b.dst from b1 join b on b.src = b1.id), m0 as (select center, q, w.id from b2 join w on w.id = b2.id)"
    for k in range(rounds):
        tests = [t for a, c in q_edges for t in (
            f"(q <> {a} or exists (select 1 from g join m{k} y on y.id = g.dst and y.q = {c} and y.center = x.center where g.src = x.id))",
            f"(q <> {c} or exists (select 1 from g join m{k} y on y.id = g.src and y.q = {a} and y.center = x.center where g.dst = x.id))")]
        out += f", m{k + 1} as (select center, q, id from m{k} x where {' and '.join(tests)})"
    m = f"m{rounds}"
    out += f", full_ as (select * from {m} where center in (select center from {m} group by center having count(distinct q) = {len(q_labels)}))"
    real = " union ".join(f"select x.center, x.id as src, y.id as dst from full_ x join g on g.src = x.id join full_ y on y.id = g.dst and y.center = x.center where x.q = {a} and y.q = {c}" for a, c in q_edges)
    out += f", real1 as ({real}), real2 as (select center, src, dst from real1 union select center, dst, src from real1)"
    out += ", hit(center, id) as (select distinct center, id from full_ where center = id union select hit.center, real2.dst from hit join real2 on real2.center = hit.center and real2.src = hit.id)"
    return out + " select full_.center, q, full_.id from full_ join hit on hit.center = full_.center and hit.id = full_.id"


def without_each(name: str) -> str:
    """CTE k(x, id, m): component labels of the graph without vertex x; and the pairs of edges at a vertex that share a block."""
    return f"""with recursive {sym(name)},
k(x, id, m) using key (x, id) as (
  select x.id, y.id, y.id from v x join v y on x.id <> y.id
  union
  select p.x, e.dst, min(p.m) from k p join e on e.src = p.id and e.dst <> p.x join recurring.k o on o.x = p.x and o.id = e.dst where p.m < o.m group by p.x, e.dst)
"""


def cut_vertices(name: str) -> str:
    return without_each(name) + "select e.src as id from e join k on k.x = e.src and k.id = e.dst group by e.src having count(distinct k.m) > 1"


def bridge_edges(name: str) -> str:
    return f"""with recursive {sym(name)},
h as (select src as a, dst as b from e where src < dst),
k(a, b, id) as (
  select a, b, a from h
  union
  select k.a, k.b, e.dst from k join e on e.src = k.id and not (e.src = k.a and e.dst = k.b) and not (e.src = k.b and e.dst = k.a))
select a as src, b as dst from h where not exists (select 1 from k where k.a = h.a and k.b = h.b and k.id = h.b)"""
