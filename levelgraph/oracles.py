"""Independent DuckDB SQL for the graph queries, built from shared table expressions."""

from __future__ import annotations

RAW = {
    "purchase": "select 2 * o_custkey as src, 2 * l_partkey + 1 as dst from lineitem join orders on l_orderkey = o_orderkey",
    "returned_purchase": "select 2 * o_custkey as src, 2 * l_partkey + 1 as dst from lineitem join orders on l_orderkey = o_orderkey where l_returnflag = 'R'",
    "supply": "select 2 * l_suppkey as src, 2 * l_partkey + 1 as dst from lineitem",
    "customer_orders": "select 2 * o_custkey as src, 2 * o_orderkey + 1 as dst from orders",
    "bulk_returns": "select 2 * l_orderkey as src, 2 * l_partkey + 1 as dst from lineitem where l_returnflag = 'R' and l_quantity >= 45",
    "user_flow": "select src, dst from (select user_id as src, lead(user_id) over (order by ts, event_id) as dst from events) where dst is not null",
    "geo_tree": "select 4 * n_nationkey + 1 as src, 4 * n_regionkey as dst from nation union all select 4 * c_custkey + 2, 4 * c_nationkey + 1 from customer union all select 4 * s_suppkey + 3, 4 * s_nationkey + 1 from supplier",
    "turn_chain": "select 100 * a.conv_id + a.turn as src, 100 * a.conv_id + a.turn + 1 as dst from conversations a join conversations b on a.conv_id = b.conv_id and b.turn = a.turn + 1",
    "doc_copies": "select first as src, doc_id as dst from (select doc_id, min(doc_id) over (partition by text) as first from documents where text is not null) where first <> doc_id",
    "page_anchor": """select 2 * page_id as src, 2 * rk + 1 as dst from (select page_id, unnest(regexp_extract_all(html, 'href="(/[^"]*)"', 1)) as path from pages) join (select path, row_number() over (order by encode(path)) - 1 as rk from (select distinct unnest(regexp_extract_all(html, 'href="(/[^"]*)"', 1)) as path from pages)) using (path)""",
}
RAW["vector_sim"] = "select a.vec_id as src, b.vec_id as dst from embeddings a join embeddings b on a.vec_id < b.vec_id where list_cosine_similarity(a.embedding::double[], b.embedding::double[]) > 0.45"
RAW["bench_overlap"] = "select 2 * doc_id as src, 2 * item_id + 1 as dst from documents d join benchmark b on contains(d.text, b.text)"
VERTICES = {
    "vector_sim": "select vec_id as v from embeddings",
    "bench_overlap": "select 2 * doc_id as v from documents union select 2 * item_id + 1 from benchmark",
    "purchase": "select 2 * c_custkey as v from customer union select 2 * p_partkey + 1 from part",
    "returned_purchase": "select 2 * c_custkey as v from customer union select 2 * p_partkey + 1 from part",
    "supply": "select 2 * s_suppkey as v from supplier union select 2 * l_partkey + 1 from lineitem",
    "customer_orders": "select 2 * c_custkey as v from customer union select 2 * o_orderkey + 1 from orders",
    "bulk_returns": "select 2 * o_orderkey as v from orders union select 2 * p_partkey + 1 from part",
    "user_flow": "select distinct user_id as v from events",
    "geo_tree": "select 4 * r_regionkey as v from region union select 4 * n_nationkey + 1 from nation union select 4 * c_custkey + 2 from customer union select 4 * s_suppkey + 3 from supplier",
    "turn_chain": "select distinct 100 * conv_id + turn as v from conversations",
    "doc_copies": "select distinct doc_id as v from documents",
    "page_anchor": "select 2 * page_id as v from pages union select dst from raw",
}


def _kron(scale: int, index: str) -> str:
    bits = f"(select range as l from range({scale}))"
    r = "('0x' || substr(md5('7:' || e || ':' || l), 1, 8))::bigint / 4294967296.0::double"
    draws = f"select e, l, {r} as r from ({index}), {bits}"
    return f"select sum(case when r >= 0.76 then 1::bigint << l else 0 end)::bigint as src, sum(case when (r >= 0.57 and r < 0.76) or r >= 0.95 then 1::bigint << l else 0 end)::bigint as dst from ({draws}) group by e"


def _kron_other(scale: int, a: float, ab: float, abc: float, index: str) -> str:
    draws = f"select e, l, ('0x' || substr(md5('7:' || e || ':' || l), 1, 8))::bigint / 4294967296.0::double as r from ({index}), (select range as l from range({scale}))"
    return f"select sum(case when r >= {ab} then 1::bigint << l else 0 end)::bigint as src, sum(case when (r >= {a} and r < {ab}) or r >= {abc} then 1::bigint << l else 0 end)::bigint as dst from ({draws}) group by e"


RAW["uniform10"] = _kron_other(10, 0.25, 0.5, 0.75, "select range as e from range(16384)")
RAW["shuffled10"] = f"select a.at as src, b.at as dst from ({_kron(10, 'select range as e from range(16384)')}) x join (select range as v, row_number() over (order by md5('7:' || range), range) - 1 as at from range(1024)) a on a.v = x.src join (select range as v, row_number() over (order by md5('7:' || range), range) - 1 as at from range(1024)) b on b.v = x.dst"
VERTICES["uniform10"] = VERTICES["shuffled10"] = "select range as v from range(1024)"
for _s in (8, 10, 12, 14):
    RAW[f"kron{_s}"] = _kron(_s, f"select range as e from range({16 << _s})")
    VERTICES[f"kron{_s}"] = f"select range as v from range({1 << _s})"
RAW["kron_orders"] = _kron(10, "select o_orderkey as e from orders")
VERTICES["kron_orders"] = "select range as v from range(1024)"

SOURCE = "(select v from deg order by md5('7:' || v), v limit 1)"


def base(g: str, *more: str) -> str:
    """Common table expressions of a graph, followed by ``more``."""
    parts = [
        f"raw as materialized ({RAW[g]})",
        f"vert as materialized ({VERTICES[g]})",
        "edges as materialized (select distinct least(src, dst) as u, greatest(src, dst) as v from raw where src <> dst)",
        "arcs as materialized (select u as src, v as dst from edges union all select v, u from edges)",
        "deg as materialized (select src as v, count(*) as deg from arcs group by src)",
        *more,
    ]
    return "with recursive " + ",\n".join(parts) + "\n"


LISTS = "lists as materialized (select a.src, a.dst, s.deg, d.deg as dst_deg, row_number() over (partition by a.src order by {order}) - 1 as place from arcs a join deg s on s.v = a.src join deg d on d.v = a.dst)"


def lists(order: str = "deg_desc") -> str:
    return LISTS.format(order={"deg_desc": "d.deg desc, a.dst", "deg_asc": "d.deg, a.dst", "id": "a.dst"}[order])


def depth(levels: int = 12) -> str:
    return f"""reach(v, d) as (select v, 0 from (select {SOURCE} as v) union select a.dst, d + 1 from reach join arcs a on a.src = reach.v where d < {levels}),
depth as materialized (select v, min(d) as depth from reach group by v)"""


def walk(alpha: int = 64, beta: int = 8) -> str:
    """Level sizes and the direction of each step of the hybrid search."""
    return f"""sizes as materialized (select depth as step, count(*) as nf, sum(deg) as mf from depth join deg using (v) group by depth),
walk(step, direction, was_up) as (select 0, case when mf * {alpha} > (select sum(deg) from deg) - mf then 'bottom_up' else 'top_down' end, false from sizes where step = 0
union all select s.step, case when w.direction = 'bottom_up' then case when s.nf * {beta} < (select count(*) from deg) then 'top_down' else 'bottom_up' end
when w.was_up or s.nf <= b.nf then 'top_down' when s.mf * {alpha} > (select sum(deg) from deg) - (select sum(mf) from sizes z where z.step <= s.step) then 'bottom_up' else 'top_down' end, w.was_up or (w.direction = 'bottom_up' and s.nf * {beta} < (select count(*) from deg))
from walk w join sizes s on s.step = w.step + 1 join sizes b on b.step = w.step)"""


def many(k: int, levels: int = 9) -> str:
    """Distances from the first k sampled sources."""
    return f"""source_list as materialized (select v from deg order by md5('7:' || v), v limit {k}),
far(root, v, d) as (select v, v, 0 from source_list union select root, a.dst, d + 1 from far join arcs a on a.src = far.v where d < {levels}),
dist as materialized (select root, v, min(d) as d from far group by 1, 2)"""


# arcs, degrees and distances under the labels of an order
RELABELLED = """larcs as materialized (select x.label as src, y.label as dst from arcs join perm x on x.v = src join perm y on y.v = dst),
ldeg as materialized (select src as v, count(*) as deg from larcs group by src)"""


def traced(arcs: str, deg: str, dist: str, steps: tuple[int, ...] = (1, 2), bits: int = 64) -> str:
    """Lines probed by bottom-up steps from all sources, each with the line before it."""
    return f"""tlists as materialized (select a.src, a.dst, row_number() over (partition by a.src order by d.deg desc, a.dst) - 1 as place from {arcs} a join {deg} d on d.v = a.dst),
wait as materialized (select s.v as root, step, g.v, e.d from source_list s cross join (values {', '.join(f'({k})' for k in steps)}) t(step) cross join {deg} g left join {dist} e on e.root = s.v and e.v = g.v where coalesce(e.d, 1000) > step),
stops as materialized (select e.root, l.src as v, min(place) as stop from tlists l join {dist} e on e.v = l.dst join {dist} f on f.root = e.root and f.v = l.src and f.d = e.d + 1 group by 1, 2),
trace as materialized (select root, step, v, 0 as i, v // {bits} as line from wait union all select w.root, step, w.v, place + 1, dst // {bits} from wait w join tlists l on l.src = w.v left join stops s on s.root = w.root and s.v = w.v where coalesce(w.d, 1000) <> step + 1 or place <= s.stop),
counted as materialized (select root, line, lag(line) over (partition by root, step order by v, i) as was from trace),
per_source as materialized (select root as source, count(*)::bigint as "references", count(*) filter (was is null or was <> line)::bigint as switches from counted group by 1)"""


def comps(single: bool) -> str:
    """Component of each vertex with an arc; a graph known to be one component takes a shortcut."""
    if single:
        return "comp as materialized (select v, (select min(v) from deg) as comp from deg)"
    return """linked(root, v) as (select v, v from deg union select root, a.dst from linked join arcs a on a.src = linked.v),
comp as materialized (select v, min(root) as comp from linked group by v)"""


def order(single: bool, levels: int = 40) -> str:
    """Place of each vertex in the sequential visit: depths from the seeds, then places level by level."""
    return f"""{comps(single)},
seed as materialized (select comp, arg_min(v, (deg, v)) as v, min((deg, v)) as k from deg join comp using (v) group by comp),
ranked as materialized (select comp, v, row_number() over (order by k) - 1 as cr from seed),
walk(v, d) as (select v, 0 from seed union select a.dst, d + 1 from walk join arcs a on a.src = walk.v where d < {levels if not single else 12}),
level as materialized (select v, min(d) as lv from walk group by v),
placed(lv, v, pos) as (select 0, v, cr from ranked union all select k + 1, v, row_number() over (order by p, deg, v) - 1 from (select placed.lv as k, a.dst as v, min(placed.pos) as p from placed join arcs a on a.src = placed.v join level on level.v = a.dst and level.lv = placed.lv + 1 group by 1, 2) join deg using (v)),
visit as materialized (select p.v, lv, c.comp, row_number() over (order by r.cr, lv, pos) - 1 as visit from placed p join comp c on c.v = p.v join ranked r on r.comp = c.comp),
perm as materialized (select (select count(*) from deg) - 1 - visit as label, v, comp from visit union all select (select count(*) from deg) + row_number() over (order by v) - 1, v, null from vert where v not in (select v from deg))"""


NATURAL = "perm as materialized (select row_number() over (order by v) - 1 as label, v from vert)"
LABELLED = "labelled as materialized (select least(a.label, b.label) as u, greatest(a.label, b.label) as v from edges e join perm a on a.v = e.u join perm b on b.v = e.v)"
