"""Queries of the experiments: ladder, cache table, balance, parameters, sources, and their oracles."""

from __future__ import annotations

import functools

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from levelgraph import oracles as o
from levelgraph.apps import consumers
from levelgraph.balance import ranges as rg
from levelgraph.bfs import hybrid, kernels, sql_search
from levelgraph.bitmap import blocks
from levelgraph.graph import build
from levelgraph.measure import report, work
from levelgraph.plans.published import CACHE, SCALING, WATTS
from levelgraph.registry import Prepared, add, plain
from levelgraph.reorder import level_order as lo
from levelgraph.reorder import locality as loc
from levelgraph.runtime import materialize

SINGLE = {"purchase", "returned_purchase", "supply", "user_flow", "kron8", "kron10", "kron_orders"}
# sources over which the cache table and range sizes are averaged
SOURCES = {"kron10": 64, "purchase": 8}


def _ladder(p: Prepared) -> DataFrame:
    """The five cumulative configurations: counters of one search each, from the same vertex."""
    drop = p.make("dense_perm", lambda: materialize(build.drop_isolated(p.graph), "dense_perm"))
    dense = build.Graph(build.relabel(p.graph.edges, drop).select(F.col("u").alias("src"), F.col("v").alias("dst")), drop.select(F.col("label").alias("v")), f"{p.name}_dense")
    start = {"base": p.source, "no_isolated": drop.where(F.col("v") == p.source).first()["label"]}
    label = p.perm("rlo").where(F.col("v") == p.source).first()["label"]
    rows = []
    for name, options in hybrid.VARIANTS.items():
        graph = p.graph if name == "base" else dense if name == "no_isolated" else p.tidy
        run = hybrid.bfs(graph, start.get(name, label), **options)
        rows.append((name, sum(s["inspected_edges"] for s in run.steps), len(run.steps), run.result.count()))
    return p.spark.createDataFrame(rows, "variant string, inspected_edges long, steps long, reached long")


def _ladder_sql(g: str) -> str:
    orders = {"id": "a.dst", "label": "q.label", "best": "d.deg desc, q.label"}
    parts = [o.base(g, o.depth(), o.order(g in SINGLE), o.walk().replace("walk", "turns")).rstrip()]
    for k, expr in orders.items():
        parts.append(
            f"l_{k} as materialized (select a.src, a.dst, row_number() over (partition by a.src order by {expr}) - 1 as place from arcs a join deg d on d.v = a.dst join perm q on q.v = a.dst),\n"
            f"h_{k} as materialized (select e.depth as step, l.src as v, min(l.place) + 1 as n from l_{k} l join depth e on e.v = l.dst group by 1, 2),\n"
            f"b_{k} as (select coalesce(sum(coalesce(h.n, x.deg)), 0) as n from turns w cross join deg x left join depth e on e.v = x.v left join h_{k} h on h.step = w.step and h.v = x.v where w.direction = 'bottom_up' and coalesce(e.depth, 1000) > w.step)"
        )
    td = "(select coalesce(sum(mf), 0) from turns join sizes using (step) where direction = 'top_down')"
    rows = [("base", "id"), ("no_isolated", "id"), ("reordered", "label"), ("reordered_lb", "best"), ("reordered_lb_vec", "best")]
    return ",\n".join(parts) + "\n" + " union all ".join(f"select '{name}' as variant, ({td} + (select n from b_{k}))::bigint as inspected_edges, (select count(*) from turns)::bigint as steps, (select count(*) from depth)::bigint as reached" for name, k in rows)


def _switches(p: Prepared, kind: str) -> DataFrame:
    steps = (1, 2)

    def made() -> DataFrame:
        near = p.near(SOURCES[p.name], max(steps))
        if kind == "natural":
            graph, depths = p.graph, near
        else:
            names = p.perm("rlo").select("v", "label")
            start = names.select(F.col("v").alias("source"), F.col("label").alias("from")).join(near.select("source").distinct(), "source")
            depths = near.join(names, "v").join(F.broadcast(start), "source").select(F.col("from").alias("source"), F.col("label").alias("v"), "depth")
            graph = p.tidy
        return materialize(work.source_switches(graph, depths, steps), "switches")

    per = p.make(f"switches_{kind}", made)
    return per.agg(F.count("*").alias("sources"), F.sum("references").alias("references"), F.sum("switches").alias("switches"))


def _switches_sql(g: str, kind: str) -> str:
    if kind == "natural":
        tables = (o.many(SOURCES[g]), o.traced("arcs", "deg", "dist"))
    else:
        moved = "ldist as materialized (select x.label as root, y.label as v, d from dist join perm x on x.v = root join perm y on y.v = dist.v)"
        renamed = "source_ids as materialized (select label as v from source_list join perm using (v))"
        tables = (o.many(SOURCES[g]), o.order(True), o.RELABELLED, moved, renamed, o.traced("larcs", "ldeg", "ldist").replace("source_list", "source_ids"))
    return o.base(g, *tables) + 'select count(*)::bigint as sources, sum("references")::bigint as "references", sum(switches)::bigint as switches from per_source'


def _cache(p: Prepared) -> DataFrame:
    a, b = (_switches(p, kind).select("references", F.col("switches").alias("misses")) for kind in ("natural", "reordered"))
    return report.cache_report(a, b).select(F.col("rb").alias("references_before"), F.col("ra").alias("references_after"), "references_cut", F.col("mb").alias("misses_before"), F.col("ma").alias("misses_after"), "misses_cut", "rate_before", "rate_after")


def _cache_sql(g: str) -> str:
    one = lambda kind: f"({_switches_sql(g, kind)})"
    return f"""select b."references" as references_before, a."references" as references_after, round(100 * (1 - a."references"::double / b."references"), 6) as references_cut, b.switches as misses_before, a.switches as misses_after,
round(100 * (1 - a.switches::double / b.switches), 6) as misses_cut, round(100 * b.switches::double / b."references", 6) as rate_before, round(100 * a.switches::double / a."references", 6) as rate_after from {one("natural")} b cross join {one("reordered")} a"""


def _live_many(p: Prepared, kind: str) -> DataFrame:
    """Mean live size of 20 descending ranges after each step, over the sampled sources that reach it."""
    key = "rlo" if kind == "reordered" else kind
    names = p.perm(key).where("comp is not null" if key == "rlo" else "true").select("v", "label")
    depths = p.many(SOURCES[p.name]).join(names, "v").select("source", F.col("label").alias("v"), "depth")
    n = p.graph.degrees.count() if key == "rlo" else p.graph.vertices.count()
    each = rg.live_range_size(names.select(F.col("label").alias("v")), depths, rg.range_table(p.spark, n, 20, 8), ("source",))
    return each.groupBy("step").agg(F.count("*").alias("sources"), F.sum("live_size").alias("live_total"), F.round(F.avg("live_size"), 6).alias("mean_live"))


def _live_sql(g: str, kind: str) -> str:
    members = "select v from vert" if kind == "natural" else "select v from deg"
    order = o.NATURAL if kind == "natural" else o.order(True)
    return o.base(g, o.many(SOURCES[g]), order) + f"""select step::bigint as step, count(*)::bigint as sources, sum(live)::bigint as live_total, round(avg(live), 6) as mean_live from (select root, step, sum(live)::bigint as live from (
select r.root, s.step, c.k, max(r.label) - min(r.label) + 1 as live from (select q.v as root, p.label, coalesce(d.d, (select max(d) + 1 from dist)) as depth from source_list q cross join perm p left join dist d on d.root = q.v and d.v = p.v where p.v in ({members})) r
join (select range as k, b * range * (41 - range) // 420 * 8 as lo, b * (range + 1) * (40 - range) // 420 * 8 as hi from (select (count(*) + 7) // 8 as b from ({members})), range(20)) c on r.label >= c.lo and r.label < c.hi
join (select distinct d as step from dist) s on r.depth > s.step group by 1, 2, 3) group by 1, 2) group by 1"""


def _executed_slots(p: Prepared, balance: str, workers: int = 8) -> DataFrame:
    """Arcs that each task gets when the frontier of every step is really dealt out."""
    out = None
    levels = [(r["depth"], r["n"]) for r in p.depths.groupBy("depth").agg(F.count("*").alias("n")).orderBy("depth").collect()]  # a row for each level
    for step, n in levels:
        frontier = p.depths.where(F.col("depth") == step).join(p.graph.degrees, "v").select("v", "deg")
        part = hybrid.dealt_arcs(p.graph.arcs, frontier, n, balance, workers).groupBy(F.spark_partition_id().alias("slot")).agg(F.count("*").alias("edges"))
        part = part.select(F.lit(step).alias("step"), "slot", "edges")
        out = part if out is None else out.union(part)
    return out


def _slots_sql(g: str, kind: str, workers: int) -> str:
    slots = "select depth as step, deg, row_number() over (partition by depth order by v) - 1 as j, count(*) over (partition by depth) as n from depth join deg using (v)"
    even = f"select step, j * {workers} // n as slot, deg as edges from ({slots})" if kind == "static" else f"select step, range as slot, deg // {workers} as edges from ({slots}), range({workers}) union all select step, j % {workers}, deg % {workers} from ({slots})"
    return f"select step::bigint as step, slot::bigint as slot, sum(edges)::bigint as edges from ({even}) group by 1, 2 having sum(edges) > 0"


def imbalance_sql(slots: str, workers: int) -> str:
    return f"select step, max(edges)::bigint as max_edges, round(sum(edges) / {workers}::double, 6) as mean_edges, ({workers} - count(*))::bigint as idle, round(sqrt(greatest(sum(edges * edges) / {workers}::double - pow(sum(edges) / {workers}::double, 2), 0)) / (sum(edges) / {workers}::double), 6) as variation from ({slots}) group by step"


def _range_files(p: Prepared) -> DataFrame:
    """Lists and arcs in the file of each descending range, and how many files hold the range."""
    lists, _ = kernels.range_lists(p.graph, p.graph.totals["top"] + 1, 20, 64, "descending")
    named = lists.select("rid", F.size("nbrs").alias("arcs"), F.input_file_name().alias("file"))
    return named.groupBy("rid").agg(F.count("*").alias("lists"), F.sum("arcs").alias("arcs"), F.countDistinct("file").alias("files"))


def _phases(p: Prepared) -> DataFrame:
    run = hybrid.bfs(p.graph, p.source, phase_plan=("sliced", "full", "static"), vectorized=False, block=64)
    return run.result


def _tune_sql(g: str) -> str:
    grid = [(a, b) for a in (1, 8, 64, 256) for b in (2, 8, 64)]
    parts = [o.base(g, o.depth(), o.lists()).rstrip(), "sizes as materialized (select depth as step, count(*) as nf, sum(deg) as mf from depth join deg using (v) group by depth)",
             "hit as materialized (select e.depth as step, l.src as v, min(l.place) + 1 as n from lists l join depth e on e.v = l.dst group by 1, 2)",
             "up as materialized (select s.step, sum(coalesce(h.n, x.deg)) as n from sizes s cross join deg x left join depth e on e.v = x.v left join hit h on h.step = s.step and h.v = x.v where coalesce(e.depth, 1000) > s.step group by 1)"]
    for k, (a, b) in enumerate(grid):
        parts.append(o.walk(a, b).split("\n", 1)[1].replace("walk", f"walk{k}"))
    rows = " union all ".join(f"select {a}::bigint as alpha, {b}::bigint as beta, coalesce(sum(case when w.direction = 'bottom_up' then coalesce(u.n, 0) else s.mf end), 0)::bigint as inspected_edges, count(*) filter (w.direction = 'bottom_up')::bigint as bottom_up_steps from walk{k} w join sizes s using (step) left join up u using (step)" for k, (a, b) in enumerate(grid))
    return ",\n".join(parts) + "\n" + rows


def _tune(p: Prepared) -> DataFrame:
    """Inspected edges of the hybrid search over a grid of alpha and beta."""
    rows = []
    for alpha in (1, 8, 64, 256):
        for beta in (2, 8, 64):
            run = hybrid.bfs(p.graph, p.source, alpha=alpha, beta=beta, trim=False)
            rows.append((alpha, beta, sum(s["inspected_edges"] for s in run.steps), sum(s["direction"] == "bottom_up" for s in run.steps)))
    return p.spark.createDataFrame(rows, "alpha long, beta long, inspected_edges long, bottom_up_steps long")


RANGE_ROWS = """ranges20 as (select (row_number() over (order by lo) - 1) as rid, lo, least(hi, n) as hi from (select n, b * range * (41 - range) // 420 * 8 as lo, b * (range + 1) * (40 - range) // 420 * 8 as hi from (select max(v) + 1 as n, (max(v) + 8) // 8 as b from vert), range(20)) where lo < hi),
hits20 as materialized (select l.src as v, min(l.place) + 1 as n from lists l join depth e on e.v = l.dst join depth f on f.v = l.src and f.depth = e.depth + 1 group by 1),
work20 as materialized (select s.step, r.rid, count(*) as unvisited, sum(x.deg) as degree_sum, sum(case when f.depth = s.step + 1 then coalesce(h.n, x.deg) else x.deg end) as inspected_edges
from (select distinct depth as step from depth) s cross join deg x join ranges20 r on x.v >= r.lo and x.v < r.hi left join depth f on f.v = x.v left join hits20 h on h.v = x.v where coalesce(f.depth, 1000) > s.step group by 1, 2)"""


def _ranges(p: Prepared) -> DataFrame:
    return rg.range_table(p.spark, p.graph.vertices.agg(F.max("v")).first()[0] + 1, 20, 8)


def _balance_layer() -> None:
    for g in ("purchase", "supply", "kron10"):
        head = o.base(g, o.depth())
        for kind, made in (("static", rg.static_slots), ("sliced", rg.sliced_slots)):
            for t in (4, 8, 40):
                if (g, t) in (("purchase", 8), ("kron10", 8)):
                    continue  # registered with the search queries
                add(f"slot_{kind}_t{t}_{g}", lambda p, f=made, t=t: f(rg.placed_frontier(p.graph, p.depths), t), head + _slots_sql(g, kind, t), g)
                add(f"imbalance_{kind}_t{t}_{g}", lambda p, f=made, t=t: rg.imbalance(f(rg.placed_frontier(p.graph, p.depths), t), t), head + imbalance_sql(_slots_sql(g, kind, t), t), g)
            if g != "purchase":
                add(f"slots_executed_{kind}_{g}", lambda p, k=kind: _executed_slots(p, k), head + _slots_sql(g, kind, 8), g)
    for g in ("purchase", "kron10"):
        work20 = o.base(g, o.depth(), o.lists(), RANGE_ROWS)
        add(f"range_work_{g}", lambda p: work.range_inspection(p.graph, p.depths, _ranges(p)), work20 + "select step::bigint as step, rid::bigint as rid, unvisited::bigint as unvisited, degree_sum::bigint as degree_sum, inspected_edges::bigint as inspected_edges from work20", g)
        pull = """, tasks as materialized (select step, row_number() over (partition by step order by rid) as k, degree_sum::double as w, count(*) over (partition by step) as n from work20),
pull(step, k, loads) as (select distinct step, 0::bigint, [0.0::double, 0.0::double, 0.0::double, 0.0::double] from tasks
union all select p.step, t.k, list_transform(range(1, 5), lambda i: case when i = list_position(p.loads, list_min(p.loads)) then p.loads[i] + t.w else p.loads[i] end) from pull p join tasks t on t.step = p.step and t.k = p.k + 1)
select p.step::bigint as step, list_max(loads) as makespan, list_sum(loads) / 4 as mean, list_max(loads) / (list_sum(loads) / 4) as ratio from pull p join (select distinct step, n from tasks) t on t.step = p.step and t.n = p.k"""
        add(f"pulling_makespan_{g}", lambda p: rg.pulling_report(work.range_inspection(p.graph, p.depths, _ranges(p)), 4), work20.rstrip() + pull, g)
        add(f"range_files_{g}", _range_files, o.base(g) + "select r.rid::bigint as rid, count(*)::bigint as lists, sum(deg)::bigint as arcs, 1::bigint as files from deg join (select (row_number() over (order by lo) - 1) as rid, lo, least(hi, n) as hi from (select n, b * range * (41 - range) // 420 * 64 as lo, b * (range + 1) * (40 - range) // 420 * 64 as hi from (select max(v) + 1 as n, (max(v) + 64) // 64 as b from deg), range(20)) where lo < hi) r on v >= lo and v < hi group by 1", g)
        add(f"phase_summary_{g}", lambda p: p.run.step_log().groupBy("phase").agg(F.count("*").alias("steps"), F.sum("discovered").alias("discovered")), o.base(g, o.depth(), o.walk()) + "select phase::bigint as phase, count(*)::bigint as steps, sum(coalesce((select nf from sizes z where z.step = x.step + 1), 0))::bigint as discovered from (select step, case when direction = 'bottom_up' then 2 when was_up then 3 else 1 end as phase from walk) x group by 1", g)
        add(f"bfs_phases_{g}", _phases, o.base(g, o.depth()) + "select d.v, (case when d.depth = 0 then d.v else (select arg_max(a.src, (x.deg, -a.src)) from arcs a join depth e on e.v = a.src join deg x on x.v = a.src where a.dst = d.v and e.depth = d.depth - 1) end)::bigint as parent, d.depth::bigint as depth from depth d", g)
    plain("lambda_rule", lambda spark, sf: rg.lambda_table(spark), "select range as scale, (case when range < 26 then 10 else 24 end)::bigint as lam from range(20, 33)")


def _locality_layer() -> None:
    for g in SOURCES:
        for kind in ("natural", "reordered"):
            add(f"line_switches_{kind}_{g}", functools.partial(_switches, kind=kind), _switches_sql(g, kind), g)
            add(f"live_range_many_{kind}_{g}", functools.partial(_live_many, kind=kind), _live_sql(g, kind), g)
        add(f"cache_report_{g}", _cache, _cache_sql(g), g)
    for g in ("kron8", "kron10"):
        lru = o.base(g, o.depth(), o.lists()) + """, waiting as (select d.v from deg d left join depth e using (v) where coalesce(e.depth, 1000) > 1), stop as (select l.src as v, min(place) as stop from lists l join depth e on e.v = l.dst where e.depth = 1 group by 1),
trace as materialized (select row_number() over (order by v, i) as t, line from (select v, 0 as i, v // 64 as line from waiting union all select w.v, place + 1, dst // 64 from waiting w join lists l on l.src = w.v left join stop s on s.v = w.v where s.stop is null or place <= s.stop)),
linked as materialized (select t, line, lag(t) over (partition by line order by t) as p from trace),
between_uses as materialized (select a.t, count(*) as others from linked a join linked b on b.t > a.p and b.t < a.t and coalesce(b.p, 0) <= a.p group by a.t)
select count(*)::bigint as "references", count(*) filter (p is null or coalesce(others, 0) >= 4)::bigint as misses from linked left join between_uses using (t)"""
        add(f"lru_misses_{g}", lambda p: work.line_misses(work.probe_trace(p.graph, p.depths, 1), 4), lru, g)


def _ladder_layer() -> None:
    for g in ("kron10", "purchase", "returned_purchase"):
        add(f"ablation_{g}", _ladder, _ladder_sql(g), g)
    for g in ("kron8", "kron10"):
        add(f"tune_switch_{g}", _tune, _tune_sql(g), g)


def _source_layer() -> None:
    for g, k in (("kron10", 64), ("purchase", 8)):
        add(f"bfs_{k}_sources_{g}", lambda p, k=k: p.many(k), o.base(g, o.many(k)) + "select root as source, v, d::bigint as depth from dist", g)
        runs = "select root, count(*) as reached, max(d) + 1 as steps, (select count(*) from raw where src in (select x.v from dist x where x.root = far.root)) as edges from dist far group by root"
        add(f"edges_per_step_{g}", lambda p, k=k: _edges_per_step(p, k), o.base(g, o.many(k)) + f"select count(*)::bigint as runs, round(avg(edges / steps::double), 6) as mean, round(count(*) / sum(steps / edges::double), 6) as harmonic_mean, round(min(edges / steps::double), 6) as min, round(quantile_cont(edges / steps::double, 0.25), 6) as q1, round(quantile_cont(edges / steps::double, 0.5), 6) as median, round(quantile_cont(edges / steps::double, 0.75), 6) as q3, round(max(edges / steps::double), 6) as max from ({runs})", g)
    for g in ("kron8", "page_anchor"):
        every = """every(root, v, d) as (select v, v, 0 from deg union select root, a.dst, d + 1 from every join arcs a on a.src = every.v where d < 12), pairs as materialized (select root, v, min(d) as d from every group by 1, 2),
paths(root, v, d, n) as (select root, v, 0, 1.0::double from pairs where d = 0 union all select p.root, a.dst, p.d + 1, sum(p.n) from paths p join arcs a on a.src = p.v join pairs q on q.root = p.root and q.v = a.dst and q.d = p.d + 1 group by p.root, a.dst, p.d),
chosen as (select v from deg order by md5('7:' || v), v limit 8)"""
        add(f"betweenness_{g}", lambda p: consumers.betweenness(p.graph, [r["v"] for r in hybrid.sample_sources(p.graph, 8).collect()]), o.base(g, every) + "select a.v, round(coalesce(sum(case when c.v is not null and c.v <> a.v and st.v is not null then a.n * c.n / st.n end), 0), 6) as betweenness from chosen s join paths a on a.root = s.v left join paths c on c.root = a.v left join paths st on st.root = s.v and st.v = c.v and st.d = a.d + c.d where a.v <> s.v group by a.v", g)
    add("bfs_sql_geo_tree", lambda p: sql_search.recursive_depths(p.graph, p.source, 4), o.base("geo_tree", o.depth(4)) + "select v, depth::bigint as depth from depth", "geo_tree")
    add("bounded_search_purchase", lambda p: hybrid.bfs(p.graph, p.source, max_depth=2).result.select("v", "depth"), o.base("purchase", o.depth(2)) + "select v, depth::bigint as depth from depth", "purchase")


def _edges_per_step(p: Prepared, k: int) -> DataFrame:
    """Summary of raw edges per level over the sampled sources: the throughput summary with levels in place of seconds."""
    d = p.many(k)
    steps = d.groupBy("source").agg((F.max("depth") + 1).alias("seconds"))
    edges = p.graph.raw_edges.join(d.select("source", F.col("v").alias("src")), "src").groupBy("source").agg(F.count("*").alias("edges"))
    out = report.teps_summary(steps.join(edges, "source"))
    return out.select("runs", *[F.round(c, 6).alias(c) for c in out.columns if c != "runs"])


def _graph_layer() -> None:
    for g in ("kron12", "kron14", "uniform10", "shuffled10"):
        add(f"graph_stats_{g}", lambda p: p.graph.stats(), o.base(g) + """select (select count(*) from vert)::bigint as vertices, (select count(*) from deg)::bigint as non_isolated, (select count(*) from raw)::bigint as raw_edges,
(select count(*) from raw where src = dst)::bigint as loops, (select count(*) from edges)::bigint as simple_edges, (select coalesce(max(deg), 0) from deg)::bigint as max_degree""", g)
    for g in ("kron12", "kron14"):
        census = "select size::bigint as size, count(*)::bigint as n_components from (select coalesce(comp, v) as comp, count(*) as size from deg left join comp using (v) group by 1) group by 1"
        # the giant component is what the vertex of highest degree reaches; the few others are small
        comp = """hub as (select v from deg order by deg desc, v limit 1), giant(v, d) as (select v, 0 from hub union select a.dst, d + 1 from giant join arcs a on a.src = giant.v where d < 12), inside as materialized (select distinct v from giant),
linked(root, v) as (select v, v from deg where v not in (select v from inside) union select root, a.dst from linked join arcs a on a.src = linked.v), comp as materialized (select v, (select min(v) from inside) as comp from inside union all select v, min(root) from linked group by v)"""
        add(f"component_sizes_{g}", lambda p: consumers.components(p.graph).join(p.graph.degrees, "v").groupBy("comp").agg(F.count("*").alias("size")).groupBy("size").agg(F.count("*").alias("n_components")), o.base(g, comp) + census, g)
        add(f"isolated_share_{g}", lambda p: p.graph.stats().select((F.col("vertices") - F.col("non_isolated")).alias("isolated"), F.round((F.col("vertices") - F.col("non_isolated")) / F.col("vertices"), 6).alias("share")), o.base(g) + "select count(*)::bigint as isolated, round(count(*)::double / (select count(*) from vert), 6) as share from vert where v not in (select v from deg)", g)
    for g in ("kron10", "user_flow"):
        add(f"raw_degrees_{g}", lambda p: p.graph.raw_degrees(), o.base(g) + "select v, max(deg)::bigint as deg, count(*)::bigint as raw_deg from deg join (select src as v from raw union all select dst from raw) using (v) group by v", g)
    add("edge_share_supply", lambda p: build.edge_share(p.graph, 20).select("bucket", F.round("share", 6).alias("share")), o.base("supply") + "select bucket::bigint as bucket, round(sum(sum(deg)) over (order by bucket) / sum(sum(deg)) over ()::double, 6) as share from (select deg, (row_number() over (order by deg desc, v) - 1) * 20 // (select count(*) from deg) as bucket from deg) group by bucket", "supply")
    add("kron_edges_shuffled", lambda p: p.graph.raw.groupBy("src", "dst").agg(F.count("*").alias("n")), o.base("shuffled10") + "select src, dst, count(*)::bigint as n from raw group by 1, 2", "shuffled10")
    add("csr_dst_supply", lambda p: build.to_csr(p.graph)[1], o.base("supply") + "select (row_number() over (order by src, dst) - 1)::bigint as pos, dst as w from arcs", "supply")
    for order, expr in (("deg_asc", "d.deg, a.dst"), ("id", "a.dst")):
        add(f"top_neighbour_{order}_purchase", lambda p, x=order: build.split_top(build.adjacency(p.graph, x)).select("v", "deg", "top_nbr", F.size("rest").alias("rest")), o.base("purchase", o.LISTS.format(order=expr)) + "select src as v, max(deg)::bigint as deg, min(case when place = 0 then dst end) as top_nbr, (count(*) - 1)::bigint as rest from lists group by src", "purchase")


def _order_layer() -> None:
    add("degree_order_desc_supply", lambda p: lo.degree_order(p.graph, desc=True, isolated="drop").select("label", "v"), o.base("supply") + "select (row_number() over (order by deg desc, v) - 1)::bigint as label, v from deg", "supply")
    add("partial_order_visit_prefix_p25_kron10", lambda p: lo.partial_level_order(p.graph, 0.25, "visit_prefix", isolated="drop").select("label", "v"), o.base("kron10", o.order(True)) + "select label::bigint as label, v from (select (select count(*) from deg) - 1 - visit as label, v from visit where visit < ceil(0.25 * (select count(*) from deg)) union all select row_number() over (order by v) - 1, v from deg where v not in (select v from visit where visit < ceil(0.25 * (select count(*) from deg))))", "kron10")
    add("perm_inverse_kron10", lambda p: lo.perm_compose(p.perm("rlo"), lo.perm_invert(p.perm("rlo"))).select("label", "v"), o.base("kron10") + "select v as label, v from vert", "kron10")
    add("perm_compose_kron10", lambda p: lo.perm_compose(p.perm("natural"), p.perm("rlo")).select("label", "v"), o.base("kron10", o.order(True)) + "select p.label::bigint as label, n.v from (select row_number() over (order by v) - 1 as mid, v from vert) n join perm p on p.v = n.mid", "kron10")
    for g in ("returned_purchase", "kron_orders", "user_flow"):
        for kind, head in (("natural", o.base(g, o.NATURAL, o.LABELLED)), ("reordered", o.base(g, o.order(g in SINGLE), o.LABELLED))):
            key = "rlo" if kind == "reordered" else kind
            add(f"bandwidth_{kind}_{g}", lambda p, k=key: loc.bandwidth(p.labelled(k)), head + "select max(v - u)::bigint as bandwidth, (select sum(v - u) from (select v, min(u) as u from labelled group by v))::bigint as profile from labelled", g)


def _bitmap_layer() -> None:
    packed = lambda p, cond: blocks.pack_blocks(p.depths.where(cond))
    g = "page_anchor"
    head = o.base(g, o.depth())
    add(f"bitmap_or_{g}", lambda p: blocks.count_bits(blocks.or_blocks(packed(p, "depth <= 1"), packed(p, "depth = 2"))), head + "select (v // 512)::bigint as block, count(*)::bigint as bits from depth where depth <= 2 group by 1", g)
    add(f"bitmap_and_not_{g}", lambda p: blocks.to_rows(blocks.and_not_blocks(blocks.pack_blocks(p.graph.degrees), packed(p, "depth <= 2"))), head + "select v from deg where v not in (select v from depth where depth <= 2)", g)
    g = "kron10"
    head = o.base(g, o.depth())
    add(f"bitmap_members_{g}", lambda p: blocks.in_blocks(p.graph.edges.select(F.col("u").alias("v"), F.col("v").alias("w")), packed(p, "depth <= 2")).groupBy("v").agg(F.count("*").alias("n")), head + "select u as v, count(*)::bigint as n from edges where u in (select v from depth where depth <= 2) group by 1", g)


def _energy(p: Prepared) -> DataFrame:
    """Millions of raw edges per level of a search and per watt: levels stand for seconds, watts are an input."""
    levels = p.depths.agg((F.max("depth") + 1).alias("levels"))
    edges = work.teps_edges(p.graph, p.depths, p.source).select("source", "raw_edges")
    both = edges.join(F.broadcast(levels), how="cross")  # two single rows
    return both.select("source", "raw_edges", "levels", F.round(report.mteps_per_watt(F.col("raw_edges") / F.col("levels") / 1000000, WATTS), 9).alias("mteps_per_watt"))


def _report_layer() -> None:
    g = "returned_purchase"
    add(f"energy_{g}", _energy, o.base(g, o.depth()) + f"select source, raw_edges, levels, round(raw_edges / levels::double / 1000000 / {WATTS}::double, 9) as mteps_per_watt from (select {o.SOURCE}::bigint as source, (select count(*) from raw where src in (select v from depth))::bigint as raw_edges, (select max(depth) + 1 from depth)::bigint as levels)", g)
    rows = ", ".join(f"({n}, {a}::double, {b}::double)" for n, a, _, b, _ in SCALING)
    plain(
        "scaling_report_published",
        lambda spark, sf: report.scaling_report(spark.createDataFrame([(v, n, x) for n, a, _, b, _ in SCALING for v, x in (("plain", a), ("reordered", b))], "variant string, threads long, teps double")).select("variant", "threads", F.round("speedup", 4).alias("speedup"), F.round("efficiency", 4).alias("efficiency")),
        f"select variant, threads::bigint as threads, round(teps / base, 4) as speedup, round(teps / base / threads, 4) as efficiency from (select *, first_value(teps) over (partition by variant order by threads) as base from (select 'plain' as variant, n as threads, a as teps from (values {rows}) t(n, a, b) union all select 'reordered', n, b from (values {rows}) t(n, a, b)))",
    )
    cache = ", ".join("(" + ", ".join(f"{x}::double" if i else str(x) for i, x in enumerate(r)) + ")" for r in CACHE)
    speed = ", ".join("(" + ", ".join(f"{x}::double" if i else str(x) for i, x in enumerate(r)) + ")" for r in SCALING)
    plain("published_check", lambda spark, sf: report.published_check(spark), f"""with c as (select * from (values {cache}) t(k, r0, r1, rc, m0, m1, mc, p0, p1)), s as (select * from (values {speed}) t(n, g0, s0, g1, s1))
select 'references_cut' as "table", k::bigint as row, rc as printed, round(100 * (1 - r1 / r0), 4) as recomputed from c union all select 'misses_cut', k, mc, round(100 * (1 - m1 / m0), 4) from c union all select 'rate_before', k, p0, round(100 * m0 / r0, 4) from c
union all select 'rate_after', k, p1, round(100 * m1 / r1, 4) from c union all select 'speedup_plain', n, s0, round(g0 / (select g0 from s where n = 1), 4) from s union all select 'speedup_reordered', n, s1, round(g1 / (select g1 from s where n = 1), 4) from s""")


def register() -> None:
    _graph_layer()
    _order_layer()
    _balance_layer()
    _locality_layer()
    _ladder_layer()
    _source_layer()
    _bitmap_layer()
    _report_layer()
