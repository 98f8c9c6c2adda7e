import pytest
from pyspark.sql import functions as F
from tests import toy

from levelgraph.balance import ranges as rg
from levelgraph.bfs import hybrid
from levelgraph.bitmap import blocks
from levelgraph.graph import build
from levelgraph.measure import report, work
from levelgraph.plans.published import CACHE, COST, GTEPS, SCALING, WATTS
from levelgraph.reorder import level_order as lo
from levelgraph.reorder import locality as loc


def make(spark, edges, vertices):
    return build.Graph(spark.createDataFrame(edges, "src long, dst long"), spark.createDataFrame([(v,) for v in vertices], "v long"), "toy")


@pytest.fixture(scope="module")
def graph(spark):
    return make(spark, toy.EDGES, toy.VERTICES)


def pairs(df, a, b):
    return {r[a]: r[b] for r in df.collect()}


def test_stats(graph):
    assert graph.stats().first().asDict() == dict(vertices=10, non_isolated=8, raw_edges=10, loops=1, simple_edges=8, max_degree=4)


@pytest.mark.parametrize("cap", [0, 64])
def test_reverse_level_order(graph, cap):
    perm = lo.reverse_level_order(graph, small_cap=cap)
    assert [r["v"] for r in perm.orderBy("label").collect()] == [8, 4, 3, 7, 9, 2, 5, 1, 0, 6]
    assert lo.bijection_violations(perm, 10).isEmpty()
    edges = loc.labelled_edges(graph, perm)
    assert loc.bandwidth(edges).first()["bandwidth"] == 3
    natural = loc.labelled_edges(graph, lo.natural_order(graph, "drop"))
    assert loc.bandwidth(natural).first()["bandwidth"] == 5


def test_partial_limits(graph):
    whole, none = lo.partial_level_order(graph, 1.0), lo.partial_level_order(graph, 0.0)
    assert pairs(whole, "v", "label") == pairs(lo.reverse_level_order(graph), "v", "label")
    assert pairs(none, "v", "label") == pairs(lo.natural_order(graph, "append"), "v", "label")


def test_order_against_queue(spark):
    import random

    rng = random.Random(3)
    edges = [(rng.randrange(60), rng.randrange(60)) for _ in range(70)]
    g = make(spark, edges, range(60))
    order = toy.visit(edges)
    for cap in (0, 5):
        perm = lo.reverse_level_order(g, isolated="drop", small_cap=cap)
        assert [r["v"] for r in perm.orderBy(F.desc("label")).collect()] == order


def test_far_starts_against_queue(spark):
    # the leaf of least id hangs on the middle of a path, so the walk to a far end must move the start
    edges = [(v, v + 1) for v in range(10, 14)] + [(12, 1), (20, 21)]
    far = lo.reverse_level_order(make(spark, edges, range(22)), start="pseudo_peripheral", isolated="drop")
    assert [r["v"] for r in far.orderBy(F.desc("label")).collect()] == toy.visit(edges, toy.peripheral) != toy.visit(edges)


@pytest.mark.parametrize("options", [dict(mode="top_down"), dict(mode="bottom_up"), dict(mode="bottom_up", two_pass=False, trim=False), dict(mode="hybrid"), dict(mode="bottom_up", order="deg_asc")])
def test_search(graph, options):
    run = hybrid.bfs(graph, 1, block=1, **options)
    rows = {r["v"]: (r["parent"], r["depth"]) for r in run.result.collect()}
    assert rows == {1: (1, 0), 5: (1, 1), 2: (5, 2), 7: (5, 2), 9: (5, 2), 3: (7, 3)}, options
    inspected = [s["inspected_edges"] for s in run.steps]
    if options["mode"] == "top_down":
        assert inspected == [1, 4, 7, 2]
    elif options["mode"] == "bottom_up":
        assert inspected == ([12, 11, 3, 2] if options.get("order") == "deg_asc" else [15, 7, 3, 2])
    assert all(r["violations"] == 0 for r in hybrid.validate(graph, run.result, 1).collect())


def test_isolated_and_bounded_search(graph):
    assert [tuple(r) for r in hybrid.bfs(graph, 6).result.collect()] == [(6, 6, 0)]
    assert hybrid.bfs(graph, 1, max_depth=1).result.count() == 2
    assert pairs(hybrid.bfs_many(graph, [4]), "v", "depth") == {4: 0, 8: 1}


def test_closed_form_work(graph):
    d = hybrid.bfs(graph, 1).result.select("v", F.col("depth").cast("long").alias("depth"))
    assert pairs(work.inspected_bottom_up(graph, d), "step", "inspected_edges") == {0: 15, 1: 7, 2: 3, 3: 2}
    assert pairs(work.inspected_bottom_up(graph, d, "deg_asc"), "step", "inspected_edges") == {0: 12, 1: 11, 2: 3, 3: 2}


def test_csr(graph):
    offsets, dst = build.to_csr(graph)
    assert pairs(offsets, "v", "row_end")[9] == 16 and dst.count() == 16
    assert sorted(r["w"] for r in build.neighbors((offsets, dst), 5).collect()) == [1, 2, 7, 9]


def test_empty_graph(spark):
    g = make(spark, [], [1, 2])
    assert g.stats().first()["simple_edges"] == 0
    assert pairs(lo.reverse_level_order(g), "v", "label") == {1: 0, 2: 1}
    assert hybrid.bfs(g, 1).result.count() == 1


def test_ranges():
    assert rg.descending_cuts(10, 4) == [0, 4, 7, 9, 10]
    for kind in ("equal", "descending"):
        r = rg.label_ranges(10_001, 7, 8, kind)
        assert r[0][1] == 0 and r[-1][2] == 10_001 and all(a[2] == b[1] for a, b in zip(r, r[1:]))
    assert rg.simulate_pulling([4, 3, 2, 1], 2) == (5.0, 5.0)


def test_slices_cover(spark):
    frontier = spark.createDataFrame([(0, 4, 3, 5), (0, 9, 1, 5), (0, 2, 4, 5)], "step long, deg long, j long, n long")
    assert sum(r["edges"] for r in rg.sliced_slots(frontier, 3).collect()) == 15
    assert pairs(rg.sliced_slots(frontier.where("deg = 4"), 8), "slot", "edges") == {3: 4}


def test_blocks(spark):
    ids = [0, 63, 64, 511, 512, 1000]
    packed = blocks.pack_blocks(spark.createDataFrame([(i,) for i in ids], "v long"))
    assert sorted(r["v"] for r in blocks.to_rows(packed).collect()) == ids
    other = blocks.pack_blocks(spark.createDataFrame([(63,), (2000,)], "v long"))
    assert sorted(r["v"] for r in blocks.to_rows(blocks.or_blocks(packed, other)).collect()) == sorted([*ids, 2000])
    assert sorted(r["v"] for r in blocks.to_rows(blocks.and_not_blocks(packed, other)).collect()) == [0, 64, 511, 512, 1000]
    assert blocks.in_blocks(spark.range(70).withColumnRenamed("id", "v"), packed).count() == 3


def test_published_arithmetic(spark):
    for _, r0, r1, rc, m0, m1, mc, p0, p1 in CACHE:
        assert abs(100 * (1 - r1 / r0) - rc) <= 0.01 and abs(100 * (1 - m1 / m0) - mc) <= 0.01
        assert abs(100 * m0 / r0 - p0) <= 0.03 and abs(100 * m1 / r1 - p1) <= 0.03
    for _, g0, s0, g1, s1 in SCALING:
        assert abs(g0 / SCALING[0][1] - s0) <= 0.1 and abs(g1 / SCALING[0][3] - s1) <= 0.1
    assert [round(report.amortisation(*c)) for c in COST] == [1271, 772, 432]
    assert abs(report.mteps_per_watt(GTEPS * 1000, WATTS) - 326.48) < 0.02


def test_top_down_plan_does_not_shuffle_arcs(graph):
    level = graph.degrees.where("v = 1").select("v", F.lit(1).alias("parent"), F.lit(0).alias("depth"), "deg")
    plan = hybrid.top_down_step(graph.arcs, graph.degrees, level, level.limit(0), 1, 1)._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "SinglePartition" not in plan.split("LocalLimit")[0]


@pytest.mark.parametrize("seed", [1, 2])
def test_every_form_of_search_gives_the_same_rows(spark, seed, monkeypatch):
    """Joins, packed sets, split passes, chunked lists, executed slices and every range against a plain queue."""
    import random

    from levelgraph.bfs import kernels

    rng = random.Random(seed)
    edges = [(int(rng.random() ** 3 * 90), rng.randrange(90)) for _ in range(220)]
    g = make(spark, edges, range(95))
    source = edges[0][0] if edges[0][0] != edges[0][1] else edges[1][0]
    want = toy.depths(edges, source)
    first = None
    forms = [dict(vectorized=False), dict(vectorized=True, block=64, lam=1), dict(vectorized=True, mode="bottom_up", block=1, lam=2), dict(vectorized=True, mode="top_down", trim=False), dict(vectorized=True, two_pass=False, ranges="equal", block=64), dict(phase_plan=("sliced", "full", "static")), dict(phase_plan=("static", "plain", "sliced")), dict(order="id")]
    for options in forms:
        run = hybrid.bfs(g, source, workers=3, **options)
        rows = sorted(map(tuple, run.result.collect()))
        first = first or rows
        assert rows == first and {v: d for v, _, d in rows} == want, options
    monkeypatch.setattr(kernels, "SPLIT_BYTES", 0)
    split = hybrid.bfs(g, source, mode="bottom_up")
    assert sorted(map(tuple, split.result.collect())) == first
    whole = hybrid.bfs(g, source, mode="bottom_up", vectorized=False)
    counts = lambda run: [(s["inspected_edges"], s["discovered"], s["top_hits"]) for s in run.steps]
    assert counts(split) == counts(whole)
    fresh = make(spark, edges, range(95))
    monkeypatch.setattr(kernels, "MAX_LIST", 4)
    lists, cuts = kernels.range_lists(fresh, fresh.totals["top"] + 1, 4, 16, "descending", 4)
    assert lists.groupBy("v").count().agg(F.max("count")).first()[0] > 1
    sc = spark.sparkContext
    seen, now = ~fresh.packed(128), fresh.packed(128)
    found = kernels.least_place(kernels.bottom_up(lists, sc.broadcast(seen & ~now), sc.broadcast(now), 4))
    assert found.where("place <> 0").isEmpty() and found.count() == fresh.totals["n"]


def test_packed_words():
    import numpy as np

    from levelgraph.bitmap import words as bw

    rng = np.random.default_rng(0)
    a, b = (np.unique(rng.integers(0, 3000, n)) for n in (200, 900))
    x, y = bw.pack(a, 3000), bw.pack(b, 3000)
    assert bw.unpack(x).tolist() == a.tolist() and bw.count(y) == len(b)
    assert (bw.merge(x, y) == bw.merge_one_by_one(x, y)).all() and bw.unpack(bw.merge(x, y)).tolist() == sorted({*a, *b})
    assert bw.holds(x, np.arange(3000)).nonzero()[0].tolist() == a.tolist()
    for block in (1, 64, 512):
        ranges = rg.label_ranges(3000, 7, block)
        want = [(rid, min(free), max(free)) for rid, lo, hi in ranges if (free := [v for v in range(lo, hi) if v not in set(b.tolist())])]
        assert bw.live_stretches(y, ranges) == want
        if block == 512:  # a line of the sets belongs to one range
            assert all(lo % 512 == 0 for _, lo, _ in ranges)


def test_rank_and_order_variants(spark):
    import random

    rng = random.Random(9)
    edges = [(rng.randrange(40), rng.randrange(40)) for _ in range(60)]
    g = make(spark, edges, range(42))
    for select in ("degree_asc", "visit_prefix"):
        whole = lo.partial_level_order(g, 1.0, select)
        assert pairs(whole, "v", "label") == pairs(lo.reverse_level_order(g), "v", "label")
        assert lo.bijection_violations(lo.partial_level_order(g, 0.4, select), 42).isEmpty()
    perm = lo.reverse_level_order(g)
    assert all(k == v for k, v in pairs(lo.perm_compose(perm, lo.perm_invert(perm)), "v", "label").items())
    peripheral = lo.reverse_level_order(g, start="pseudo_peripheral")
    assert lo.bijection_violations(peripheral, 42).isEmpty()


def test_lru_against_a_replay(spark):
    import random
    from collections import OrderedDict

    rng = random.Random(4)
    lines = [int(rng.random() ** 2 * 12) for _ in range(500)]
    trace = spark.createDataFrame([(k // 7, k % 7, line) for k, line in enumerate(lines)], "v long, i long, line long")
    for capacity in (1, 3, 8):
        cache, misses = OrderedDict(), 0
        for line in lines:
            misses += line not in cache
            cache.pop(line, None)
            cache[line] = 1
            if len(cache) > capacity:
                cache.popitem(last=False)
        assert tuple(work.line_misses(trace, capacity).first()) == (500, misses)
    assert work.line_switches(trace).first()["switches"] == work.line_misses(trace, 1).first()["misses"]
