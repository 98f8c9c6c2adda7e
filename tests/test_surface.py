import duckdb
import pandas as pd
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from levelgraph.apps import consumers
from levelgraph.functions.register import register
from levelgraph.graph import build
from levelgraph.graph.kronecker import kronecker
from levelgraph.plans.switch import StepState, choose
from levelgraph.sources import io
from levelgraph.streaming import edges as stream

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_entry(spark):
    out = entry.entry(spark)
    assert out.columns == ["v", "parent", "depth"] and out.count() > 0


@pytest.mark.parametrize("name", ["graph_stats_user_flow", "degree_histogram_bulk_returns", "kron_quadrants", "op_as_of_join", "op_interval_join", "op_pivot", "amortisation", "ranges_descending"])
def test_queries_match_their_oracles(spark, tiny, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{tiny}/{t}.parquet'")
    want = con.sql(entry.oracle_sql()[name]).df()
    got = entry.queries()[name](spark, tiny).toPandas()
    assert sorted(got.columns) == sorted(want.columns)
    def plain(df):
        return sorted(str([None if pd.isna(x) else x if isinstance(x, str) else round(float(x), 6) for x in r]) for r in df[sorted(df.columns)].itertuples(index=False))

    assert plain(got) == plain(want)


def test_switch():
    s = lambda **k: StepState(**(dict(frontier_vertices=10, frontier_edges=100, unexplored_edges=1000, previous_vertices=1, vertices=1000) | k))
    assert choose("top_down", False, s()) == "bottom_up"
    assert choose("top_down", True, s()) == "top_down" and choose("top_down", True, s(), guard=False) == "bottom_up"
    assert choose("top_down", False, s(previous_vertices=20)) == "top_down"
    assert choose("bottom_up", False, s()) == "top_down" and choose("bottom_up", False, s(frontier_vertices=500)) == "bottom_up"


def test_generator_source_equals_expressions(spark):
    spark.dataSource.register(io.KroneckerSource)
    a = spark.read.format("kronecker").options(scale=6, parts=3).load()
    b = kronecker(spark, 6).raw
    assert sorted(map(tuple, a.collect())) == sorted(map(tuple, b.collect()))


def test_store_and_read(spark, tmp_path):
    g = kronecker(spark, 5)
    io.write_graph(g, f"{tmp_path}/g", 4)
    back = io.read_graph(spark, f"{tmp_path}/g")
    assert sorted(map(tuple, back.arcs.collect())) == sorted(map(tuple, g.arcs.collect()))
    (tmp_path / "e.txt").write_text("# comment\n1 2\n2\t3\n\n% more\n3,1\n")
    assert sorted(map(tuple, io.read_edge_list(spark, f"{tmp_path}/e.txt").collect())) == [(1, 2), (2, 3), (3, 1)]


def test_sql_functions(spark):
    register(spark)
    assert [tuple(r) for r in spark.sql("select * from descending_ranges(10, 4, 1) order by rid").collect()] == [(0, 0, 4), (1, 4, 7), (2, 7, 9), (3, 9, 10)]
    assert spark.sql("select sum(edges) from slice_slots(13, 2, 4)").first()[0] == 13
    assert spark.sql("select block_of(1025), static_slot(5, 10, 4)").first() == (2, 2)


def test_applications(spark):
    raw = spark.createDataFrame([(1, 2), (2, 3), (3, 4), (4, 1), (3, 5), (7, 8)], "src long, dst long")
    g = build.Graph(raw, spark.createDataFrame([(v,) for v in (1, 2, 3, 4, 5, 7, 8, 9)], "v long"), "app")
    assert {r["v"]: r["comp"] for r in consumers.components(g).collect()} == {1: 1, 2: 1, 3: 1, 4: 1, 5: 1, 7: 7, 8: 7, 9: 9}
    assert [r["v"] for r in consumers.shortest_path(g, 1, 5).orderBy("hop").collect()][-1] == 5 and consumers.shortest_path(g, 1, 8).count() == 0
    assert consumers.spanning_forest(g).where("v <> parent").count() == 5
    assert consumers.bipartite_conflicts(g).isEmpty()
    assert {r["v"]: r["betweenness"] for r in consumers.betweenness(g, [1]).collect()} == {2: 1.0, 3: 1.0, 4: 1.0, 5: 0.0}


def test_stream_equals_batch(spark, tiny, tmp_path):
    events = stream.event_stream(spark, tiny)
    edges = stream.user_type_edges(events)
    q = stream.windowed_counts(edges).writeStream.format("memory").queryName("w").outputMode("complete").trigger(availableNow=True).start()
    q.awaitTermination()
    batch = stream.windowed_counts(stream.user_type_edges(spark.read.parquet(f"{tiny}/events.parquet")))
    assert sorted(map(tuple, spark.table("w").select("start", "edges").collect())) == sorted(map(tuple, batch.select("start", "edges").collect()))
    q = stream.running_degrees(edges.select("src", "dst")).writeStream.format("memory").queryName("d").outputMode("update").trigger(availableNow=True).start()
    q.awaitTermination()
    last = spark.table("d").groupBy("v").agg(F.max("deg").alias("deg"))
    want = spark.read.parquet(f"{tiny}/events.parquet").groupBy((F.col("user_id") * 2).alias("v")).count()
    assert sorted(map(tuple, last.collect())) == sorted(map(tuple, want.collect()))
    seen = []
    folder = f"{tmp_path}/s"
    run = stream.refresh_search(0, lambda df, n: seen.append(df.count()), folder)
    run(spark.createDataFrame([(0, 1), (1, 2)], "src long, dst long"), 0)
    run(spark.createDataFrame([(2, 3)], "src long, dst long"), 1)
    assert seen == [3, 4]
