import math

import pytest
from pyspark.sql import functions as F

from plate_engine.mpg import graph as G


@pytest.fixture(scope="module")
def graph(spark):
    rows = [(u, 100 * u + k) for u in range(40) for k in range(10 + u % 7)]
    return G.MessageGraph.of(spark.createDataFrame(rows, "user long, event long"), "user", ["event"], 8)


def test_ids_and_siblings(spark, graph):
    n = graph.ids["x"].size
    assert graph.ids["z"].lo == n and graph.ids["phi"].hi == 2 * n + 40 + 8 - 1
    back = G.id_to_rv(graph.vertices().withColumnRenamed("rv", "told"), "vid", graph.ids)
    assert back.filter("rv <> told").count() == 0 and back.count() == 2 * n + 48
    assert graph.edges().count() == n * (8 + 2)


@pytest.mark.parametrize("m", [4, 16])
def test_partitions_keep_the_promises(spark, graph, m):
    n = graph.ids["x"].size
    edges = graph.edges().persist()
    for s in G.STRATEGIES:
        pids = G.partition_ids(edges, graph.ids, s, m)
        lo, hi = pids.agg(F.min("pid"), F.max("pid")).first()
        assert lo >= 0 and hi < m
        x = G.replicas(pids).filter(F.col("vid") <= graph.ids["x"].hi).agg(F.avg("n")).first()[0]
        largest = G.partition_loads(pids).agg(F.max("n")).first()[0]
        if s == "tailored":
            assert x == 1.0 and largest <= 3 * math.ceil(n / m) + 8
        if s in ("rvc", "crvc"):
            assert abs(x / G.expected_replicas(s, m, 8) - 1) < 0.06


def test_placement_is_physical(spark, graph):
    edges = G.placed(G.partition_ids(graph.edges(), graph.ids, "tailored", 4), 4)
    assert edges.withColumn("p", F.spark_partition_id()).filter("p <> pid").count() == 0


def test_canonical_cut_puts_both_directions_together(spark, graph):
    e = graph.edges()
    back = e.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "etype", "root")
    both = G.partition_ids(e.union(back), graph.ids, "crvc", 16).groupBy(F.least("src", "dst"), F.greatest("src", "dst")).agg(F.count_distinct("pid").alias("n"))
    assert both.agg(F.max("n")).first()[0] == 1


def test_formulas():
    assert abs(G.expected_replicas("rvc", 16, 8) - 7.05) < 0.01
    assert abs(G.expected_replicas("2d", 16, 8) - 3.70) < 0.01
    assert G.largest_partition_bound("tailored", 1000, 16, 8) == 3 * 63 + 8


def test_changed_vertices_alone_starve_a_round(graph):
    got = {r["etype"]: (r["needed"], r["starved"]) for r in G.starved_messages(graph).collect()}
    assert got["z-x"][0] == got["z-x"][1] > 0
    assert got["phi-x"][1] == got["phi-x"][0] // 2


def test_a_pregel_round_of_changed_vertices_stalls(spark, graph):
    n = graph.ids["x"].size
    (stalled,) = G.pregel_run(graph)
    # Every x hears from the components, none from its z, so nothing can update.
    assert stalled == {"sent": 8, "reached": n, "ready": 0}
    all_ready = G.pregel_round(graph.edges(), graph.vertices().select("vid"))
    assert all_ready.filter("not ready").count() == 0 and all_ready.count() == graph.vertices().count()
    assert all_ready.agg(F.sum("needed")).first()[0] == 2 * graph.edges().count()


def test_oriented_edges_are_runs_of_the_receiver(spark, graph):
    edges = G.orient_edges(graph.edges(), 4)
    placed = edges.withColumn("p", F.spark_partition_id())
    assert placed.groupBy("dst").agg(F.count_distinct("p").alias("n")).filter("n > 1").count() == 0
    assert edges.exceptAll(graph.edges()).count() == 0 and edges.count() == graph.edges().count()
    for part in edges.select("dst").rdd.glom().collect():
        assert [r["dst"] for r in part] == sorted(r["dst"] for r in part)


def test_tables_of_replicas_are_of_given_rows(spark):
    """Both tables change with the rows that they are about, and equal the formulas of single values."""
    from plate_engine.queries import methods

    seen = []
    for sf in ("/root/testdata/sf0.001", "/root/testdata/sf0.01"):
        rows = methods.expected_replicas_table(spark, sf).collect()
        assert all(abs(r["replicas"] - G.expected_replicas(r["strategy"], r["m"], r["k"])) < 1e-6 for r in rows)
        orders = sum(r["orders"] for r in rows if r["strategy"] == "1d" and r["m"] == 4)
        assert orders == spark.read.parquet(f"{sf}/lineitem.parquet").select("l_orderkey").distinct().count()
        found = methods.asymptotic_table(spark, sf).collect()
        n = spark.read.parquet(f"{sf}/events.parquet").count()
        assert len(found) == 2 * len(G.ASYMPTOTIC) and {r["n"] for r in found} == {n}
        for r in found:
            k = 8 if r["k"] == "O(1)" else r["m"]
            assert abs(r["expected"] - G.expected_replicas(r["strategy"], r["m"], k)) < 1e-6
            assert abs(r["bound"] - G.largest_partition_bound(r["strategy"], n, r["m"], k)) < 1e-3
        seen.append((orders, n))
    assert seen[0] != seen[1]
