"""Construction, components, scans, the registry without the text subpackage."""

import subprocess
import sys

from pyspark.sql import functions as F

from seedspread.operators.components import connected_components
from seedspread.operators.frontier import prefix_sum
from seedspread.operators.graph import Graph, graph_stats, relabel
from seedspread.sources import builders, generators


def test_normalised_edges(spark):
    g = Graph.from_edges(spark.createDataFrame([(1, 2), (2, 1), (3, 3), (None, 4), (2, 5)], "src long, dst long"))
    assert sorted(map(tuple, g.edges.collect())) == [(1, 2), (2, 1), (2, 5), (5, 2)]
    assert g.n == 3 and g.m == 2


def test_torus_and_generators(spark):
    row = graph_stats(generators.torus3d(spark, 4)).first()
    assert (row["n"], row["m"], row["min_deg"], row["max_deg"]) == (64, 192, 6, 6)
    assert graph_stats(generators.clique(spark, 5)).first()["m"] == 10
    assert graph_stats(generators.barbell(spark, 4)).first()["m"] == 13
    assert graph_stats(generators.path(spark, 5)).first()["m"] == 4


def test_known_counts(spark, sf):
    row = graph_stats(builders.geo(spark, sf)).first()
    assert (row["n"], row["m"]) == (190, 185)
    row = graph_stats(builders.user_hour(spark, sf)).first()
    assert (row["n"], row["m"]) == (546, 951)


def test_chunked_lists_cover_hubs(spark, monkeypatch):
    from seedspread.operators import graph as module

    monkeypatch.setattr(module, "CHUNK", 10)
    g = generators.star(spark, 101)
    chunks = g.adjacency.filter("v = 0").collect()
    assert len(chunks) > 3 and sum(len(c["nbrs"]) for c in chunks) == 100


def test_components(spark):
    edges = spark.createDataFrame([(1, 2), (2, 3), (9, 8), (5, 5), (None, 3), (8, 7), (3, 1)], "a long, b long")
    assert {tuple(r) for r in connected_components(edges).collect()} == {(1, 1), (2, 1), (3, 1), (7, 7), (8, 7), (9, 7)}
    assert connected_components(edges.filter("a = 5")).count() == 0
    chain = spark.range(60).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b"))
    assert connected_components(chain).filter("component <> 0").count() == 0
    shared = connected_components(chain.union(edges.filter("a > 5").selectExpr("a + 100", "b + 100")), finish_edges=0)
    assert shared.filter("v <= 60 and component <> 0").count() == 0 and shared.count() == 64


def test_two_pass_scan_and_relabel(spark):
    df = spark.range(100).select(F.col("id").alias("k"), (F.col("id") % 7).alias("x"))
    got = {r["k"]: r["s"] for r in prefix_sum(df, ["k"], "x", "s").collect()}
    total = 0
    for k in range(100):
        total += k % 7
        assert got[k] == total
    low = {r["k"]: r["s"] for r in prefix_sum(df.withColumn("x", F.col("k") % 7 + 3), ["k"], "x", "s", op="min").collect()}
    assert low[50] == 3
    ids = sorted(r["id"] for r in relabel(df.withColumn("name", F.concat(F.lit("n"), "k")), "name").collect())
    assert ids == list(range(100))


def test_registry_imports_without_llm():
    code = "import sys; sys.modules['seedspread.llm'] = None; import __spark_entry__ as e; q = e.queries(); assert 'local_cluster_geo' in q and not any(k.startswith('op') for k in q), sorted(q)[:5]; assert set(e.oracle_sql()) <= set(q)"
    done = subprocess.run([sys.executable, "-c", code], capture_output=True, text=True, cwd=__file__.rsplit("/tests/", 1)[0])
    assert done.returncode == 0, done.stderr[-800:]
