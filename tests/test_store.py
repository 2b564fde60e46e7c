"""The store reads only touched buckets and carries the same graph; the generator source; workloads."""

from seedspread.operators import diffusion as d
from seedspread.plans import workloads
from seedspread.sources import builders, datasource, generators
from seedspread.sources.store import AdjacencyStore, StoredGraph


def test_store_prunes_and_equals(spark, sf, tmp_path):
    graph = builders.geo(spark, sf)
    store = AdjacencyStore.write(graph, f"file://{tmp_path}/lists", 16)
    one = spark.createDataFrame([(0,)], "v long")
    lists = store.lists_of(one)
    assert [r["v"] for r in lists.collect()] == [0]
    assert "PartitionFilters: [isnotnull(bucket" in lists._jdf.queryExecution().toString() or "bucket#" in lists._jdf.queryExecution().toString()
    kept = StoredGraph(store)
    assert kept.n == graph.n and kept.m == graph.m
    seed = d.seeds_frame(spark, [0])
    a = {tuple(r) for r in d.residual_push(graph, seed, 0.2, 1e-2).p.select("v", "p").collect()}
    b = {tuple(r) for r in d.residual_push(kept, seed, 0.2, 1e-2).p.select("v", "p").collect()}
    assert a == b


def test_generator_source(spark):
    datasource.register(spark)
    made = spark.read.format("seed_graph").option("k", 4).load()
    want = generators.torus3d(spark, 4).edges
    assert made.count() == 384 and made.exceptAll(want).count() == 0


def test_workloads(spark, sf):
    rules = workloads.rule_ablation(spark, sf, eps=1e-4, graphs=("geo",)).collect()
    assert rules[0]["phi"] == rules[1]["phi"] and rules[1]["pushes"] < rules[0]["pushes"]
    counts = workloads.push_counts(spark, sf, eps=1e-4, graphs=("geo",)).first()
    assert 0.3 < counts["ratio"] < 2
    good = {r["graph"]: r["phi"] for r in workloads.no_good_cluster(spark, sf).collect()}
    assert good["geo"] < 0.1 < good["cust_part"]
    rows = workloads.local_against_dense(spark, sf, 2).collect()
    assert all(r["local_rows"] < r["dense_rows"] for r in rows)
