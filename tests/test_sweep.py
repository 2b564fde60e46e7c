"""The worked example of the sweep, and agreement of all its forms."""

import pytest
from pyspark.sql import functions as F

from seedspread.operators import sweep
from seedspread.sources import generators


@pytest.fixture(scope="module")
def toy(spark):
    return generators.toy8(spark)


@pytest.fixture(scope="module")
def vector(spark):
    return spark.createDataFrame([(0, 0, 0.4), (0, 1, 0.4), (0, 2, 0.5), (0, 3, 0.3)], "run_id long, v long, p double")


def rows(profile):
    return [(r["rank"], r["v"], r["vol"], r["cut"], r["phi"]) for r in profile.orderBy("rank").collect()]


WANT = [(1, 0, 2, 2, 1.0), (2, 1, 4, 2, 0.5), (3, 2, 7, 1, 1 / 7), (4, 3, 11, 3, 0.6)]


@pytest.mark.parametrize("form", ["compact", "pairs", "large", "naive", "one_by_one"])
def test_worked_example(toy, vector, form):
    made = {
        "compact": lambda: sweep.sweep_profile(toy, vector), "pairs": lambda: sweep.sweep_profile(toy, vector, "pairs"), "large": lambda: sweep.sweep_profile(toy, vector, large=True),
        "naive": lambda: sweep.sweep_cut_naive(toy, vector), "one_by_one": lambda: sweep.sweep_cut_sequential(toy, vector),
    }[form]()
    assert rows(made) == WANT


def test_net_deltas_and_members(toy, vector):
    ranked = sweep.ranks(toy, vector)
    deltas = {r["rank"]: r["delta"] for r in sweep.edge_rank_pairs(toy, ranked).collect()}
    assert {k: v for k, v in deltas.items() if v} == {1: 2, 3: -1, 4: 2, 5: -3}
    cluster = sweep.sweep_cut(toy, vector)
    assert sorted(r["v"] for r in cluster.members().collect()) == [0, 1, 2]


def test_empty_and_whole_graph(toy, spark):
    none = spark.createDataFrame([], "run_id long, v long, p double")
    assert sweep.sweep_cut(toy, none).members().count() == 0
    everything = toy.degrees.select(F.lit(0).cast("long").alias("run_id"), "v", F.col("deg").cast("double").alias("p"))
    assert rows(sweep.sweep_profile(toy, everything))[-1][4] is None


def test_naive_prefixes_are_few_disjoint_blocks(spark):
    rows = spark.range(1, 101).select(F.lit(0).cast("long").alias("run_id"), F.col("id").alias("rank"), F.col("id").alias("x"))
    parts = sweep.blocks_of_prefixes(rows, 100)
    assert parts.groupBy("rank").count().agg(F.max("count")).first()[0] == 6  # 63 has six binary ones
    sums = parts.join(sweep.whole_blocks(rows, 100, "x"), ["run_id", "level", "block"]).groupBy("rank").agg(F.sum("x").alias("s"))
    assert {r["rank"]: r["s"] for r in sums.collect()} == {i: i * (i + 1) // 2 for i in range(1, 101)}


def test_naive_profile_of_several_runs(spark):
    graph = generators.torus3d(spark, 4)
    p = graph.degrees.select((F.col("v") % 3).alias("run_id"), "v", (F.col("v") % 11 + 1.0).alias("p"))
    key = lambda df: sorted(tuple(r) for r in df.select("run_id", "rank", "v", "vol", "cut", "phi").collect())
    assert key(sweep.sweep_cut_naive(graph, p)) == key(sweep.sweep_profile(graph, p))
    assert sweep.sweep_cut_naive(graph, p.filter("p < 0")).count() == 0
