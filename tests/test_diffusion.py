"""Invariants, work bounds, equality of bulk, DataFrame and one-by-one forms, and exact vectors."""

import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from seedspread.operators import diffusion as d
from seedspread.operators import graph, kernels, measures, profile
from seedspread.plans import planner
from seedspread.sources import builders, generators
from seedspread.streaming import streams


@pytest.fixture(scope="module")
def geo(spark, sf):
    return builders.geo(spark, sf).persist()


@pytest.fixture(scope="module")
def seed(spark):
    return d.seeds_frame(spark, [0, 4])


def vector(out):
    return {(r["run_id"], r["v"]): r["p"] for r in out.p.collect()}


def same(a, b, tol=1e-12):
    a, b = vector(a), vector(b)
    assert a.keys() == b.keys()
    assert max(abs(a[k] - b[k]) for k in a) < tol


@pytest.mark.parametrize("rule", ["lazy", "aggressive"])
def test_push_invariants(geo, seed, rule):
    alpha, eps = 0.1, 1e-4
    out = d.residual_push(geo, seed, alpha, eps, rule)
    totals = {r["run_id"]: r["mass"] for r in out.mass().collect()}
    left = {r["run_id"]: r["s"] for r in out.r.groupBy("run_id").agg({"r": "sum"}).withColumnRenamed("sum(r)", "s").collect()}
    for run, mass in totals.items():
        assert abs(mass + left[run] - 1) < 1e-9
    assert all(r["peak"] < eps for r in measures.residual_peak(out.r).collect())
    assert all(r["edges"] <= planner.work_bound("push", alpha=alpha, eps=eps) for r in measures.push_counters(out.stats).collect())


def test_push_frames_equal_in_task(geo, seed):
    same(d.residual_push(geo, seed, 0.2, 1e-2, mode="frames"), d.residual_push(geo, seed, 0.2, 1e-2, mode="in_task"))


def test_rules_share_the_exact_vector(geo, seed):
    exact = d.pagerank_exact(geo, seed, 0.2, 1e-13)
    for rule in ("lazy", "aggressive"):
        out = d.residual_push(geo, seed, 0.2, 1e-10, rule)
        assert all(r["worst"] < 1e-8 for r in measures.vector_error(geo, out.p, exact.p).collect())
    near = d.residual_push(geo, seed, 0.2, 1e-4)
    assert all(r["worst"] <= 1e-4 for r in measures.vector_error(geo, near.p, exact.p).collect())


def test_queue_forms_and_inflation(geo, seed):
    bulk = d.residual_push(geo, seed, 0.1, 1e-4)
    fifo, heap = d.residual_push_fifo(geo, seed, 0.1, 1e-4), d.residual_push_priority(geo, seed, 0.1, 1e-4)
    for one in (fifo, heap):
        assert all(r["worst"] <= 2e-4 for r in measures.vector_error(geo, bulk.p, one.p).collect())
    assert all(r["ratio"] < 3 for r in measures.push_inflation(bulk.stats, fifo.stats).collect())


def test_beta_and_blocks_keep_mass(geo, seed):
    for out in (d.residual_push(geo, seed, 0.1, 1e-3, beta=0.3), d.residual_push(geo, seed, 0.1, 1e-3, blocks=3)):
        assert all(r["peak"] < 1e-3 for r in measures.residual_peak(out.r).collect())


def test_walk_forms(geo, seed):
    bulk = d.truncated_walk(geo, seed, 6, 1e-4)
    same(bulk, d.truncated_walk(geo, seed, 6, 1e-4, mode="frames"))
    same(bulk, d.truncated_walk_sequential(geo, seed, 6, 1e-4))
    assert all(abs(r["mass"] - 1) < 1e-9 for r in d.lazy_walk_exact(geo, seed, 4).mass().collect())


def test_walk_returns_vector_before_the_empty_one(spark):
    star = generators.star(spark, 50)
    out = d.truncated_walk(star, d.seeds_frame(spark, [0]), 20, 0.2)
    assert vector(out) == {(0, 0): 1.0}


def test_heat_forms(geo, seed):
    bulk = d.heat_taylor(geo, seed, 3, 8, 1e-3)
    same(bulk, d.heat_taylor(geo, seed, 3, 8, 1e-3, mode="frames"), 1e-10)
    same(bulk, d.heat_taylor_queue(geo, seed, 3, 8, 1e-3), 1e-10)
    exact = d.heat_exact(geo, seed, 3, 30)
    assert all(abs(r["mass"] - math.exp(3)) < 1e-6 for r in exact.mass().collect())
    close = d.heat_taylor(geo, seed, 3, 20, 1e-4, last_level="taylor")
    assert all(r["worst"] * math.exp(-3) < 1e-4 for r in measures.vector_error(geo, close.p, exact.p).collect())


def test_heat_walks(geo, spark):
    one = d.seeds_frame(spark, [0])
    hashed = d.heat_walks(geo, one, 2, 6, 4000)
    same(hashed, d.heat_walks(geo, one, 2, 6, 4000, aggregate="sort"))
    assert abs(hashed.mass().first()["mass"] - 1) < 1e-9
    exact = {k[1]: v for k, v in vector(d.heat_exact(geo, one, 2, 6)).items()}
    share = {k[1]: v for k, v in vector(d.heat_walks_grouped(geo, one, 2, 6, 4000)).items()}
    cut = sum(exact.values())
    assert abs(share.get(0, 0) - exact[0] / cut) < 0.05


def test_walk_starts_follow_weights(geo, spark):
    """All three forms: weighted seeds, a seed outside the graph, a stream per run, and 4 sigma around the exact vector."""
    n, weights = 8000, [(0, 0, 0.9), (0, 4, 0.1), (0, 999_999, 5.0), (1, 0, 0.9), (1, 4, 0.1)]
    seeds = spark.createDataFrame(weights, "run_id long, v long, w double")
    still = {k: v for k, v in vector(d.heat_walks(geo, seeds, 0.0, 3, n)).items()}
    assert still.keys() == {(0, 0), (0, 4), (1, 0), (1, 4)} and abs(still[0, 4] - 0.1) < 4 * (0.09 / n) ** 0.5
    exact = vector(d.heat_exact(geo, seeds.filter("run_id = 1"), 2, 12))
    total = sum(exact.values())
    for form in (d.heat_walks, d.heat_walks_grouped, d.heat_walks_sequential):
        out = form(geo, seeds, 2, 12, n)
        assert all(abs(r["mass"] - 1) < 1e-9 for r in out.mass().collect())
        got = vector(out)
        assert {k[1]: v for k, v in got.items() if k[0] == 0} != {k[1]: v for k, v in got.items() if k[0] == 1}
        for (_, v), x in exact.items():
            want = x / total
            assert abs(got.get((1, v), 0.0) - want) < 4 * (want * (1 - want) / n) ** 0.5 + 2e-3


def test_ball_over_the_limit_goes_in_rounds(spark, monkeypatch):
    path = graph.Graph.from_edges(spark.createDataFrame([(k, k + 1) for k in range(60)], "src long, dst long"))
    seed = d.seeds_frame(spark, [30])
    forms = (lambda mode: d.residual_push(path, seed, 0.1, 1e-3, mode=mode), lambda mode: d.truncated_walk(path, seed, 8, 1e-5, mode=mode), lambda mode: d.heat_taylor(path, seed, 2, 8, 1e-5, mode=mode))
    want = [vector(f("in_task")) for f in forms]
    monkeypatch.setattr(planner, "IN_TASK_EDGES", 20)
    for form, exact in zip(forms, want, strict=True):
        got = vector(form("in_task"))
        assert got.keys() == exact.keys() and max(abs(got[k] - exact[k]) for k in got) < 1e-12
    with pytest.raises(d.TooLarge):
        d.residual_push_fifo(path, seed, 0.1, 1e-3)
    inside, cut = d.ball(path, seed, 50, 20)
    assert cut and inside.join(path.degrees, "v").agg({"deg": "sum"}).first()[0] <= 20
    monkeypatch.setattr(planner, "IN_TASK_EDGES", 60)
    assert vector(d.truncated_walk(path, seed, 4, 1e-3, mode="in_task")).keys() == {(0, v) for v in range(26, 35)}


def test_edge_upkeep_survives_a_replay(spark):
    rows = lambda users: spark.createDataFrame([(u, k * 3600) for u, k in users], "user_id long, s long").selectExpr("user_id", "timestamp_seconds(s) as ts")
    one, two = rows([(1, 5), (2, 5)]), rows([(2, 5), (3, 6)])
    kept = streams.EdgeUpkeep(spark)
    assert kept.edges().count() == 0
    kept.apply(one, 0)
    kept.apply(one, 0)
    kept.apply(two, 1)
    streams.EdgeUpkeep(spark, kept.path).apply(two, 1)
    assert {tuple(r) for r in kept.edges().collect()} == {(2, 11), (4, 11), (6, 13)}


def test_unknown_seed_and_empty_graph(geo, spark):
    lost = d.seeds_frame(spark, [999_999_999])
    assert d.residual_push(geo, lost, 0.1, 1e-3).p.count() == 0
    assert d.truncated_walk(geo, lost, 3, 1e-3, mode="frames").p.count() == 0


def test_planted_block_is_found(spark):
    g = generators.planted(spark, 4, 30, 0.5, 0.01)
    cluster = profile.local_cluster(g, d.seeds_frame(spark, [3]), "push", alpha=0.05, eps=1e-5)
    found = {r["v"] for r in cluster.members().collect()}
    truth = set(range(30))
    assert 2 * len(found & truth) / (len(found) + 30) >= 0.9


@settings(max_examples=25, deadline=None)
@given(st.integers(0, 10_000), st.floats(0.02, 0.5), st.sampled_from([1e-2, 1e-3]))
def test_push_on_random_graphs(salt, alpha, eps):
    rng = np.random.default_rng(salt)
    pairs = {(min(a, b), max(a, b)) for a, b in rng.integers(0, 25, (60, 2)) if a != b}
    src = np.array([a for a, b in pairs] + [b for a, b in pairs])
    dst = np.array([b for a, b in pairs] + [a for a, b in pairs])
    deg = np.bincount(src, minlength=25)
    ball = kernels.Ball.of(src, dst, deg[src], deg[dst])
    seeds = [(int(ball.ids[0]), 1.0)]
    for rule in ("lazy", "aggressive"):
        out = kernels.push_bulk(ball, seeds, alpha, eps, rule)
        assert abs(out.p.sum() + out.r.sum() - 1) < 1e-9
        assert (out.r < eps * ball.deg).all() and (out.r >= 0).all()
        assert sum(x[1] for x in out.rounds) <= 1 / (alpha * eps) + deg.max()


def test_psi_and_degree():
    assert kernels.psi(3, 2.0)[0] == pytest.approx(1 + 2 + 2 + 8 / 6)
    assert planner.default_degree(10, 1e-7) == math.ceil(20 * math.log(1e7))
