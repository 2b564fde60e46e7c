"""Whole tasks around the methods: one cluster, comparisons, peeling, grids of runs, community profiles, seeds."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seedspread.operators import diffusion as d
from seedspread.operators.components import connected_components
from seedspread.operators.graph import Graph
from seedspread.operators.sweep import Cluster, best_prefix, sweep_cut, sweep_profile
from seedspread.runtime import materialize

METHODS: dict[str, Callable] = {"walk": d.truncated_walk, "push": d.residual_push, "heat": d.heat_taylor, "heat_walks": d.heat_walks}


def local_cluster(graph: Graph, seeds: DataFrame, method: str = "push", **params) -> Cluster:
    """Spread from the seeds, then sweep."""
    return sweep_cut(graph, METHODS[method](graph, seeds, **params).p)


def compare_methods(graph: Graph, seeds: DataFrame, specs: dict[str, tuple[str, dict]]) -> DataFrame:
    """``(name, run_id, size, vol, cut, phi)`` of several methods from the same seeds."""
    out = None
    for name, (method, params) in specs.items():
        one = local_cluster(graph, seeds, method, **params).summary().select(F.lit(name).alias("name"), "*")
        out = one if out is None else out.union(one)
    return out


def peel(graph: Graph, pick_seed: Callable[[Graph], int | None], rounds: int, method: str = "push", **params) -> DataFrame:
    """``(round, v)``: find a cluster, remove it, repeat on what is left."""
    found = None
    for k in range(rounds):
        seed = pick_seed(graph)
        if seed is None:
            break
        members = materialize(local_cluster(graph, d.seeds_frame(graph.spark, [seed]), method, **params).members(), "peel")
        if members.isEmpty():
            break
        one = members.select(F.lit(k).alias("round"), "v")
        found = one if found is None else found.union(one)
        graph = Graph(materialize(graph.subtract(members).edges, "peel"))
    return found if found is not None else graph.spark.createDataFrame([], "round int, v long")


class Session:
    """A resident graph for many queries."""

    def __init__(self, graph: Graph):
        self.graph = graph.persist()

    def query(self, seeds: list[int], method: str = "push", **params) -> Cluster:
        return local_cluster(self.graph, d.seeds_frame(self.graph.spark, {0: seeds}), method, **params)

    def close(self) -> None:
        self.graph.unpersist()


def run_grid(graph: Graph, seeds: DataFrame, grid: list[dict], method: str = "push") -> DataFrame:
    """``(point, run_id, size, vol, cut, phi)``: all seeds with every point of a parameter grid.

    Seeds run together in each point; points are separate plans because parameters shape the plan.
    """
    out = None
    for k, params in enumerate(grid):
        one = local_cluster(graph, seeds, method, **params).summary().select(F.lit(k).alias("point"), "*")
        out = one if out is None else out.union(one)
    return out


def community_profile(graph: Graph, seeds: DataFrame, alphas: list[float], epsilons: list[float], mode: str = "prefix", rule: str = "aggressive") -> DataFrame:
    """``(size, phi)``: the least conductance found at each cluster size over all runs.

    ``mode="prefix"`` counts every prefix of every sweep, "cluster" only the best one of each run.
    """
    out = None
    for alpha in alphas:
        for eps in epsilons:
            profile = sweep_profile(graph, d.residual_push(graph, seeds, alpha, eps, rule).p)
            rows = profile.select(F.col("rank").alias("size"), "phi") if mode == "prefix" else best_prefix(profile).select("size", "phi")
            least = rows.filter("phi is not null").groupBy("size").agg(F.min("phi").alias("phi"))
            out = least if out is None else out.union(least)
    return out.groupBy("size").agg(F.min("phi").alias("phi"))


def binned(profile: DataFrame, per_decade: int = 10) -> DataFrame:
    """The profile in logarithmic bins of size."""
    bin_ = F.floor(F.log10("size") * per_decade).cast("long")
    return profile.groupBy(bin_.alias("bin")).agg(F.min("size").alias("from_size"), F.min("phi").alias("phi"))


def sampled_vertices(graph: Graph, n: int, salt: int = 0) -> DataFrame:
    """``(run_id, v, w)``: n vertices in hash order, one run each (run_id = v)."""
    order = F.md5(F.concat_ws(":", F.lit(salt), "v"))
    return graph.degrees.orderBy(order, "v").limit(n).select(F.col("v").alias("run_id"), "v", F.lit(1.0).alias("w"))


def best_seed(graph: Graph, n: int, method: str = "push", **params) -> DataFrame:
    """``(v, phi, size)``: of n sampled vertices the one whose cluster has the least conductance."""
    found = local_cluster(graph, sampled_vertices(graph, n), method, **params).summary()
    return found.agg(F.min_by(F.struct("run_id", "phi", "size"), F.struct("phi", "run_id")).alias("b")).select(F.col("b.run_id").alias("v"), "b.phi", "b.size")


def components(graph: Graph) -> DataFrame:
    """``(v, component)``: the smallest vertex reachable."""
    return connected_components(graph.edges.filter("src < dst").select(F.col("src").alias("a"), F.col("dst").alias("b")))


def largest_component_seed(graph: Graph) -> DataFrame:
    """``(v, size)``: the smallest vertex of the largest component."""
    sizes = components(graph).groupBy("component").agg(F.count("*").alias("size"))
    return sizes.agg(F.max_by(F.struct("component", "size"), F.struct("size", -F.col("component"))).alias("b")).select(F.col("b.component").alias("v"), "b.size")
