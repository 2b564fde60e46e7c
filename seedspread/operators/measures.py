"""Cluster quality, cost counters and accuracy measures."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seedspread.operators.graph import Graph


def volume(graph: Graph, sets: DataFrame) -> DataFrame:
    """``sets(set_id, v)`` → ``(set_id, size, vol)``."""
    return sets.join(graph.degrees, "v").groupBy("set_id").agg(F.count("*").alias("size"), F.sum("deg").alias("vol"))


def boundary(graph: Graph, sets: DataFrame) -> DataFrame:
    """``(set_id, cut)``: edges with exactly one end in the set."""
    ends = sets.select("set_id", F.col("v").alias("src")).join(graph.edges, "src")
    leaving = ends.join(sets.select("set_id", F.col("v").alias("dst")), ["set_id", "dst"], "left_anti")
    return leaving.groupBy("set_id").agg(F.count("*").alias("cut"))


def conductance(graph: Graph, sets: DataFrame) -> DataFrame:
    """``(set_id, size, vol, cut, phi)``; phi is null where the smaller side has no volume."""
    low = F.least(F.col("vol"), F.lit(graph.total_volume) - F.col("vol"))
    both = volume(graph, sets).join(boundary(graph, sets), "set_id", "left").withColumn("cut", F.coalesce("cut", F.lit(0)))
    return both.withColumn("phi", F.when(low > 0, F.col("cut") / low))


def push_counters(stats: DataFrame) -> DataFrame:
    """Per run: rounds, pushes, edges, pushes per round and final masses, from per-round counters."""
    return stats.groupBy("run_id").agg(
        F.count("*").alias("rounds"), F.sum("frontier").alias("pushes"), F.sum("edges").alias("edges"), (F.sum("frontier") / F.count("*")).alias("pushes_per_round"),
        F.max_by("mass_p", "round").alias("mass_p"), F.max_by("mass_r", "round").alias("mass_r"))


def push_inflation(bulk: DataFrame, sequential: DataFrame) -> DataFrame:
    """``(run_id, ratio)`` of the pushes of two forms."""
    a = push_counters(bulk).select("run_id", F.col("pushes").alias("bulk"))
    b = sequential.groupBy("run_id").agg(F.sum("frontier").alias("seq"))
    return a.join(b, "run_id").select("run_id", "bulk", "seq", (F.col("bulk") / F.col("seq")).alias("ratio"))


def residual_peak(r: DataFrame) -> DataFrame:
    """``(run_id, peak)``: the largest residual per degree."""
    return r.groupBy("run_id").agg(F.max(F.col("r") / F.col("deg")).alias("peak"))


def vector_error(graph: Graph, p: DataFrame, exact: DataFrame) -> DataFrame:
    """``(run_id, worst, l1)``: largest difference per degree and the sum of differences."""
    a, b = p.select("run_id", "v", "p"), exact.select("run_id", "v", F.col("p").alias("q"))
    gap = a.join(b, ["run_id", "v"], "full").select("run_id", "v", F.abs(F.coalesce("p", F.lit(0.0)) - F.coalesce("q", F.lit(0.0))).alias("gap"))
    return gap.join(graph.degrees, "v").groupBy("run_id").agg(F.max(F.col("gap") / F.col("deg")).alias("worst"), F.sum("gap").alias("l1"))


def set_scores(found: DataFrame, truth: DataFrame) -> DataFrame:
    """``(set_id, precision, recall, f1, jaccard)`` of two collections of sets with the same ids."""
    hit = found.join(truth, ["set_id", "v"]).groupBy("set_id").agg(F.count("*").alias("both"))
    sizes = found.groupBy("set_id").agg(F.count("*").alias("a")).join(truth.groupBy("set_id").agg(F.count("*").alias("b")), "set_id")
    rows = sizes.join(hit, "set_id", "left").withColumn("both", F.coalesce("both", F.lit(0)))
    return rows.select(
        "set_id", (F.col("both") / F.col("a")).alias("precision"), (F.col("both") / F.col("b")).alias("recall"), (2 * F.col("both") / (F.col("a") + F.col("b"))).alias("f1"),
        (F.col("both") / (F.col("a") + F.col("b") - F.col("both"))).alias("jaccard"))


def timed(job: Callable[[], object]) -> tuple[object, float]:
    """What a job returns, and its wall-clock seconds."""
    began = time.perf_counter()
    out = job()
    return out, time.perf_counter() - began


def speedup(seconds: dict[int, float]) -> dict[int, float]:
    """Self-relative speed-up per number of cores, against the fewest."""
    base = seconds[min(seconds)]
    return {cores: base / s for cores, s in sorted(seconds.items())}
