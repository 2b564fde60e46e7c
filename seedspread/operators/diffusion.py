"""The four spreading methods and their baselines over batches of runs.

Every method takes ``seeds(run_id, v, w)``; one call serves one query or very many. ``mode="frames"`` runs
rounds of joins and sums over DataFrames, ``mode="in_task"`` hands the ball around the seeds to one task per
batch of runs and iterates on arrays; both give the same vectors. ``mode=None`` lets the planner choose.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from seedspread.operators import kernels
from seedspread.operators.frontier import edge_map, until_empty
from seedspread.operators.graph import Graph
from seedspread.plans import planner
from seedspread.runtime import materialize, release

VECTOR = "run_id long, v long, deg long, p double, r double"
STATS = "run_id long, round int, frontier long, edges long, mass_p double, mass_r double"


@dataclass
class Diffusion:
    """A sparse vector per run, the residual where the method has one, and counters per round."""

    graph: Graph
    p: DataFrame
    r: DataFrame | None = None
    stats: DataFrame | None = None
    rounds: list[dict] = field(default_factory=list)

    def top(self, k: int) -> DataFrame:
        """The k heaviest vertices of each run."""
        place = F.row_number().over(Window.partitionBy("run_id").orderBy(F.col("p").desc(), "v"))
        return self.p.withColumn("place", place).filter(F.col("place") <= k)

    def support(self) -> DataFrame:
        return self.p.groupBy("run_id").agg(F.count("*").alias("support"), F.sum("deg").alias("vol"))

    def mass(self) -> DataFrame:
        return self.p.groupBy("run_id").agg(F.sum("p").alias("mass"))

    def write(self, path: str) -> None:
        self.p.write.mode("overwrite").parquet(path)


def seeds_frame(spark: SparkSession, seeds: dict[int, list[int]] | list[int]) -> DataFrame:
    """``{run_id: [vertices]}`` or a list of single-vertex runs; weights are 1 / size of the seed set."""
    if isinstance(seeds, list):
        seeds = {k: [v] for k, v in enumerate(seeds)}
    rows = [(run, v, 1.0 / len(vs)) for run, vs in seeds.items() for v in vs]
    return spark.createDataFrame(rows, "run_id long, v long, w double")


class TooLarge(Exception):
    """The ball that a run needs exceeds what one task may hold."""


def ball(graph: Graph, seeds: DataFrame, hops: int, max_volume: int | None = None) -> tuple[DataFrame, bool]:
    """(``(v)`` within ``hops`` of the seeds, whether it was cut short).

    A ring that would take the ball's volume past ``max_volume`` is left out whole, whatever its size.
    """
    held = materialize(seeds.select("v").distinct().join(graph.degrees, "v"), "ball")
    ring, volume = held, 0
    for hop in range(hops + 1):
        row = ring.agg(F.count("*").alias("n"), F.coalesce(F.sum("deg"), F.lit(0)).alias("vol")).first()
        if row["n"] == 0:
            break
        if max_volume is not None and volume + row["vol"] > max_volume:
            return (held if hop else held.filter("false")).select("v"), True
        volume += row["vol"]
        if hop:
            held = materialize(held.union(ring), "ball")
        if hop < hops:
            side = ring.select(F.col("v").alias("src"))
            near = graph.edges.join(F.broadcast(side) if row["n"] <= 200_000 else side, "src").select(F.col("dst").alias("v")).distinct()
            ring = materialize(near.join(held, "v", "left_anti").join(graph.degrees, "v").select(*held.columns), "ball")
    return held.select("v"), False


def _in_task(graph: Graph, seeds: DataFrame, kernel: Callable, batches: int = 8, hops: int = 6) -> tuple[DataFrame, DataFrame]:
    """Run ``kernel(ball, seeds, run)`` for each run in a task that holds the ball; widen the ball while any run leaves it.

    Raises ``TooLarge`` where a run leaves the largest ball that a task may hold.
    """
    ends, degrees = graph.edges, graph.degrees
    seeds = materialize(seeds, "seeds")
    batches = max(1, min(batches, seeds.select("run_id").distinct().limit(batches).count()))
    while True:
        inside, cut = None, False
        if graph.total_volume > planner.IN_TASK_EDGES:
            inside, cut = ball(graph, seeds, hops, planner.IN_TASK_EDGES)
            ends = graph.edges.join(inside.withColumnRenamed("v", "src"), "src", "left_semi")
        both = ends.join(degrees.select(F.col("v").alias("src"), F.col("deg").alias("ds")), "src").join(degrees.select(F.col("v").alias("dst"), F.col("deg").alias("dd")), "dst")
        # the ball is bounded by IN_TASK_EDGES, its copies by the number of batches
        copies = both.withColumn("batch", F.explode(F.sequence(F.lit(0), F.lit(batches - 1))))
        dealt = seeds.withColumn("batch", F.pmod("run_id", F.lit(batches)).cast("int"))

        def solve(runs: pd.DataFrame, edges: pd.DataFrame) -> pd.DataFrame:
            columns = {"run_id": [], "kind": [], "v": [], "deg": [], "p": [], "r": [], "frontier": [], "edges": []}
            out = [pd.DataFrame(columns)]
            if len(runs) and not len(edges) and cut:
                out.append(pd.DataFrame({"run_id": runs.run_id.unique(), "kind": 2}))
            elif len(runs) and len(edges):
                held = kernels.Ball.of(*(edges[c].to_numpy(np.int64) for c in ("src", "dst", "ds", "dd")))
                for run, own in runs.groupby("run_id"):
                    try:
                        done = kernel(held, list(zip(own.v, own.w, strict=True)), int(run))
                    except kernels.Escaped:
                        out.append(pd.DataFrame({"run_id": [run], "kind": [2]}))
                        continue
                    keep = np.flatnonzero((done.p != 0) | (done.r != 0))
                    out.append(pd.DataFrame({"run_id": run, "kind": 0, "v": held.ids[keep], "deg": held.deg[keep], "p": done.p[keep], "r": done.r[keep]}))
                    rounds = done.rounds
                    out.append(pd.DataFrame({"run_id": run, "kind": 1, "v": range(len(rounds)), "frontier": [x[0] for x in rounds], "edges": [x[1] for x in rounds], "p": [x[2] for x in rounds], "r": [x[3] for x in rounds]}))
            full = pd.concat(out, ignore_index=True).reindex(columns=list(columns))
            return full.astype({"p": float, "r": float}).fillna(0).astype({c: "int64" for c in ("run_id", "kind", "v", "deg", "frontier", "edges")})

        schema = "run_id long, kind long, v long, deg long, p double, r double, frontier long, edges long"
        found = materialize(dealt.groupBy("batch").cogroup(copies.groupBy("batch")).applyInPandas(solve, schema), "in_task")
        if inside is None or found.filter("kind = 2").isEmpty():
            break
        if cut:
            raise TooLarge(f"a run leaves a ball of {planner.IN_TASK_EDGES} edges")
        hops *= 2
    stats = found.filter("kind = 1").select("run_id", F.col("v").cast("int").alias("round"), "frontier", "edges", F.col("p").alias("mass_p"), F.col("r").alias("mass_r"))
    return found.filter("kind = 0").select("run_id", "v", "deg", "p", "r"), stats


def _result(graph: Graph, found: tuple[DataFrame, DataFrame], scale: float = 1.0) -> Diffusion:
    rows, stats = found
    p = rows.filter("p > 0").select("run_id", "v", "deg", (F.col("p") * scale).alias("p"))
    return Diffusion(graph, p, rows.filter("r > 0").select("run_id", "v", "deg", "r"), stats)


def _start(graph: Graph, seeds: DataFrame) -> DataFrame:
    """Seeds with their degrees; seeds that are not in the graph vanish."""
    return seeds.groupBy("run_id", "v").agg(F.sum("w").alias("w")).join(graph.degrees, "v")


# ---- residual push -------------------------------------------------------------------------------------


def residual_push(graph: Graph, seeds: DataFrame, alpha: float, eps: float, rule: str = "aggressive", beta: float = 1.0, force_seed: bool = True,
                  blocks: int = 1, mode: str | None = None, chain: int = 1, max_rounds: int = 100_000) -> Diffusion:
    """Approximate PageRank by pushing residual mass in rounds.

    ``rule``: "lazy" keeps half of the rest at the vertex, "aggressive" sends it all. ``beta`` pushes only that
    top share of a round's qualifiers by r / deg. ``blocks`` pushes the qualifiers of a round in hash blocks,
    each on fresh residuals. Invariants: p and r sum to the seed mass; r / deg < eps at the end; the pushed
    volume is at most 1 / (alpha eps). Runs from an unknown or isolated vertex have an empty vector.
    """
    mode = mode or planner.choose(planner.work_bound("push", alpha=alpha, eps=eps), graph.total_volume)
    if mode == "in_task":
        try:
            return _result(graph, _in_task(graph, seeds, lambda b, s, run: kernels.push_bulk(b, s, alpha, eps, rule, beta, force_seed, max_rounds, blocks)))
        except TooLarge:
            pass  # the rounds below need no ball
    gain, send, stay = kernels.coefficients(rule, alpha)
    over = (F.col("r") >= eps * F.col("deg")) & (F.col("r") > 0)
    state = _start(graph, seeds).select("run_id", "v", "deg", F.lit(0.0).alias("p"), F.col("w").alias("r"), F.lit(force_seed).alias("forced"))

    def step(state: DataFrame, small: bool) -> DataFrame:
        flagged = state.withColumn("on", over | F.col("forced"))
        if beta < 1:
            by_run = Window.partitionBy("run_id", "on")
            place = F.row_number().over(by_run.orderBy(F.round(F.col("r") / F.col("deg"), 12).desc(), "v"))
            flagged = flagged.withColumns({"place": place, "many": F.count("*").over(by_run)}).withColumn("on", F.col("on") & (F.col("place") <= F.ceil(beta * F.col("many"))))
        for b in range(blocks):
            mine = F.col("on") if blocks == 1 else F.col("on") & (F.pmod("v", F.lit(blocks)) == b)
            here = flagged.withColumn("now", mine)
            sent = edge_map(graph, here.filter("now"), send * F.col("r") / F.col("deg"), broadcast=small)
            own = here.select("run_id", "v", "deg", F.when(F.col("now"), F.col("p") + gain * F.col("r")).otherwise(F.col("p")).alias("p"), F.when(F.col("now"), stay * F.col("r")).otherwise(F.col("r")).alias("r"), (F.col("on") & ~F.col("now")).alias("on"))
            both = own.union(sent.select("run_id", "v", "deg", F.lit(0.0), "mass", F.lit(False)))
            flagged = both.groupBy("run_id", "v").agg(F.max("deg").alias("deg"), F.sum("p").alias("p"), F.sum("r").alias("r"), F.max("on").alias("on"))
        return flagged.select("run_id", "v", "deg", "p", "r", F.lit(False).alias("forced"))

    state, rounds = until_empty(state, over | F.col("forced"), step, max_rounds, 1 if blocks > 1 else chain)
    return Diffusion(graph, state.filter("p > 0").select("run_id", "v", "deg", "p"), state.filter("r > 0").select("run_id", "v", "deg", "r"), None, rounds)


def residual_push_fifo(graph: Graph, seeds: DataFrame, alpha: float, eps: float, rule: str = "aggressive") -> Diffusion:
    """Baseline: one vertex at a time from a queue, one task per batch of runs."""
    return _result(graph, _in_task(graph, seeds, lambda b, s, run: kernels.push_queue(b, s, alpha, eps, rule)))


def residual_push_priority(graph: Graph, seeds: DataFrame, alpha: float, eps: float, rule: str = "aggressive") -> Diffusion:
    """Baseline variant: the queue is a heap keyed by r / deg at insertion."""
    return _result(graph, _in_task(graph, seeds, lambda b, s, run: kernels.push_queue(b, s, alpha, eps, rule, priority=True)))


def residual_push_dense(graph: Graph, seeds: DataFrame, alpha: float, eps: float, rule: str = "aggressive", max_rounds: int = 1000) -> Diffusion:
    """Baseline that is not local: every round handles every vertex of the graph; rounds count all rows."""
    gain, send, stay = kernels.coefficients(rule, alpha)
    everyone = seeds.select("run_id").distinct().join(graph.degrees).select("run_id", "v", "deg")
    state = everyone.join(seeds, ["run_id", "v"], "left").select("run_id", "v", "deg", F.lit(0.0).alias("p"), F.coalesce("w", F.lit(0.0)).alias("r"))
    over = (F.col("r") >= eps * F.col("deg")) & (F.col("r") > 0)

    def step(state: DataFrame, small: bool) -> DataFrame:
        value = F.when(over, F.col("r")).otherwise(0.0)
        sent = edge_map(graph, state.withColumn("x", value), send * F.col("x") / F.col("deg"), broadcast=False)
        got = sent.groupBy("run_id", "v").agg(F.sum("mass").alias("mass"))
        new = F.when(over, stay * F.col("r")).otherwise(F.col("r")) + F.coalesce("mass", F.lit(0.0))
        return state.join(got, ["run_id", "v"], "left").select("run_id", "v", "deg", (F.col("p") + gain * value).alias("p"), new.alias("r"))

    state, rounds = until_empty(state, over, step, max_rounds)
    n = graph.n
    return Diffusion(graph, state.filter("p > 0").select("run_id", "v", "deg", "p"), state.filter("r > 0").select("run_id", "v", "deg", "r"), None, [r | {"rows": n} for r in rounds])


# ---- truncated lazy walk -------------------------------------------------------------------------------


def truncated_walk(graph: Graph, seeds: DataFrame, T: int, eps: float, target_phi: float | None = None, truncate_output: bool = False, mode: str | None = None) -> Diffusion:  # noqa: N803
    """Lazy walk of T steps; entries under eps deg are dropped as a step begins.

    If no vertex of a new vector qualifies, the vector before it is the result. ``target_phi`` sweeps every
    vector and ends a run at the first cluster under it (column ``reached`` of ``p``). ``truncate_output``
    also drops small entries of the result.
    """
    mode = mode or ("frames" if target_phi is not None else planner.choose(planner.work_bound("walk", T=T, eps=eps), graph.total_volume))
    out = None
    if mode == "in_task":
        try:
            out = _result(graph, _in_task(graph, seeds, lambda b, s, run: kernels.walk_bulk(b, s, T, eps)))
        except TooLarge:
            pass  # the rounds need no ball
    if out is None:
        out = _walk_frames(graph, seeds, T, eps, target_phi)
    if truncate_output:
        out.p = out.p.filter(F.col("p") >= eps * F.col("deg"))
    return out


def _walk_frames(graph: Graph, seeds: DataFrame, steps: int, eps: float, target_phi: float | None) -> Diffusion:
    over = (F.col("p") >= eps * F.col("deg")) & (F.col("p") > 0)
    state = _start(graph, seeds).select("run_id", "v", "deg", F.col("w").alias("p"), F.lit(False).alias("done"), F.lit(None).cast("double").alias("reached"))
    state, rounds = materialize(state, "walk"), []
    for k in range(steps):
        going = state.filter("not done")
        active = going if k == 0 else going.filter(over)
        row = active.agg(F.count("*").alias("frontier"), F.coalesce(F.sum("deg"), F.lit(0)).alias("edges")).first()
        if row["frontier"] == 0:
            break
        rounds.append({"round": k, "frontier": row["frontier"], "edges": row["edges"]})
        sent = edge_map(graph, active, F.col("p") / 2 / F.col("deg"), broadcast=row["frontier"] <= 200_000)
        moved = active.select("run_id", "v", "deg", (F.col("p") / 2).alias("mass")).union(sent.select("run_id", "v", "deg", "mass"))
        new = moved.groupBy("run_id", "v").agg(F.max("deg").alias("deg"), F.sum("mass").alias("p"))
        new = materialize(new, "walk")
        alive = new.filter(over).select("run_id").distinct()
        kept = new.join(alive, "run_id", "left_semi").select("run_id", "v", "deg", "p", F.lit(False).alias("done"), F.lit(None).cast("double").alias("reached"))
        ended = state.join(kept.select("run_id").distinct(), "run_id", "left_anti").withColumn("done", F.lit(True))
        if target_phi is not None:
            from seedspread.operators.sweep import best_prefix, sweep_profile

            best = best_prefix(sweep_profile(graph, kept.select("run_id", "v", "p"))).filter(F.col("phi") < target_phi).select("run_id", F.col("phi").alias("phi_"))
            kept = kept.join(best, "run_id", "left").select("run_id", "v", "deg", "p", F.col("phi_").isNotNull().alias("done"), F.col("phi_").alias("reached"))
        following = materialize(kept.union(ended), "walk")
        release(state)
        release(new)
        state = following
    return Diffusion(graph, state.filter("p > 0").select("run_id", "v", "deg", "p", "reached") if target_phi is not None else state.filter("p > 0").select("run_id", "v", "deg", "p"), None, None, rounds)


def truncated_walk_sequential(graph: Graph, seeds: DataFrame, T: int, eps: float) -> Diffusion:  # noqa: N803
    """Baseline: the same updates vertex by vertex."""
    return _result(graph, _in_task(graph, seeds, lambda b, s, run: kernels.walk_bulk(b, s, T, eps, one_by_one=True)))


def lazy_walk_exact(graph: Graph, seeds: DataFrame, T: int, mode: str | None = None) -> Diffusion:  # noqa: N803
    """The walk without truncation."""
    return truncated_walk(graph, seeds, T, 0.0, mode=mode)


# ---- heat kernel by Taylor levels ----------------------------------------------------------------------


def heat_taylor(graph: Graph, seeds: DataFrame, t: float, N: int, eps: float, threshold: str = "scaled", last_level: str = "bare", scale_output: bool = False, mode: str | None = None) -> Diffusion:  # noqa: N803
    """Degree-N Taylor form of the heat kernel, level by level, small residuals dropped.

    ``threshold``: "scaled" compares with e^t eps (meets the work bound), "strict" with e^-t eps.
    ``last_level``: "bare" spreads the last residual by 1 / deg, "taylor" by t / (N deg).
    ``scale_output`` multiplies by e^-t; otherwise the vector is e^t times the kernel.
    """
    mode = mode or planner.choose(planner.work_bound("heat", t=t, N=N, eps=eps), graph.total_volume)
    scale = float(np.exp(-t)) if scale_output else 1.0
    if mode == "in_task":
        try:
            return _result(graph, _in_task(graph, seeds, lambda b, s, run: kernels.heat_bulk(b, s, t, N, eps, threshold, last_level)), scale)
        except TooLarge:
            pass  # the rounds below need no ball
    weights, levels, rounds = kernels.psi(N, t), [], []
    r = materialize(_start(graph, seeds).select("run_id", "v", "deg", F.col("w").alias("r")), "heat")
    for j in range(N):
        row = r.agg(F.count("*").alias("frontier"), F.coalesce(F.sum("deg"), F.lit(0)).alias("edges")).first()
        if row["frontier"] == 0:
            break
        rounds.append({"round": j, "frontier": row["frontier"], "edges": row["edges"]})
        levels.append(r.select("run_id", "v", "deg", F.col("r").alias("p")))
        share = kernels.last_share(t, N, last_level) if j + 1 == N else t / (j + 1)
        sent = edge_map(graph, r, share * F.col("r") / F.col("deg"), broadcast=row["frontier"] <= 200_000)
        if j + 1 == N:
            levels.append(sent.select("run_id", "v", "deg", F.col("mass").alias("p")))
            break
        summed = sent.groupBy("run_id", "v").agg(F.max("deg").alias("deg"), F.sum("mass").alias("r"))
        r = materialize(summed.filter(F.col("r") >= kernels.level_floor(j + 1, t, N, eps, threshold, weights) * F.col("deg")), "heat")
    total = levels[0]
    for level in levels[1:]:
        total = total.union(level)
    p = total.groupBy("run_id", "v").agg(F.max("deg").alias("deg"), (F.sum("p") * scale).alias("p"))
    return Diffusion(graph, materialize(p, "heat"), None, None, rounds)


def heat_taylor_queue(graph: Graph, seeds: DataFrame, t: float, N: int, eps: float, threshold: str = "scaled", last_level: str = "bare") -> Diffusion:  # noqa: N803
    """Baseline: entries (vertex, level) from a queue."""
    return _result(graph, _in_task(graph, seeds, lambda b, s, run: kernels.heat_queue(b, s, t, N, eps, threshold, last_level)))


# ---- heat kernel by random walks -----------------------------------------------------------------------


def _uniform(rng: str, *parts):
    """A number in [0, 1) that depends on the parts only."""
    if rng == "md5":
        return F.conv(F.substring(F.md5(F.concat_ws(":", *parts)), 1, 8), 16, 10).cast("long") / F.lit(float(1 << 32))
    return F.pmod(F.xxhash64(*parts), F.lit(1 << 52)) / F.lit(float(1 << 52))


def walk_lengths(spark: SparkSession, runs: DataFrame, n_walks: int | DataFrame, t: float, K: int, seed: int, overflow: str = "clamp", rng: str = "xxhash64") -> DataFrame:  # noqa: N803
    """``(run_id, walk_id, remaining)``: lengths drawn by inverting the cumulative Poisson table.

    ``n_walks`` is a number of walks or a DataFrame ``(walk_id)``.

    ``overflow="reject"`` redraws lengths over K (eight tries, then clamps); the other rules change the table.
    """
    cdf = kernels.length_cdf(t, K, "clamp" if overflow == "reject" else overflow)
    ids = n_walks if isinstance(n_walks, DataFrame) else spark.range(n_walks).select(F.col("id").alias("walk_id"))
    walks = ids.join(F.broadcast(runs.select("run_id").distinct()))
    draw = lambda k: _uniform(rng, F.lit(seed).cast("string") if rng == "md5" else F.lit(seed), F.col("run_id"), F.col("walk_id"), F.lit(f"length{k}" if k else "length"))
    if overflow == "reject":
        import math as m

        inside = float(sum(m.exp(-t) * t**k / m.factorial(k) for k in range(K + 1)))
        u = F.coalesce(*[F.when(draw(k) < inside, draw(k)) for k in range(8)], F.lit(inside))
    else:
        u = draw(0)
    index = sum((F.when(u >= c, 1).otherwise(0) for c in cdf[:-1]), F.lit(0))
    return walks.select("run_id", "walk_id", index.alias("remaining"))


def walk_starts(graph: Graph, seeds: DataFrame, lengths: DataFrame, seed: int, rng: str) -> DataFrame:
    """``(run_id, walk_id, remaining, at)``: each walk starts at a seed drawn by weight among the run's seeds in the graph.

    A run with one such seed draws nothing; a run without any has no walks.
    """
    held = seeds.groupBy("run_id", "v").agg(F.sum("w").alias("w")).filter("w > 0").join(graph.degrees.select("v"), "v", "left_semi")
    run, upto = Window.partitionBy("run_id"), Window.partitionBy("run_id").orderBy("v").rowsBetween(Window.unboundedPreceding, 0)
    share = held.withColumns({"hi": F.sum("w").over(upto) / F.sum("w").over(run), "place": F.row_number().over(Window.partitionBy("run_id").orderBy("v")), "many": F.count("*").over(run)})
    share = share.withColumn("lo", F.coalesce(F.lag("hi").over(Window.partitionBy("run_id").orderBy("v")), F.lit(0.0)))
    share = share.withColumn("hi", F.when(F.col("place") == F.col("many"), F.lit(2.0)).otherwise(F.col("hi"))).select("run_id", F.col("v").alias("at"), "lo", "hi")
    u = _uniform(rng, F.lit(seed).cast("string") if rng == "md5" else F.lit(seed), F.col("run_id"), F.col("walk_id"), F.lit("start"))
    return lengths.withColumn("u", u).join(share, "run_id").filter((F.col("u") >= F.col("lo")) & (F.col("u") < F.col("hi"))).select("run_id", "walk_id", "remaining", "at")


def heat_walks(graph: Graph, seeds: DataFrame, t: float, K: int, n_walks: int, seed: int = 1, overflow: str = "clamp", aggregate: str = "hash", rng: str = "xxhash64") -> Diffusion:  # noqa: N803
    """Heat kernel as the share of random walks of Poisson length that end at each vertex.

    A step is one join with the neighbour lists; finished walks leave the loop. With several seeds per run each
    walk draws its start by weight; seeds outside the graph take no part, so the mass is 1. ``aggregate``: "hash" counts by group with map-side partials, "sort" counts
    by offsets in the sorted list of ends. All choices are functions of (seed, run, walk, step).
    """
    spark = graph.spark
    lengths = walk_lengths(spark, seeds, n_walks, t, K, seed, overflow, rng)
    walkers = materialize(walk_starts(graph, seeds, lengths, seed, rng), "walkers")
    lists = graph.edges.groupBy("src").agg(F.array_sort(F.collect_list("dst")).alias("nbrs")) if rng == "md5" else graph.adjacency.groupBy("v").agg(F.array_sort(F.flatten(F.collect_list(F.transform("nbrs", lambda x: x["v"])))).alias("nbrs")).withColumnRenamed("v", "src")
    lists = materialize(lists, "lists")
    ends = walkers.filter("remaining = 0").select("run_id", "walk_id", "at")
    for k in range(K):
        walkers = walkers.filter("remaining > 0")
        u = _uniform(rng, F.lit(seed).cast("string") if rng == "md5" else F.lit(seed), F.col("run_id"), F.col("walk_id"), F.lit(f"step{k}"))
        moved = walkers.join(lists, F.col("at") == F.col("src")).select("run_id", "walk_id", (F.col("remaining") - 1).alias("remaining"), F.get("nbrs", F.floor(u * F.size("nbrs")).cast("int")).alias("at"))
        walkers = materialize(moved, "walkers")
        ends = ends.union(walkers.filter("remaining = 0").select("run_id", "walk_id", "at"))
    counts = count_ends_hash(ends) if aggregate == "hash" else count_ends_sort(ends)
    p = counts.select("run_id", F.col("at").alias("v"), (F.col("walks") / n_walks).alias("p")).join(graph.degrees, "v").select("run_id", "v", "deg", "p")
    return Diffusion(graph, p)


def count_ends_hash(ends: DataFrame) -> DataFrame:
    """``(run_id, at, walks)`` by grouping."""
    return ends.groupBy("run_id", "at").agg(F.count("*").alias("walks"))


def count_ends_sort(ends: DataFrame) -> DataFrame:
    """The same from the sorted ends: places where the value changes, and differences of those places."""
    order = Window.partitionBy("run_id").orderBy("at", "walk_id")
    placed = ends.select("run_id", "at", F.row_number().over(order).alias("place"), F.lag("at").over(order).alias("before"))
    heads = placed.filter("before is null or before <> at").select("run_id", "at", "place")
    total = ends.groupBy("run_id").agg(F.count("*").alias("all"))
    after = F.lead("place").over(Window.partitionBy("run_id").orderBy("place"))
    return heads.join(total, "run_id").select("run_id", "at", (F.coalesce(after, F.col("all") + 1) - F.col("place")).alias("walks"))


def compact_ids(df: DataFrame, key: str) -> DataFrame:
    """``(key, compact)``: dense numbers from 0, for counting with bounded keys."""
    from seedspread.operators.graph import relabel

    return relabel(df, key).withColumnRenamed("id", "compact")


def heat_walks_grouped(graph: Graph, seeds: DataFrame, t: float, K: int, n_walks: int, seed: int = 1) -> Diffusion:  # noqa: N803
    """The same law with counts for walkers: a row (vertex, remaining, count) splits its count over the neighbours by a multinomial draw."""
    spark = graph.spark
    lengths = walk_lengths(spark, seeds, n_walks, t, K, seed)
    dealt = walk_starts(graph, seeds, lengths, seed, "xxhash64")
    rows = materialize(dealt.groupBy("run_id", "remaining", "at").agg(F.count("*").alias("count")), "grouped")
    ends = rows.filter("remaining = 0").select("run_id", "at", "count")
    lists = materialize(graph.edges.groupBy(F.col("src").alias("at")).agg(F.array_sort(F.collect_list("dst")).alias("nbrs")), "lists")

    def split(batches):
        for pdf in batches:
            out = []
            for run, remaining, count, at, near in zip(pdf.run_id, pdf.remaining, pdf["count"], pdf["at"], pdf.nbrs, strict=True):
                draws = np.random.default_rng([seed, run, remaining, at]).multinomial(count, np.full(len(near), 1 / len(near)))
                hit = np.flatnonzero(draws)
                out.append(pd.DataFrame({"run_id": run, "remaining": remaining - 1, "at": np.asarray(near)[hit], "count": draws[hit]}))
            yield pd.concat(out) if out else pd.DataFrame({"run_id": [], "remaining": [], "at": [], "count": []})

    for _ in range(K):
        moved = rows.filter("remaining > 0").join(lists, "at").mapInPandas(split, "run_id long, remaining int, at long, count long")
        rows = materialize(moved.groupBy("run_id", "remaining", "at").agg(F.sum("count").alias("count")), "grouped")
        ends = ends.union(rows.filter("remaining = 0").select("run_id", "at", "count"))
    p = ends.groupBy("run_id", F.col("at").alias("v")).agg((F.sum("count") / n_walks).alias("p")).join(graph.degrees, "v").select("run_id", "v", "deg", "p")
    return Diffusion(graph, p)


def heat_walks_sequential(graph: Graph, seeds: DataFrame, t: float, K: int, n_walks: int, seed: int = 1, overflow: str = "clamp") -> Diffusion:  # noqa: N803
    """Baseline: one walk at a time."""
    return _result(graph, _in_task(graph, seeds, lambda b, s, run: kernels.walks_one_by_one(b, s, t, K, n_walks, seed, overflow, run)))


# ---- exact vectors -------------------------------------------------------------------------------------


def pagerank_exact(graph: Graph, seeds: DataFrame, alpha: float, tol: float = 1e-12, max_rounds: int = 5000) -> Diffusion:
    """The vector that both push rules approximate, by power iteration of the lazy walk with teleport ``alpha``.

    No push is involved: x ← alpha s + (1 - alpha) x W with W half stay, half move, until a step changes less
    than ``tol`` in all. For graphs that one task may hold.
    """
    if graph.total_volume > planner.IN_TASK_EDGES:
        raise TooLarge("the exact vector fills its component; use residual_push with a small eps beyond one task")
    return _result(graph, _in_task(graph, seeds, lambda b, s, run: kernels.power_iteration(b, s, alpha, tol, max_rounds)))


def heat_exact(graph: Graph, seeds: DataFrame, t: float, K: int) -> Diffusion:  # noqa: N803
    """Taylor series of K levels without truncation, times e^t."""
    return heat_taylor(graph, seeds, t, K, 0.0, last_level="taylor", mode="in_task")
