"""The experiment workloads on the given tables: each function returns one result table.

``size`` scales the number of seeds and walks; seconds are wall-clock of the plan that produced the row.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seedspread.operators import diffusion as d
from seedspread.operators import measures, profile, sweep
from seedspread.operators.graph import graph_stats
from seedspread.sources import builders, generators

GRAPHS = ("geo", "order_part", "page_path")


def _start(graph) -> DataFrame:
    """One vertex of the largest component."""
    seed = profile.largest_component_seed(graph).first()["v"]
    return d.seeds_frame(graph.spark, [seed])


def _phi(graph, p: DataFrame) -> float | None:
    row = sweep.sweep_cut(graph, p).summary().first()
    return None if row is None else row["phi"]


def inventory(spark: SparkSession, sf: str) -> DataFrame:
    """Vertices, edges and degrees of every graph."""
    out = None
    for name, build in builders.BUILDERS.items():
        one = graph_stats(build(spark, sf)).select(F.lit(name).alias("graph"), "*")
        out = one if out is None else out.union(one)
    return out


def rule_ablation(spark: SparkSession, sf: str, alpha: float = 0.01, eps: float = 1e-5, graphs=GRAPHS) -> DataFrame:
    """Lazy against aggressive pushes: counters, seconds and conductance, which should agree."""
    rows = []
    for name in graphs:
        g = builders.BUILDERS[name](spark, sf).persist()
        start = _start(g)
        for rule in ("lazy", "aggressive"):
            out, seconds = measures.timed(lambda g=g, start=start, rule=rule: d.residual_push(g, start, alpha, eps, rule, mode="in_task"))
            c = measures.push_counters(out.stats).first()
            rows.append((name, rule, c["pushes"], c["rounds"], seconds, _phi(g, out.p)))
        g.unpersist()
    return spark.createDataFrame(rows, "graph string, rule string, pushes long, rounds long, seconds double, phi double")


def push_counts(spark: SparkSession, sf: str, alpha: float = 0.01, eps: float = 1e-5, graphs=GRAPHS) -> DataFrame:
    """Pushes of the queue and of the bulk form, rounds, and their ratio."""
    rows = []
    for name in graphs:
        g = builders.BUILDERS[name](spark, sf).persist()
        start = _start(g)
        bulk = measures.push_counters(d.residual_push(g, start, alpha, eps, mode="in_task").stats).first()
        queue = d.residual_push_fifo(g, start, alpha, eps).stats.agg(F.sum("frontier")).first()[0]
        rows.append((name, queue, bulk["pushes"], bulk["rounds"], bulk["pushes"] / queue, bulk["pushes_per_round"]))
        g.unpersist()
    return spark.createDataFrame(rows, "graph string, pushes_seq long, pushes_bulk long, rounds long, ratio double, per_round double")


def beta_study(spark: SparkSession, sf: str, alpha: float = 0.05, eps: float = 1e-5) -> DataFrame:
    """Share of qualifiers pushed per round against pushes, rounds and conductance."""
    g = builders.geo(spark, sf).persist()
    start, rows = _start(g), []
    for beta in (0.1, 0.25, 0.5, 1.0):
        out = d.residual_push(g, start, alpha, eps, beta=beta, mode="in_task")
        c = measures.push_counters(out.stats).first()
        rows.append((beta, c["pushes"], c["rounds"], _phi(g, out.p)))
    return spark.createDataFrame(rows, "beta double, pushes long, rounds long, phi double")


def queue_study(spark: SparkSession, sf: str, alpha: float = 0.05, eps: float = 1e-5) -> DataFrame:
    """Queue against priority queue."""
    g = builders.geo(spark, sf).persist()
    start, rows = _start(g), []
    for name, run in (("fifo", d.residual_push_fifo), ("priority", d.residual_push_priority)):
        out, seconds = measures.timed(lambda run=run: run(g, start, alpha, eps))
        rows.append((name, out.stats.agg(F.sum("frontier")).first()[0], seconds))
    return spark.createDataFrame(rows, "queue string, pushes long, seconds double")


def parameter_study(spark: SparkSession, sf: str, graph: str = "geo") -> DataFrame:
    """Conductance and seconds over the parameters of each method."""
    g = builders.BUILDERS[graph](spark, sf).persist()
    start, rows = _start(g), []
    points = [("walk", d.truncated_walk, {"T": t, "eps": e}) for t in (5, 10, 20, 40) for e in (1e-3, 1e-5)]
    points += [("push", d.residual_push, {"alpha": 0.05, "eps": e}) for e in (1e-3, 1e-4, 1e-5, 1e-6)]
    points += [("heat", d.heat_taylor, {"t": 5, "N": n, "eps": e}) for n in (5, 10, 20) for e in (1e-3, 1e-5)]
    points += [("heat_walks", d.heat_walks, {"t": 5, "K": k, "n_walks": n}) for k in (5, 10) for n in (1_000, 10_000)]
    for name, run, params in points:
        out, seconds = measures.timed(lambda run=run, params=params: run(g, start, **params))
        rows.append((name, str(params), seconds, _phi(g, out.p)))
    return spark.createDataFrame(rows, "method string, params string, seconds double, phi double")


def running_times(spark: SparkSession, sf: str, graphs=("order_part", "cust_part"), torus: int = 20, walks: int = 20_000) -> DataFrame:
    """Bulk and one-by-one forms of every method with fixed parameters."""
    made = {n: builders.BUILDERS[n](spark, sf) for n in graphs} | {f"torus{torus}": generators.torus3d(spark, torus), "id_local": generators.id_local(spark, torus**3)}
    rows = []
    for name, g in made.items():
        g.persist()
        start = _start(g)
        jobs = {
            ("walk", "bulk"): lambda g=g, s=start: d.truncated_walk(g, s, 20, 1e-6, mode="in_task"), ("walk", "one_by_one"): lambda g=g, s=start: d.truncated_walk_sequential(g, s, 20, 1e-6),
            ("push", "bulk"): lambda g=g, s=start: d.residual_push(g, s, 0.01, 1e-5, mode="in_task"), ("push", "one_by_one"): lambda g=g, s=start: d.residual_push_fifo(g, s, 0.01, 1e-5),
            ("heat", "bulk"): lambda g=g, s=start: d.heat_taylor(g, s, 10, 20, 1e-5, mode="in_task"), ("heat", "one_by_one"): lambda g=g, s=start: d.heat_taylor_queue(g, s, 10, 20, 1e-5),
            ("heat_walks", "bulk"): lambda g=g, s=start: d.heat_walks(g, s, 10, 10, walks), ("heat_walks", "one_by_one"): lambda g=g, s=start: d.heat_walks_sequential(g, s, 10, 10, walks),
        }
        for (method, form), job in jobs.items():
            out, seconds = measures.timed(lambda job=job: (o := job(), o.p.count())[0])
            rows.append((name, method, form, seconds))
            if (method, form) == ("walk", "bulk"):
                for how, cut in (("bulk", lambda p, g=g: sweep.sweep_profile(g, p).count()), ("one_by_one", lambda p, g=g: sweep.sweep_cut_sequential(g, p).count())):
                    rows.append((name, "sweep", how, measures.timed(lambda cut=cut, out=out: cut(out.p))[1]))
        g.unpersist()
    return spark.createDataFrame(rows, "graph string, method string, form string, seconds double")


def sweep_by_volume(spark: SparkSession, sf: str) -> DataFrame:
    """Seconds of a sweep against the volume it covers; should grow about linearly."""
    g = builders.order_part(spark, sf).persist()
    start, rows = _start(g), []
    for steps in (2, 3, 4, 6):
        p = d.truncated_walk(g, start, steps, 1e-9, mode="in_task").p
        vol = p.agg(F.sum("deg")).first()[0]
        rows.append((steps, vol, measures.timed(lambda p=p: sweep.sweep_cut(g, p).summary().collect())[1]))
    return spark.createDataFrame(rows, "steps int, vol long, seconds double")


def community_curve(spark: SparkSession, sf: str, graph: str = "geo", n_seeds: int = 100) -> DataFrame:
    """Least conductance by size over many seeds and two settings each of alpha and eps."""
    g = builders.BUILDERS[graph](spark, sf).persist()
    return profile.binned(profile.community_profile(g, profile.sampled_vertices(g, n_seeds), [0.05, 0.2], [1e-3, 1e-4]))


def no_good_cluster(spark: SparkSession, sf: str) -> DataFrame:
    """Graphs without a good local cluster beside one that has them."""
    rows = []
    for name, g in (("geo", builders.geo(spark, sf)), ("cust_part", builders.cust_part(spark, sf)), ("torus", generators.torus3d(spark, 12))):
        out = d.residual_push(g, _start(g), 0.05, 1e-5, mode="in_task")
        rows.append((name, out.p.count(), _phi(g, out.p)))
    return spark.createDataFrame(rows, "graph string, touched long, phi double")


def local_against_dense(spark: SparkSession, sf: str, rounds: int = 5) -> DataFrame:
    """Rows handled per round by the local form and by the form that handles every vertex."""
    g = builders.geo(spark, sf).persist()
    start = _start(g)
    near = d.residual_push(g, start, 0.05, 1e-4, mode="frames", max_rounds=rounds).rounds
    dense = d.residual_push_dense(g, start, 0.05, 1e-4, max_rounds=rounds).rounds
    return spark.createDataFrame([(a["round"], a["frontier"], b["rows"]) for a, b in zip(near, dense, strict=False)], "round int, local_rows long, dense_rows long")


def counting_study(spark: SparkSession, sf: str, walks: int = 20_000) -> DataFrame:
    """Counting walk ends by groups against by sorting."""
    g = builders.geo(spark, sf).persist()
    rows = [(how, measures.timed(lambda how=how: d.heat_walks(g, _start(g), 5, 10, walks, aggregate=how).p.count())[1]) for how in ("hash", "sort")]
    return spark.createDataFrame(rows, "counting string, seconds double")


def interactive(spark: SparkSession, sf: str) -> DataFrame:
    """Latency of queries on a resident graph, first and later ones."""
    session = profile.Session(builders.geo(spark, sf))
    rows = [(k, measures.timed(lambda k=k: session.query([4 * k], alpha=0.05, eps=1e-4).summary().collect())[1]) for k in range(4)]
    session.close()
    return spark.createDataFrame(rows, "query int, seconds double")


WORKLOADS = {f.__name__: f for f in (inventory, rule_ablation, push_counts, beta_study, queue_study, parameter_study, running_times, sweep_by_volume, community_curve, no_good_cluster, local_against_dense, counting_study, interactive)}
