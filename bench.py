"""Headline workloads at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line of seconds."""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from seedspread.operators import diffusion as d
from seedspread.operators import measures, profile, sweep
from seedspread.sources import builders, generators

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "4")


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", str(2 * int(CPUS))).config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").config("spark.driver.memory", "5g").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    seconds: dict[str, float] = {}
    counters: dict[str, float] = {}

    def timed(name, job):
        began = time.perf_counter()
        out = job()
        seconds[name] = round(time.perf_counter() - began, 3)
        return out

    def built(make):
        graph = make().persist()
        graph.total_volume, graph.n, graph.adjacency.count()  # noqa: B018  edges, degrees and lists are made and held within the time
        return graph

    graph = timed("build_order_part", lambda: built(lambda: builders.order_part(spark, SF)))
    seed = d.seeds_frame(spark, [graph.edges.agg(F.min("src")).first()[0]])
    walk = timed("walk_T20_eps1e-8", lambda: (o := d.truncated_walk(graph, seed, 20, 1e-8, mode="in_task"), o.p.count())[0])
    push = timed("push_alpha0.01_eps1e-7", lambda: (o := d.residual_push(graph, seed, 0.01, 1e-7, mode="in_task"), o.p.count())[0])
    lazy = timed("push_lazy_alpha0.01_eps1e-7", lambda: (o := d.residual_push(graph, seed, 0.01, 1e-7, "lazy", mode="in_task"), o.p.count())[0])
    timed("heat_t10_N20_eps1e-7", lambda: d.heat_taylor(graph, seed, 10, 20, 1e-7, mode="in_task").p.count())
    timed("heat_walks_t10_K10_1e5", lambda: d.heat_walks(graph, seed, 10, 10, 100_000).p.count())
    timed("sweep_of_walk", lambda: sweep.sweep_cut(graph, walk.p).summary().collect())
    timed("push_frames_3_rounds", lambda: d.residual_push(graph, seed, 0.01, 1e-6, mode="frames", max_rounds=3).p.count())
    for name, out in (("push", push), ("push_lazy", lazy)):
        row = measures.push_counters(out.stats).first()
        counters |= {f"{name}_pushes": row["pushes"], f"{name}_rounds": row["rounds"]}
    geo = timed("build_geo", lambda: built(lambda: builders.geo(spark, SF)))
    starts = geo.degrees.filter("v % 4 = 0").orderBy("v").limit(200).select(F.col("v").alias("run_id"), "v", F.lit(1.0).alias("w"))
    timed("profile_geo_200_seeds", lambda: profile.community_profile(geo, starts, [0.05], [1e-4]).collect())
    torus = timed("build_torus40", lambda: built(lambda: generators.torus3d(spark, 40)))
    timed("push_torus40", lambda: d.residual_push(torus, d.seeds_frame(spark, [0]), 0.01, 1e-7).p.count())
    print(json.dumps({"metric": "total_seconds", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "counters": counters, "sf": SF.rsplit("sf", 1)[-1], "cpus": int(CPUS)}))
    spark.stop()


if __name__ == "__main__":
    main()
