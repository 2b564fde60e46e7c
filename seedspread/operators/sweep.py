"""Sweep: order the support of a vector by p / deg and find the prefix of least conductance.

Ties in p / deg (rounded to 12 digits) go by vertex id; equal minima give the smallest prefix; a prefix whose
smaller side has no volume has no conductance; an empty vector gives no rows.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from seedspread.operators import kernels
from seedspread.operators.frontier import prefix_sum
from seedspread.operators.graph import Graph
from seedspread.runtime import materialize

#: Support of a single run from which ranks come from the two-pass scan instead of one window per run.
LARGE_SUPPORT = 20_000_000


def ranks(graph: Graph, p: DataFrame, large: bool = False) -> DataFrame:
    """``(run_id, v, deg, rank)`` of the support of ``p(run_id, v, p)``.

    ``large`` ranks one giant run without bringing it to one task: a range partition and two passes.
    """
    held = p.filter("p > 0").select("run_id", "v", "p").join(graph.degrees, "v").withColumn("key", -F.round(F.col("p") / F.col("deg"), 12))
    if large:
        return prefix_sum(held.withColumn("one", F.lit(1).cast("long")), ["key", "v"], "one", "rank").select("run_id", "v", "deg", "rank")
    place = F.row_number().over(Window.partitionBy("run_id").orderBy("key", "v"))
    return held.select("run_id", "v", "deg", place.cast("long").alias("rank"))


def prefix_volumes(ranked: DataFrame) -> DataFrame:
    """Adds ``vol``: the sum of degrees up to each rank."""
    return prefix_sum(ranked, ["rank"], "deg", "vol", ["run_id"])


def edge_rank_pairs(graph: Graph, ranked: DataFrame) -> DataFrame:
    """``(run_id, rank, delta)``: every edge end adds +1 at its rank and -1 at the rank of its other end.

    Only the lower end of an edge adds, outsiders rank one past the last, and deltas are summed per rank.
    """
    last = ranked.groupBy("run_id").agg(F.max("rank").alias("last"))
    ends = ranked.select("run_id", F.col("v").alias("src"), "rank").join(graph.edges, "src").join(last, "run_id")
    far = ranked.select("run_id", F.col("v").alias("dst"), F.col("rank").alias("far"))
    seen = ends.join(far, ["run_id", "dst"], "left").withColumn("far", F.coalesce("far", F.col("last") + 1)).filter("far > rank")
    pairs = seen.select("run_id", F.inline(F.array(F.struct(F.col("rank"), F.lit(1).alias("delta")), F.struct(F.col("far").alias("rank"), F.lit(-1).alias("delta")))))
    return pairs.groupBy("run_id", "rank").agg(F.sum("delta").alias("delta"))


def earlier_neighbours(graph: Graph, ranked: DataFrame) -> DataFrame:
    """``(run_id, v, earlier)``: neighbours that stand before v in the order."""
    near = ranked.select("run_id", F.col("v").alias("src"), "rank").join(graph.edges, "src")
    far = ranked.select("run_id", F.col("v").alias("dst"), F.col("rank").alias("far"))
    return near.join(far, ["run_id", "dst"]).filter("far < rank").groupBy("run_id", F.col("src").alias("v")).agg(F.count("*").alias("earlier"))


def _conductance(profile: DataFrame, total: int) -> DataFrame:
    low = F.least(F.col("vol"), F.lit(total) - F.col("vol"))
    return profile.withColumn("phi", F.when(low > 0, F.col("cut") / low))


def sweep_profile(graph: Graph, p: DataFrame, form: str = "compact", large: bool = False) -> DataFrame:
    """``(run_id, rank, v, vol, cut, phi)`` of every prefix.

    ``form="compact"`` scans one number per vertex, deg - 2 earlier neighbours; ``form="pairs"`` scans the
    summed edge deltas. Both give the same cuts.
    """
    ranked = materialize(ranks(graph, p, large), "ranks")
    if form == "pairs":
        deltas = edge_rank_pairs(graph, ranked)
    else:
        found = ranked.join(earlier_neighbours(graph, ranked), ["run_id", "v"], "left")
        deltas = found.select("run_id", "rank", (F.col("deg") - 2 * F.coalesce("earlier", F.lit(0))).alias("delta"))
    rows = ranked.join(deltas, ["run_id", "rank"], "left").withColumn("delta", F.coalesce("delta", F.lit(0)))
    if large:
        scanned = prefix_sum(prefix_sum(rows, ["rank"], "deg", "vol"), ["rank"], "delta", "cut")
    else:
        scanned = prefix_sum(prefix_volumes(rows), ["rank"], "delta", "cut", ["run_id"])
    return _conductance(scanned, graph.total_volume).select("run_id", "rank", "v", "vol", "cut", "phi")


def best_prefix(profile: DataFrame) -> DataFrame:
    """``(run_id, size, vol, cut, phi)`` of the first prefix of least conductance."""
    best = F.min_by(F.struct("rank", "vol", "cut", "phi"), F.struct("phi", "rank"))
    return profile.filter("phi is not null").groupBy("run_id").agg(best.alias("b")).select("run_id", F.col("b.rank").alias("size"), "b.vol", "b.cut", "b.phi")


class Cluster:
    """The best prefix of each run."""

    def __init__(self, profile: DataFrame):
        self.profile = profile
        self._best = best_prefix(profile)

    def summary(self) -> DataFrame:
        return self._best

    def members(self) -> DataFrame:
        """``(run_id, v, rank)``; the one row per run of the summary is what is joined."""
        return self.profile.join(self._best.select("run_id", "size"), "run_id").filter(F.col("rank") <= F.col("size")).select("run_id", "v", "rank")

    def explain(self) -> None:
        self._best.explain("formatted")


def sweep_cut(graph: Graph, p: DataFrame, form: str = "compact", large: bool = False) -> Cluster:
    """The cluster of each run of ``p(run_id, v, p)``."""
    return Cluster(sweep_profile(graph, p, form, large))


def whole_blocks(rows: DataFrame, last: int, *values: str) -> DataFrame:
    """``(run_id, level, block, *values)``: sums of ``rows(run_id, rank, *values)`` over blocks of 2^level ranks.

    Only blocks of even number are formed: no prefix needs another one.
    """
    dealt = rows.select("run_id", "rank", *values, F.explode(F.sequence(F.lit(0), F.lit(last.bit_length() - 1))).alias("level"))
    dealt = dealt.withColumn("block", F.expr("shiftright(rank - 1, level)")).filter("block % 2 = 0")
    return dealt.groupBy("run_id", "level", "block").agg(*[F.sum(x).alias(x) for x in values])


def blocks_of_prefixes(ranked: DataFrame, last: int) -> DataFrame:
    """``(run_id, rank, level, block)``: the prefix of each rank as disjoint blocks, one for every binary 1 of the rank."""
    dealt = ranked.select("run_id", "rank", F.explode(F.sequence(F.lit(0), F.lit(last.bit_length() - 1))).alias("level"))
    return dealt.withColumn("block", F.expr("shiftright(rank, level) - 1")).filter("block % 2 = 0")


def sweep_cut_naive(graph: Graph, p: DataFrame) -> DataFrame:
    """Baseline: volume and cut of every prefix counted anew, with no running sum; the same profile.

    A prefix is put together from whole blocks of ranks, at most log2 of its length, so no prefix is joined with all
    of its members. An edge end opens at its rank and closes at the later one of both ends; open ends are cut.
    """
    ranked = materialize(ranks(graph, p), "ranks")
    last = ranked.agg(F.max("rank")).first()[0] or 1
    ends = ranked.select("run_id", F.col("v").alias("src"), "rank").join(graph.edges, "src")
    far = ranked.select("run_id", F.col("v").alias("dst"), F.col("rank").alias("far"))
    closed = ends.join(far, ["run_id", "dst"]).select("run_id", F.greatest("rank", "far").alias("rank"), F.lit(0).alias("deg"), F.lit(-1).alias("cut"))
    marks = ranked.select("run_id", "rank", "deg", F.lit(0).alias("cut")).unionByName(ends.select("run_id", "rank", F.lit(0).alias("deg"), F.lit(1).alias("cut"))).unionByName(closed)
    sums = whole_blocks(marks.groupBy("run_id", "rank").agg(F.sum("deg").alias("vol"), F.sum("cut").alias("cut")), last, "vol", "cut")
    rows = blocks_of_prefixes(ranked, last).join(sums, ["run_id", "level", "block"]).groupBy("run_id", "rank").agg(F.sum("vol").alias("vol"), F.sum("cut").alias("cut"))
    return _conductance(rows.join(ranked.select("run_id", "rank", "v"), ["run_id", "rank"]), graph.total_volume).select("run_id", "rank", "v", "vol", "cut", "phi")


def sweep_cut_sequential(graph: Graph, p: DataFrame) -> DataFrame:
    """Baseline: one vertex after another in one task per run; the same profile."""
    total = graph.total_volume
    held = p.filter("p > 0").select("run_id", "v", "p").join(graph.degrees, "v")
    near = graph.edges.groupBy(F.col("src").alias("v")).agg(F.collect_list("dst").alias("nbrs"))

    def solve(pdf: pd.DataFrame) -> pd.DataFrame:
        src = np.repeat(pdf.v.to_numpy(np.int64), pdf.nbrs.map(len))
        dst = np.concatenate([np.asarray(x, np.int64) for x in pdf.nbrs])
        known = dict(zip(pdf.v, pdf.deg, strict=True))
        ball = kernels.Ball.of(src, dst, np.repeat(pdf.deg.to_numpy(np.int64), pdf.nbrs.map(len)), np.array([known.get(x, 1) for x in dst]))
        p_ = np.zeros(len(ball.ids))
        p_[np.searchsorted(ball.ids, pdf.v)] = pdf.p
        rows = kernels.sweep_one_by_one(ball, p_, total)
        out = pd.DataFrame(rows, columns=["rank", "v", "vol", "cut", "phi"])
        out.insert(0, "run_id", pdf.run_id.iloc[0])
        return out

    return held.join(near, "v").groupBy("run_id").applyInPandas(solve, "run_id long, rank long, v long, vol long, cut long, phi double")
