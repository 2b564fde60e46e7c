"""SQL functions and table functions of the engine."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf


def conductance(cut: Column, vol: Column, total: Column) -> Column:
    """cut / min(vol, total - vol), null where the smaller side is empty."""
    low = F.least(vol, total - vol)
    return F.when(low > 0, cut / low)


def edge_share(mass: Column, deg: Column) -> Column:
    """What each edge of a vertex carries."""
    return F.try_divide(mass, deg)


def poisson_length(u: Column, t: float, longest: int) -> Column:
    """Walk length from a uniform number, clamped to ``longest``."""
    from seedspread.operators.kernels import length_cdf

    return sum((F.when(u >= c, 1).otherwise(0) for c in length_cdf(t, longest)[:-1]), F.lit(0))


def poisson_cdf(k: Column, t: float) -> Column:
    """Chance that a walk's Poisson length is at most ``k``: the sum of e^-t t^j / j! over every j from 0 to ``k``, each term made from the one before; 0 below 0."""
    first = F.exp(F.lit(-t))

    def add(held: Column, j: Column) -> Column:
        term = held["term"] * t / j
        return F.struct(term.alias("term"), (held["total"] + term).alias("total"))

    upto = F.aggregate(F.sequence(F.lit(1), k), F.struct(first.alias("term"), first.alias("total")), add, lambda held: held["total"])
    return F.when(k < 0, 0.0).when(k == 0, first).when(k > 0, upto)


def psi(k: Column, degree: int, t: float) -> Column:
    """Tail weight of a Taylor level."""
    from seedspread.operators.kernels import psi as table

    return F.element_at(F.array(*map(F.lit, table(degree, t))), k + 1)


@udtf(returnType="run_id long, rank long, v long, vol long, cut long, phi double", useArrow=False)
class SweepTable:
    """``TABLE(run_id, v, p, deg, nbrs, total) PARTITION BY run_id`` → every prefix of each run's sweep."""

    def __init__(self):
        self.rows = []

    def eval(self, row):
        self.rows.append((row["run_id"], row["v"], row["p"], row["deg"], row["nbrs"], row["total"]))

    def terminate(self):
        held = sorted((r for r in self.rows if r[2] > 0), key=lambda r: (-round(r[2] / r[3], 12), r[1]))
        inside, vol, cut = set(), 0, 0
        for rank, (run, v, _, deg, near, total) in enumerate(held, 1):
            met = sum(w in inside for w in near)
            inside.add(v)
            vol, cut = vol + deg, cut + deg - 2 * met
            low = min(vol, total - vol)
            yield run, rank, v, vol, cut, cut / low if low > 0 else None


@udtf(returnType="src long, dst long")
class BallEdges:
    """``seed_ball_edges(v, nbrs)`` → one row per listed neighbour, for use with LATERAL."""

    def eval(self, v: int, nbrs: list):
        for w in nbrs or []:
            yield v, w


def cluster_f1(found: np.ndarray, truth: np.ndarray) -> float:
    """F1 of two membership flags; the body of the grouped-aggregate function below."""
    both = float(np.sum(found & truth))
    return 2 * both / max(1.0, float(found.sum() + truth.sum()))


def cluster_f1_agg():
    """A grouped-aggregate pandas function ``f1(found boolean, truth boolean)``."""
    import pandas as pd
    from pyspark.sql.functions import pandas_udf

    def f1(found: pd.Series, truth: pd.Series) -> float:
        return cluster_f1(found.to_numpy(bool), truth.to_numpy(bool))

    f1.__annotations__ = {"found": pd.Series, "truth": pd.Series, "return": float}
    return pandas_udf(f1, "double")


def register_functions(spark: SparkSession) -> None:
    """``seed_conductance``, ``seed_edge_share``, ``seed_sweep`` and ``seed_ball_edges`` for SQL users."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION seed_conductance(cut DOUBLE, vol DOUBLE, total DOUBLE) RETURNS DOUBLE RETURN CASE WHEN least(vol, total - vol) > 0 THEN cut / least(vol, total - vol) END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION seed_edge_share(mass DOUBLE, deg BIGINT) RETURNS DOUBLE RETURN try_divide(mass, deg)")
    spark.udtf.register("seed_sweep", SweepTable)
    spark.udtf.register("seed_ball_edges", BallEdges)
