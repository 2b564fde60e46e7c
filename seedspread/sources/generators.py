"""Synthetic graphs from arithmetic on ``spark.range``; the same arguments give the same graph anywhere."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from seedspread.operators.graph import Graph


def _unit(*parts: Column) -> Column:
    """A hash of the parts as a number in [0, 1)."""
    return F.pmod(F.xxhash64(*parts), F.lit(1 << 52)) / F.lit(float(1 << 52))


def grid_cells(df: DataFrame, k: int, x: str, y: str, z: str) -> DataFrame:
    """``(id)`` of the cells of a wrap-around grid of side ``k`` in which rows stand, by three keys modulo ``k``."""
    at = [F.pmod(F.col(c).cast("long"), F.lit(k)) for c in (x, y, z)]
    return df.select((at[0] + at[1] * k + at[2] * k * k).alias("id")).filter("id is not null").distinct()


def torus3d(spark: SparkSession, k: int, cells: DataFrame | None = None) -> Graph:
    """k³ vertices, each joined to its six neighbours of the wrap-around grid (k at least 3 for exactly 3 k³ edges).

    With ``cells(id)`` only those are vertices.
    """
    v = F.col("id")
    x, y, z = v % k, F.floor(v / k) % k, F.floor(v / (k * k))
    ahead = F.array((x + 1) % k + y * k + z * k * k, x + ((y + 1) % k) * k + z * k * k, x + y * k + ((z + 1) % k) * k * k)
    if cells is None:
        return Graph.from_edges(spark.range(k**3).select(v.alias("src"), F.explode(ahead).alias("dst")))
    pairs = cells.select(v.alias("src"), F.explode(ahead.cast("array<long>")).alias("dst"))
    return Graph.from_edges(pairs.join(cells.withColumnRenamed("id", "dst"), "dst", "left_semi"))


def id_local(spark: SparkSession, n: int, draws: int = 5, seed: int = 1, literal: bool = False, vertices: DataFrame | None = None) -> Graph:
    """Every vertex draws ``draws`` neighbours at a distance in ids; ``vertices(id)`` are the ids 0 to n - 1 where they are given.

    Distances are log-uniform, so near ids are favoured; ``literal`` makes a distance's chance proportional to it instead.
    """
    u = _unit(F.lit(seed), F.col("id"), F.col("draw"))
    reach = float(max(2, n // 2))
    distance = F.greatest(F.lit(1), F.floor(F.sqrt(u) * reach if literal else F.pow(F.lit(reach), u)))
    sign = F.when(F.pmod(F.xxhash64(F.lit(seed + 1), "id", "draw"), F.lit(2)) == 0, 1).otherwise(-1)
    drawn = (spark.range(n) if vertices is None else vertices).select("id", F.explode(F.sequence(F.lit(1), F.lit(draws))).alias("draw"))
    return Graph.from_edges(drawn.select(F.col("id").alias("src"), F.pmod(F.col("id") + sign * distance, F.lit(n)).cast("long").alias("dst")))


def planted(spark: SparkSession, blocks: int, size: int, p_in: float, p_out: float, seed: int = 1) -> Graph:
    """Blocks of ``size`` vertices; a pair is joined with probability ``p_in`` inside a block and ``p_out`` across. Block of v: v div size."""
    n = blocks * size
    pairs = spark.range(n).select(F.col("id").alias("src")).select("src", F.explode(F.sequence(F.col("src") + 1, F.greatest(F.lit(n - 1), F.col("src") + 1))).alias("dst")).filter(F.col("dst") < n)
    chance = F.when(F.floor(F.col("src") / size) == F.floor(F.col("dst") / size), p_in).otherwise(p_out)
    return Graph.from_edges(pairs.filter(_unit(F.lit(seed), F.col("src"), F.col("dst")) < chance))


def from_pairs(spark: SparkSession, pairs: list[tuple[int, int]]) -> Graph:
    return Graph.from_edges(spark.createDataFrame(pairs, "src long, dst long"))


def toy8(spark: SparkSession) -> Graph:
    """The worked example: a triangle 0 1 2 that hangs by 2-3 on a tail 3-4, 3-5, 3-6, 6-7."""
    return from_pairs(spark, [(0, 1), (0, 2), (1, 2), (2, 3), (3, 4), (3, 5), (3, 6), (6, 7)])


def path(spark: SparkSession, n: int) -> Graph:
    return Graph.from_edges(spark.range(n - 1).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst")))


def star(spark: SparkSession, n: int) -> Graph:
    return Graph.from_edges(spark.range(1, n).select(F.lit(0).alias("src"), F.col("id").alias("dst")))


def clique(spark: SparkSession, n: int, first: int = 0) -> Graph:
    ids = spark.range(first, first + n - 1).select(F.col("id").alias("src"))
    return Graph.from_edges(ids.select("src", F.explode(F.sequence(F.col("src") + 1, F.lit(first + n - 1))).alias("dst")))


def barbell(spark: SparkSession, n: int) -> Graph:
    """Two cliques of n joined by one edge."""
    bridge = spark.createDataFrame([(n - 1, n)], "src long, dst long")
    return Graph.from_edges(clique(spark, n).edges.union(clique(spark, n, n).edges).union(bridge))
