"""The graph: both directions of every undirected edge, its degrees and chunked neighbour lists."""

from __future__ import annotations

from functools import cached_property

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from seedspread.runtime import materialize

CHUNK = 4096


def symmetrize(edges: DataFrame) -> DataFrame:
    """Both directions of every pair ``(src, dst)``."""
    return edges.select("src", "dst").union(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))


def clean(edges: DataFrame) -> DataFrame:
    """Distinct pairs without self loops and nulls."""
    return edges.filter("src is not null and dst is not null and src <> dst").distinct()


def relabel(df: DataFrame, key: str) -> DataFrame:
    """``(key, id)`` with dense ids from 0 in key order, in two passes and without a global window.

    Keys are range-partitioned; each partition counts its own, only the counts (one row per partition) are
    summed over partitions, and the second pass adds each partition's offset.
    """
    keys = df.select(key).filter(F.col(key).isNotNull()).distinct()
    local = keys.repartitionByRange(key).sortWithinPartitions(key).select(key, F.spark_partition_id().alias("part"), F.monotonically_increasing_id().alias("mono"))
    local = materialize(local, "relabel")
    sizes = local.groupBy("part").agg(F.count("*").alias("n"), F.min("mono").alias("base"))
    offsets = sizes.select("part", "base", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("offset"))
    return local.join(F.broadcast(offsets), "part").select(key, (F.col("mono") - F.col("base") + F.col("offset")).alias("id"))


class Graph:
    """An undirected graph as DataFrames.

    ``edges(src, dst)`` holds both directions; isolated vertices do not exist. ``adjacency(v, chunk, deg,
    nbrs)`` lists neighbours with their degrees, hubs cut in chunks so one row stays small.
    """

    def __init__(self, edges: DataFrame):
        self.edges = edges
        self.spark = edges.sparkSession

    @classmethod
    def from_edges(cls, df: DataFrame, src: str = "src", dst: str = "dst") -> Graph:
        """Any pairs of ids; directions, repeats, self loops and nulls are normalised away."""
        pairs = df.select(F.col(src).cast("long").alias("src"), F.col(dst).cast("long").alias("dst"))
        return cls(clean(symmetrize(pairs)))

    @cached_property
    def degrees(self) -> DataFrame:
        """Written once per graph, so that no round counts them again."""
        return materialize(self.edges.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("deg")), "degrees")

    @cached_property
    def adjacency(self) -> DataFrame:
        """Written once per graph, so that no round builds the lists again."""
        ends = self.edges.join(self.degrees.select(F.col("v").alias("dst"), F.col("deg").alias("ndeg")), "dst")
        cut = ends.withColumn("chunk", F.pmod(F.xxhash64("dst"), F.lit(1 << 30)))
        sized = cut.join(self.degrees.withColumnRenamed("v", "src"), "src")
        piece = F.pmod(F.col("chunk"), F.greatest(F.lit(1), F.ceil(F.col("deg") / CHUNK))).cast("int")
        lists = sized.groupBy(F.col("src").alias("v"), piece.alias("chunk"), "deg")
        return materialize(lists.agg(F.array_sort(F.collect_list(F.struct(F.col("dst").alias("v"), F.col("ndeg").alias("deg")))).alias("nbrs")), "lists")

    @cached_property
    def total_volume(self) -> int:
        """Sum of all degrees, 2m."""
        return self.edges.count()

    @property
    def m(self) -> int:
        return self.total_volume // 2

    @cached_property
    def n(self) -> int:
        return self.degrees.count()

    def persist(self) -> Graph:
        """Keep the edges, degrees and neighbour lists resident for many queries."""
        self.edges.persist()
        self.degrees.persist()
        self.adjacency.persist()
        return self

    def unpersist(self) -> None:
        for df in (self.adjacency, self.degrees, self.edges):
            df.unpersist()

    def subtract(self, vertices: DataFrame) -> Graph:
        """The graph without the vertices ``(v)`` and their edges."""
        gone = vertices.select("v")
        left = self.edges.join(gone.withColumnRenamed("v", "src"), "src", "left_anti").join(gone.withColumnRenamed("v", "dst"), "dst", "left_anti")
        return Graph(left.select("src", "dst"))


def graph_stats(graph: Graph) -> DataFrame:
    """One row: vertices, undirected edges, smallest, largest and mean degree."""
    return graph.degrees.agg(
        F.count("*").alias("n"), F.coalesce((F.sum("deg") / 2).cast("long"), F.lit(0)).alias("m"), F.min("deg").alias("min_deg"), F.max("deg").alias("max_deg"), F.round(F.avg("deg"), 6).alias("mean_deg"))
