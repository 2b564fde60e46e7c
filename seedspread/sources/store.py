"""Neighbour lists on disk, laid out so that a frontier reads only the files of its buckets."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seedspread.operators.graph import Graph

LISTS = "v long, chunk int, deg long, nbrs array<struct<v: long, deg: long>>, bucket int"
#: Buckets named in one read; a frontier that touches more of them reads everything.
MAX_NAMED_BUCKETS = 10_000


def bucket_of(v, buckets: int):
    return F.pmod(F.xxhash64(v), F.lit(buckets)).cast("int")


class AdjacencyStore:
    """``bucket=k`` folders of neighbour lists, sorted by vertex inside each file."""

    def __init__(self, spark: SparkSession, path: str, buckets: int):
        self.spark, self.path, self.buckets = spark, path, buckets

    @classmethod
    def write(cls, graph: Graph, path: str, buckets: int = 256) -> AdjacencyStore:
        rows = graph.adjacency.withColumn("bucket", bucket_of(F.col("v"), buckets))
        rows.repartition(buckets, "bucket").sortWithinPartitions("bucket", "v").write.mode("overwrite").partitionBy("bucket").parquet(path)
        return cls(graph.spark, path, buckets)

    def scan(self) -> DataFrame:
        return self.spark.read.schema(LISTS).parquet(self.path)

    def lists_of(self, frontier: DataFrame) -> DataFrame:
        """Lists of the vertices of ``frontier(v)``: buckets become literals, so other folders are not read."""
        wanted = frontier.select("v").distinct().withColumn("bucket", bucket_of(F.col("v"), self.buckets))
        named = [r["bucket"] for r in wanted.select("bucket").distinct().limit(MAX_NAMED_BUCKETS + 1).collect()]
        rows = self.scan()
        if len(named) <= MAX_NAMED_BUCKETS:
            rows = rows.filter(F.col("bucket").isin(named))
        return rows.join(wanted, ["bucket", "v"], "left_semi")


class StoredGraph(Graph):
    """A graph whose rounds read a store: edges, degrees and lists all come from it."""

    def __init__(self, store: AdjacencyStore):
        self.store = store
        super().__init__(store.scan().select(F.col("v").alias("src"), F.explode("nbrs").alias("x")).select("src", F.col("x.v").alias("dst")))

    @property
    def degrees(self) -> DataFrame:
        return self.store.scan().filter("chunk >= 0").groupBy("v").agg(F.max("deg").alias("deg"))

    @property
    def adjacency(self) -> DataFrame:
        return self.store.scan().drop("bucket")
