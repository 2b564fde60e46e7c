"""Graphs on the given tables. Bipartite ids are 2 key for the left kind and 2 key + 1 for the right."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from seedspread.operators.graph import Graph
from seedspread.operators.overlap import linked_members
from seedspread.runtime import table


def bipartite(df: DataFrame, left: str, right: str) -> Graph:
    """Edges between two kinds of keys."""
    pairs = df.select((F.col(left).cast("long") * 2).alias("src"), (F.col(right).cast("long") * 2 + 1).alias("dst"))
    return Graph.from_edges(pairs.distinct())


def project_one_mode(df: DataFrame, member: str, group: str, max_group: int | None = None) -> Graph:
    """Members that share a group are joined. Groups of over ``max_group`` members are left out where it is given."""
    pairs = df.select(F.col(member).cast("long").alias("m"), F.col(group).alias("g")).filter("m is not null and g is not null").distinct()
    if max_group is not None:
        sizes = pairs.groupBy("g").count().filter(F.col("count") <= max_group)
        pairs = pairs.join(sizes.select("g"), "g", "left_semi")
    other = pairs.withColumnRenamed("m", "o")
    return Graph.from_edges(pairs.join(other, "g").filter("m < o").select(F.col("m").alias("src"), F.col("o").alias("dst")))


def string_ids(column: Column) -> Column:
    """Stable 48-bit ids of string keys from their md5, the same in any SQL engine."""
    return F.conv(F.substring(F.md5(column), 1, 12), 16, 10).cast("long")


def geo(spark: SparkSession, sf_dir: str) -> Graph:
    """Customers and suppliers with their nation, nations with their region. Ids: 4 key + kind."""
    link = lambda t, a, ka, b, kb: table(spark, sf_dir, t).select((F.col(a).cast("long") * 4 + ka).alias("src"), (F.col(b).cast("long") * 4 + kb).alias("dst"))
    edges = link("customer", "c_custkey", 0, "c_nationkey", 2).union(link("supplier", "s_suppkey", 1, "s_nationkey", 2)).union(link("nation", "n_nationkey", 2, "n_regionkey", 3))
    return Graph.from_edges(edges)


def _lineitems(spark, sf_dir, *columns):
    return table(spark, sf_dir, "lineitem").select("l_orderkey", *columns)


def cust_part(spark: SparkSession, sf_dir: str) -> Graph:
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    joined = _lineitems(spark, sf_dir, "l_partkey").join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    return bipartite(joined, "o_custkey", "l_partkey")


def cust_supp(spark: SparkSession, sf_dir: str) -> Graph:
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    joined = _lineitems(spark, sf_dir, "l_suppkey").join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    return bipartite(joined, "o_custkey", "l_suppkey")


def part_supp(spark: SparkSession, sf_dir: str) -> Graph:
    return bipartite(table(spark, sf_dir, "lineitem"), "l_partkey", "l_suppkey")


def order_part(spark: SparkSession, sf_dir: str) -> Graph:
    return bipartite(table(spark, sf_dir, "lineitem"), "l_orderkey", "l_partkey")


def copart(spark: SparkSession, sf_dir: str, max_group: int | None = None) -> Graph:
    return project_one_mode(table(spark, sf_dir, "lineitem"), "l_partkey", "l_orderkey", max_group)


def user_hour(spark: SparkSession, sf_dir: str) -> Graph:
    """Users and the hours they were active in; an hour's key is its number since the epoch."""
    hours = table(spark, sf_dir, "events").select("user_id", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 3_600_000_000).alias("hour"))
    return bipartite(hours, "user_id", "hour")


def user_key(spark: SparkSession, sf_dir: str) -> Graph:
    keys = table(spark, sf_dir, "events").select("user_id", F.get_json_object("props", "$.k").cast("long").alias("k"))
    return bipartite(keys.filter("k is not null"), "user_id", "k")


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(page_id, path)`` of every double-quoted link target."""
    hrefs = F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)
    return table(spark, sf_dir, "pages").select("page_id", F.explode(hrefs).alias("path")).distinct()


def page_path(spark: SparkSession, sf_dir: str) -> Graph:
    links = page_links(spark, sf_dir)
    return Graph.from_edges(links.select((F.col("page_id") * 2).alias("src"), (string_ids(F.col("path")) * 2 + 1).alias("dst")))


def shared_lines(spark: SparkSession, sf_dir: str, min_chars: int) -> DataFrame:
    """``(doc_id, line)`` of every trimmed line of at least ``min_chars`` characters."""
    lines = table(spark, sf_dir, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line"))
    return lines.select("doc_id", F.trim("line").alias("line")).filter(F.length("line") >= min_chars)


def doc_line(spark: SparkSession, sf_dir: str, min_chars: int = 20, max_group: int | None = None) -> Graph:
    """Documents that share a trimmed line of at least ``min_chars`` characters."""
    return project_one_mode(shared_lines(spark, sf_dir, min_chars), "doc_id", "line", max_group)


def doc_line_links(spark: SparkSession, sf_dir: str, min_chars: int = 20) -> DataFrame:
    """``(doc_id, n_links, component_id)`` of every document in the graph of ``doc_line``, its edges not listed.

    Lines are told apart by their 256-bit digests, which travel in their place.
    """
    lines = shared_lines(spark, sf_dir, min_chars).select(F.col("doc_id").cast("long").alias("m"), F.unhex(F.sha2("line", 256)).alias("g"))
    own = table(spark, sf_dir, "documents").select(F.col("doc_id").cast("long").alias("m")).filter("m is not null").distinct()
    rows = own.join(linked_members(lines), "m", "left")
    return rows.select(F.col("m").alias("doc_id"), F.coalesce("n_links", F.lit(0)).alias("n_links"), F.coalesce("component", "m").alias("component_id"))


def emb_knn(spark: SparkSession, sf_dir: str, k: int = 10) -> Graph:
    """The k most similar vectors by cosine, an edge where either side lists the other.

    Vectors are compared block by block: every row meets each block once and keeps its own best k of it.
    """
    return Graph.from_edges(knn(table(spark, sf_dir, "embeddings"), k))


#: Vectors of a block at most, so that a cell of two blocks has a bounded size whatever the table's.
BLOCK_ROWS = 16_384
#: Cosines in memory at once: rows of the left block by rows of the right one.
TILE = (512, 2048)


def nearest(ids: np.ndarray, x: np.ndarray, other: np.ndarray, y: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``(row of x, id, cosine)`` of each row's best k of the unit vectors ``y``, tile by tile; the id itself is left out.

    A tile only offers what is not below the k-th best that its row has so far.
    """
    found = []
    for lo in range(0, len(x), TILE[0]):
        mine, row, far, cosine = ids[lo : lo + TILE[0]], np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0)
        floor = np.full(len(mine), -np.inf)
        for at in range(0, len(y), TILE[1]):
            s, theirs = x[lo : lo + TILE[0]] @ y[at : at + TILE[1]].T, other[at : at + TILE[1]]
            if len(np.intersect1d(mine, theirs)):
                s[mine[:, None] == theirs[None, :]] = -np.inf
            if at == 0 and s.shape[1] > k:
                floor = np.round(np.partition(s, s.shape[1] - k, axis=1)[:, s.shape[1] - k], 9)
            i, j = np.nonzero((s >= floor[:, None] - 1e-9) & (s > -np.inf))
            if not len(i):
                continue
            row, far, cosine = np.concatenate([row, i]), np.concatenate([far, theirs[j]]), np.concatenate([cosine, np.round(s[i, j], 9)])
            order = np.lexsort((far, -cosine, row))
            row, far, cosine = row[order], far[order], cosine[order]
            keep = np.arange(len(row)) - np.searchsorted(row, row) < k
            row, far, cosine = row[keep], far[keep], cosine[keep]
            full = np.flatnonzero(np.bincount(row, minlength=len(mine)) == k)
            floor[full] = cosine[np.searchsorted(row, full, "right") - 1]
        found.append((row + lo, far, cosine))
    return tuple(np.concatenate(c) for c in zip(*found, strict=True))


def knn(vectors: DataFrame, k: int, blocks: int = 8) -> DataFrame:
    """``(src, dst, cosine)``: exact k nearest by cosine; ties go to the smaller id.

    There are at least ``blocks`` blocks, and as many as keep each below ``BLOCK_ROWS``.
    """
    import pandas as pd

    clean = vectors.select(F.col("vec_id").cast("long").alias("id"), F.col("embedding").alias("e")).filter("id is not null and e is not null")
    blocks = max(blocks, -(-clean.count() // BLOCK_ROWS))
    held = clean.withColumn("block", F.pmod(F.xxhash64("id"), F.lit(blocks)))
    dealt = held.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    left = dealt.select((F.col("block") * blocks + F.col("other")).alias("cell"), "id", "e")
    right = dealt.select((F.col("other") * blocks + F.col("block")).alias("cell"), "id", "e")

    def units(side: pd.DataFrame) -> tuple[np.ndarray, np.ndarray]:
        x = np.stack(side.e).astype(np.float64)
        x /= np.linalg.norm(x, axis=1, keepdims=True)
        sound = np.isfinite(x).all(axis=1)
        return side.id.to_numpy()[sound], x[sound]

    def best(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        if not left.empty and not right.empty:
            (ids, x), (other, y) = units(left), units(right)
            if len(ids) and len(other):
                row, far, cosine = nearest(ids, x, other, y, k)
                return pd.DataFrame({"src": ids[row], "dst": far, "cosine": cosine})
        return pd.DataFrame({"src": pd.Series(dtype="int64"), "dst": pd.Series(dtype="int64"), "cosine": pd.Series(dtype="float64")})

    near = left.groupBy("cell").cogroup(right.groupBy("cell")).applyInPandas(best, "src long, dst long, cosine double")
    place = F.row_number().over(Window.partitionBy("src").orderBy(F.col("cosine").desc(), "dst"))
    return near.withColumn("place", place).filter(F.col("place") <= k).drop("place")


BUILDERS = {"geo": geo, "cust_part": cust_part, "part_supp": part_supp, "cust_supp": cust_supp, "order_part": order_part, "copart": copart, "user_hour": user_hour, "user_key": user_key, "page_path": page_path, "doc_line": doc_line, "emb_knn": emb_knn}
