"""Frontier primitives: maps over vertex subsets and their edges, sums, scans, and the round loop."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from seedspread.operators.graph import Graph
from seedspread.runtime import materialize, release

#: Frontier rows up to which the frontier is broadcast to the neighbour lists (about 60 bytes a row).
BROADCAST_ROWS = 200_000


def vertex_map(subset: DataFrame, **expressions: Column) -> DataFrame:
    """Apply expressions to each member of a subset; nothing else is touched."""
    return subset.withColumns(expressions)


def edge_map(graph: Graph, subset: DataFrame, contribution: Column, carry: tuple[str, ...] = ("run_id",), broadcast: bool = True) -> DataFrame:
    """One row ``(*carry, v, deg, mass)`` for every edge that leaves a member of ``subset(*carry, v, …)``."""
    members = subset.select(*carry, "v", contribution.alias("mass"))
    side = F.broadcast(members) if broadcast else members.hint("shuffle_hash")
    sent = graph.adjacency.select("v", "nbrs").join(side, "v").select(*carry, "mass", F.inline("nbrs"))
    return sent.select(*carry, "v", "deg", "mass")


def combine(rows: DataFrame, keys: tuple[str, ...], *sums: str) -> DataFrame:
    """Order-free addition per key; partial sums are formed before the shuffle."""
    return rows.groupBy(*keys).agg(*[F.sum(c).alias(c) for c in sums])


def filter_subset(subset: DataFrame, predicate: Column) -> DataFrame:
    return subset.filter(predicate)


def prefix_sum(df: DataFrame, order: list[str], value: str, into: str, partition: list[str] | None = None, inclusive: bool = True, op: str = "sum") -> DataFrame:
    """Scan with ``sum`` or ``min`` in ``order``.

    With ``partition`` each group is scanned on its own. Without, two passes: rows are range-partitioned, each
    partition is summed, the running totals of the partitions (one row each) are broadcast, and partitions are
    scanned in place, so no partition holds more than its share.
    """
    reduce_ = {"sum": F.sum, "min": F.min}[op]
    end = 0 if inclusive else -1
    if partition:
        frame = Window.partitionBy(*partition).orderBy(*order).rowsBetween(Window.unboundedPreceding, end)
        return df.withColumn(into, reduce_(value).over(frame))
    dealt = materialize(df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_part", F.spark_partition_id()), "scan")
    totals = dealt.groupBy("_part").agg(reduce_(value).alias("_total"))
    before = totals.select("_part", reduce_("_total").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)).alias("_before"))
    inner = reduce_(value).over(Window.partitionBy("_part").orderBy(*order).rowsBetween(Window.unboundedPreceding, end))
    joined = dealt.withColumn("_inner", inner).join(F.broadcast(before), "_part")
    if op == "sum":
        both = F.when(F.col("_inner").isNull(), F.col("_before")).otherwise(F.col("_inner") + F.coalesce("_before", F.lit(0)))
    else:
        both = F.least("_inner", "_before")
    return joined.withColumn(into, both).drop("_part", "_inner", "_before")


def until_empty(state: DataFrame, active: Column, step: Callable[[DataFrame, bool], DataFrame], max_rounds: int, chain: int = 1) -> tuple[DataFrame, list[dict]]:
    """Apply ``step`` until no row is active; ``chain`` rounds form one plan between writes.

    The state is written to shared storage after each plan, so lineage stays short and lost executors cost
    one plan at most. Only the counters of a round come to the driver.
    """
    state, stats, done = materialize(state, "state"), [], 0
    while True:
        row = state.filter(active).agg(F.count("*").alias("frontier"), F.coalesce(F.sum("deg"), F.lit(0)).alias("edges")).first()
        if row["frontier"] == 0 or done >= max_rounds:
            return state, stats
        stats.append({"round": done, "frontier": row["frontier"], "edges": row["edges"]})
        following = state
        for _ in range(min(chain, max_rounds - done)):
            following = step(following, row["frontier"] * max(1, chain) <= BROADCAST_ROWS)
            done += 1
        following = materialize(following, "state")
        release(state)
        state = following
