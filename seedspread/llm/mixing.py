"""Mixing sources to target weights by capped water-filling, DataFrame functions only.

Sources get ``weight / sum of weights`` of a word budget. A source whose share is above ``max_epochs`` times
its size is clamped there and its excess is reshared by weight among the others until none is above. The
clamped set is found in one ordered pass over the per-source table: with sources sorted by cap / weight, one
is clamped exactly while the level left by those before it exceeds its own ratio.

A source then takes every document ``floor(rate)`` times and the fraction that remains as a seeded choice of
whole documents: they stand in hash order and are taken while the middle of a document lies under the
wanted sum, so a source misses its target by at most half a document. To find that point no source is
sorted as a whole: sizes are summed in 4096 hash slices per source, and only the slice in which the point
falls is ordered.

Cases: null text has size 0 and is never taken; a null source is a source of its own, ordered last; rows
that repeat are separate rows; sources of size 0 get target 0; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from seedspread.llm.text import n_blank_words, shielded
from seedspread.runtime import materialize

#: Per-source rows up to which the source table is broadcast (about 60 bytes a row).
MAX_BROADCAST_SOURCES = 50_000
CYCLE = (1, 2, 3)


def with_size_and_hash(docs: DataFrame, seed: int = 0) -> DataFrame:
    """``docs`` with the columns the mix needs: ``_size``, ``_hash`` and ``_slice`` of the seeded order."""
    key = F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))))
    return docs.withColumns({"_size": n_blank_words(F.col("text")), "_hash": key}).withColumn("_slice", F.substring("_hash", 1, 3))


def water_fill(sources: DataFrame, max_epochs: int = 3, share: float = 1.0) -> DataFrame:
    """``sources(source, source_size, weight)`` → the same with ``target`` (double), capped at ``max_epochs`` sizes."""
    by_ratio = Window.orderBy(F.col("_cap") / F.col("weight"), "source")
    before = by_ratio.rowsBetween(Window.unboundedPreceding, -1)
    everything = Window.partitionBy()
    level = (F.col("_budget") - F.col("_cap_before")) / F.col("_weight_left")
    return (
        sources.withColumn("_cap", F.col("source_size") * F.lit(max_epochs))
        .withColumn("_budget", F.sum("source_size").over(everything) * F.lit(share))
        .withColumn("_cap_before", F.coalesce(F.sum("_cap").over(before), F.lit(0)))
        .withColumn("_weight_left", F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(before), F.lit(0)))
        .withColumn("_clamped", F.col("_cap") / F.col("weight") < level)
        .withColumn("_rest", F.min(F.when(~F.col("_clamped"), F.col("_cap_before"))).over(everything))
        .withColumn("_rest_weight", F.max(F.when(~F.col("_clamped"), F.col("_weight_left"))).over(everything))
        .withColumn("target", F.when(F.col("_clamped"), F.col("_cap").cast("double")).otherwise(F.col("weight") * ((F.col("_budget") - F.col("_rest")) / F.col("_rest_weight"))))
        .select("source", "source_size", "weight", "target")
    )


def source_plan(sized: DataFrame, max_epochs: int = 3, weights: DataFrame | None = None) -> DataFrame:
    """One row per source: size, weight, target, whole epochs, wanted remainder and the slice where it ends.

    ``weights(source, weight)`` may be given; otherwise sources in code point order weigh 1, 2, 3, repeating.
    """
    slices = materialize(sized.groupBy("source", "_slice").agg(F.sum("_size").alias("_slice_size")), "mix")
    sources = slices.groupBy("source").agg(F.sum("_slice_size").alias("source_size"))
    if weights is None:
        at = (F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1) % len(CYCLE)
        sources = sources.withColumn("weight", F.element_at(F.array(*map(F.lit, CYCLE)), at + 1))
    else:
        given = weights.select(F.col("source").alias("_given"), "weight")
        sources = sources.join(given, F.col("source").eqNullSafe(F.col("_given")), "left").drop("_given").fillna(0, ["weight"]).filter("weight > 0")
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    plan = water_fill(sources, max_epochs).withColumn("_whole", F.floor(rate)).withColumn("_wanted", (rate - F.col("_whole")) * F.col("source_size"))
    running = F.sum("_slice_size").over(Window.partitionBy("source").orderBy("_slice").rowsBetween(Window.unboundedPreceding, 0))
    ends = slices.withColumn("_upto", running).select(F.col("source").alias("_s"), "_slice", "_slice_size", "_upto")
    end = (
        ends.join(plan, F.col("source").eqNullSafe(F.col("_s")))
        .filter((F.col("_upto") >= F.col("_wanted")) & (F.col("_upto") - F.col("_slice_size") < F.col("_wanted")))
        .select("_s", F.col("_slice").alias("_end"), (F.col("_upto") - F.col("_slice_size")).alias("_end_from"))
    )
    return plan.join(end, F.col("source").eqNullSafe(F.col("_s")), "left").drop("_s").withColumn("_end", F.coalesce("_end", F.lit("")))


def mix(sized: DataFrame, max_epochs: int = 3, weights: DataFrame | None = None) -> DataFrame:
    """Rows of ``with_size_and_hash`` plus ``source_size, weight, target, taken``; the same input gives the same rows."""
    plan = materialize(source_plan(sized, max_epochs, weights), "mix").withColumnRenamed("source", "_s")
    if plan.count() <= MAX_BROADCAST_SOURCES:
        plan = F.broadcast(plan)
    rows = sized.join(plan, F.col("source").eqNullSafe(F.col("_s"))).drop("_s")
    takes = lambda extra: (F.col("_size") * (F.col("_whole") + extra.cast("long"))).alias("taken")
    clear = rows.filter("_slice <> _end").select("*", takes(F.col("_slice") < F.col("_end")))
    order = Window.partitionBy("source").orderBy("_hash", "_size").rowsBetween(Window.unboundedPreceding, 0)
    middle = F.col("_end_from") + F.sum("_size").over(order) - F.col("_size") / 2
    edge = rows.filter("_slice = _end").withColumn("_middle", middle).select(*rows.columns, takes(F.col("_middle") <= F.col("_wanted")))
    return clear.union(edge).drop("_hash", "_slice", "_whole", "_wanted", "_end", "_end_from")


@shielded
def mixed(docs: DataFrame, seed: int = 0, max_epochs: int = 3, weights: DataFrame | None = None) -> DataFrame:
    """``docs(doc_id, text, source, ...)`` plus ``source_size, weight, target, taken`` and ``times``, how often the mix takes a row.

    Any other column may have any name: the operator's own columns take free names, ``times`` the last.
    """
    out = mix(with_size_and_hash(docs, seed), max_epochs, weights)
    return out.withColumn("times", F.when(F.col("taken") > 0, (F.col("taken") / F.col("_size")).cast("int")).otherwise(0)).drop("_size")
