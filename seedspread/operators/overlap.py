"""Members that share a group, one row per member: how many others it is linked with, and its component.

A group of n members stands for n² links, which are never listed. Groups with the same members count once, members
of the same groups share one count, and the union of a member's groups is formed in memory, so what is shuffled
follows the memberships and not the links.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seedspread.operators.components import connected_components
from seedspread.runtime import materialize

#: Distinct sets of groups that one task counts.
CHUNK_SETS = 20_000


def _union_sizes(sets: pd.DataFrame, groups: pd.DataFrame) -> pd.DataFrame:
    """Size of the union of each row's groups, less the member itself."""
    if sets.empty:
        return pd.DataFrame({"members": pd.Series(dtype="object"), "n_links": pd.Series(dtype="int64")})
    lists = list(groups.list)
    ids, at = np.unique(np.concatenate(lists), return_inverse=True)
    ends = np.cumsum([len(x) for x in lists])
    spans = {g: at[hi - len(x) : hi] for g, x, hi in zip(groups.g, lists, ends, strict=True)}
    seen, sizes = np.full(len(ids), -1, np.int64), np.empty(len(sets), np.int64)
    for k, own in enumerate(sets.groups):
        size = 0
        for g in own:
            fresh = spans[g][seen[spans[g]] != k]
            seen[fresh] = k
            size += len(fresh)
        sizes[k] = size - 1
    return pd.DataFrame({"members": sets.members, "n_links": sizes})


def linked_members(pairs: DataFrame, chunk_sets: int = CHUNK_SETS) -> DataFrame:
    """``pairs(m, g)`` → ``(m, n_links, component)`` of the members that share a group with another one.

    ``component`` is the smallest member reachable by links. Nulls are dropped, repeated pairs count once.
    """
    held = pairs.filter("m is not null and g is not null").groupBy("g").agg(F.array_sort(F.collect_set("m")).alias("members"))
    classes = held.filter(F.size("members") > 1).select("members").distinct()
    classes = materialize(classes.select(F.monotonically_increasing_id().alias("g"), "members"), "groups")
    owned = classes.select("g", F.explode("members").alias("m")).groupBy("m").agg(F.array_sort(F.collect_list("g")).alias("groups"))
    sets = materialize(owned.groupBy("groups").agg(F.collect_list("m").alias("members")), "sets")
    chunks = max(8, -(-sets.count() // chunk_sets))
    dealt = sets.withColumn("chunk", F.pmod(F.xxhash64("groups"), F.lit(chunks)))
    needed = dealt.select(F.col("chunk").alias("of"), F.explode("groups").alias("g")).distinct().join(classes, "g").select("of", "g", F.col("members").alias("list"))
    counted = dealt.groupBy("chunk").cogroup(needed.groupBy("of")).applyInPandas(_union_sizes, "members array<long>, n_links long")
    links = counted.select(F.explode("members").alias("m"), "n_links")
    low = connected_components(classes.select(F.col("members")[0].alias("a"), F.explode(F.slice("members", 2, F.size("members") - 1)).alias("b")))
    return links.join(low.withColumnRenamed("v", "m"), "m")
