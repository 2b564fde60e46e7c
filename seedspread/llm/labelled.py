"""Bounded, seeded samples of labelled documents for fitting the classifiers."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Longest text, in characters, that a fitting sample takes; scoring has no such bound.
MAX_SAMPLE_CHARS = 20_000


def sample(docs: DataFrame, labels: DataFrame, label: str, per_class: int, allowed: Column | None = None) -> list[tuple[int, str, int]]:
    """At most ``per_class`` rows ``(doc_id, text, label)`` of each of the classes 0 and 1, in seeded hash order.

    ``allowed`` restricts the rows of ``labels`` that may be used. The sample is at most
    ``2 * per_class * MAX_SAMPLE_CHARS`` characters.
    """
    rows = labels.select(F.col("doc_id").alias("_id"), F.col(label).cast("int").alias("_y"))
    if allowed is not None:
        rows = rows.filter(allowed)
    order = F.md5(F.col("_id").cast("string"))
    picked = None
    for y in (0, 1):
        own = rows.filter((F.col("_y") == y) & F.col("_id").isNotNull()).orderBy(order, "_id").limit(2 * per_class)
        picked = own if picked is None else picked.union(own)
    short = docs.select("doc_id", "text").filter(F.col("text").isNotNull() & (F.length("text") <= MAX_SAMPLE_CHARS))
    found = short.join(F.broadcast(picked), F.col("doc_id") == F.col("_id")).select("doc_id", "text", F.col("_y").alias("y"))
    out: list[tuple[int, str, int]] = []
    for y in (0, 1):
        own = found.filter(F.col("y") == y).orderBy(F.md5(F.col("doc_id").cast("string")), "doc_id", "text").limit(per_class)
        out += [(r["doc_id"], r["text"], r["y"]) for r in own.collect()]
    return out


def is_held_out(doc_id: Column) -> Column:
    """Rows that no label may be learnt from: crc32 of the id's text is divisible by 5."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(False))
