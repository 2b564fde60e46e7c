"""The stages of the corpus pipeline: each takes (spark, docs, sf_dir) and acts on all documents it is given."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seedspread.llm import decontaminate as contamination
from seedspread.llm import lines, minhash, mixing, quality
from seedspread.llm.text import BLANKS, fresh
from seedspread.runtime import table


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops the documents that the compression classifier rejects."""
    model = quality.fit(docs, table(spark, sf_dir, "labels"))
    scored = quality.score(docs, model)
    return scored.filter(F.col(scored.columns[-1]) == 1).select(*docs.columns)


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Cuts later copies of lines out of the texts; a document goes only when nothing but blanks is left of it."""
    cut = lines.dedup_lines(docs)
    removed = F.col(cut.columns[-1])
    left = (removed == 0) | (F.length(F.regexp_replace("text", BLANKS, "")) > 0)
    size = F.when(removed > 0, F.length("text").cast("long")).otherwise(F.col("n_chars"))
    return cut.filter(left).withColumn("n_chars", size).select(*docs.columns)


def minhash_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document with the smallest id of each group of near duplicates."""
    return minhash.keep_one(docs).select(*docs.columns)


def benchmark_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops the documents that hold a benchmark window."""
    return contamination.decontaminate(docs, table(spark, sf_dir, "benchmark")).select(*docs.columns)


def mix_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row per time that the mix takes a document, numbered by ``epoch`` (with an underscore for each clash)."""
    mixed = mixing.mixed(docs)
    times = F.col(mixed.columns[-1])
    return mixed.filter(times > 0).select(*docs.columns, F.explode(F.sequence(F.lit(1), times)).alias(fresh(docs, "epoch")[0]))


STAGES = [
    ("quality_classifier", quality_stage),
    ("line_dedup", line_stage),
    ("minhash_near_dedup", minhash_stage),
    ("benchmark_decontamination", benchmark_stage),
    ("source_mix", mix_stage),
]
