"""The ten operator queries, each over its whole table, and the SQL that states the same result."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seedspread.llm import oracles
from seedspread.runtime import table


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    from seedspread.llm.licenses import license_scan

    return license_scan(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op2_toxic_severity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from seedspread.llm.toxicity import fit, severity

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return severity(docs, fit(docs, table(spark, sf_dir, "labels")))


def op3_embedding_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from seedspread.llm.embeddings import near_vectors

    return near_vectors(table(spark, sf_dir, "embeddings"))


def op4_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    from seedspread.llm.pii import find, fit

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return find(docs, fit(docs))


def op5_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from seedspread.llm.lines import dedup_lines

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return dedup_lines(docs).select("doc_id", "n_removed", F.length("text").cast("long").alias("n_chars"), F.sha2(F.coalesce("text", F.lit("")), 256).alias("text_sha256"), "text")


def op6_warc_archive(spark: SparkSession, sf_dir: str) -> DataFrame:
    from seedspread.llm.warc import SCHEMA, archive, page_id_of, read_archive
    from seedspread.runtime import scratch_path

    path = scratch_path(spark, "warc")
    archive(table(spark, sf_dir, "pages"), path)
    stored = read_archive(spark, path, SCHEMA)
    stated = F.regexp_replace("payload_digest", "^sha256:", "")
    # a response's figures come from the payload that was read back, a revisit's from its headers
    read_back = F.col("payload").isNotNull()
    return stored.select(
        page_id_of(F.col("record_id")).alias("page_id"),
        F.when(read_back, F.octet_length("payload").cast("long")).otherwise(F.col("payload_length")).alias("payload_bytes"),
        F.when(read_back, F.sha2("payload", 256)).otherwise(stated).alias("payload_digest"),
        "record_type", page_id_of(F.col("refers_to")).alias("refers_to"),
    )


def op7_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from seedspread.llm.decontaminate import covered, scan

    docs, benchmark = table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")
    found = scan(docs.select("doc_id", "text"), benchmark.select("item_id", "text"))
    rows = found.withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("copies_").cast("int"))))
    n_hit = covered(F.col("spans"))
    return rows.select(
        "doc_id", "n_words", n_hit.alias("n_hit"), F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join(F.array_sort("items"), ","), 256).alias("items_sha256"), (F.size("spans") > 0).alias("contaminated"),
    )


def op8_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from seedspread.llm.minhash import near_duplicates

    return near_duplicates(table(spark, sf_dir, "documents"))


def op9_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    from seedspread.llm.mixing import mix, with_size_and_hash
    from seedspread.runtime import materialize

    docs = table(spark, sf_dir, "documents").select("doc_id", "source", "text")
    sized = materialize(with_size_and_hash(docs).drop("text"), "mix")
    return mix(sized).select("doc_id", F.col("_size").alias("size"), "source_size", "target", "taken", "source")


def op10_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    from seedspread.llm.labelled import is_held_out
    from seedspread.llm.quality import fit, score

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    scored = score(docs, fit(docs, table(spark, sf_dir, "labels")))
    return scored.select("doc_id", is_held_out(F.col("doc_id")).alias("held_out"), "score", "predicted")


QUERIES = {
    "op1_license_scan": op1_license_scan,
    "op2_toxic_severity": op2_toxic_severity,
    "op3_embedding_near_dedup": op3_embedding_near_dedup,
    "op4_personal_data": op4_personal_data,
    "op5_line_dedup": op5_line_dedup,
    "op6_warc_archive": op6_warc_archive,
    "op7_benchmark_decontamination": op7_benchmark_decontamination,
    "op8_minhash_near_dedup": op8_minhash_near_dedup,
    "op9_source_mix": op9_source_mix,
    "op10_quality_classifier": op10_quality_classifier,
}

ORACLES = {
    "op1_license_scan": oracles.licenses(),
    "op3_embedding_near_dedup": oracles.VECTORS,
    "op6_warc_archive": oracles.ARCHIVE,
    "op7_benchmark_decontamination": oracles.DECONTAMINATE,
    "op8_minhash_near_dedup": oracles.NEAR_DUPLICATES,
    "op9_source_mix": oracles.MIX,
}
