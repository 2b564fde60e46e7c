"""Benchmark decontamination by a broadcast hash set of benchmark word windows, DataFrame functions only.

Every position of every document is hashed with the words that follow it and probed against the hashes of
all windows of the benchmark; a hit is verified on the words themselves before it counts. The scan, the
explosion into positions and the probe are one fused stage, and only hits and one row per document leave
it, so what is shuffled does not grow with the number of words.

Cases: null and empty texts have no words and no hits; an item of fewer words than a window, but not none,
is one window of its own length; rows that repeat give the same result each; an empty benchmark leaves
every document clean.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seedspread.llm.sizes import few
from seedspread.llm.text import RAW_SEPARATORS, shielded, words
from seedspread.runtime import materialize

WINDOW = 10
#: Distinct windows up to which their table is broadcast (about 100 bytes each); beyond it the probe is a shuffled join.
MAX_BROADCAST_WINDOWS = 1_000_000


def benchmark_windows(benchmark: DataFrame, width: int = WINDOW) -> DataFrame:
    """``(length, code, phrase, items)``: the distinct windows, the hash of their words and who holds them."""
    items = benchmark.select(F.col("item_id").cast("string").alias("item"), words(F.col("text")).alias("w")).filter(F.size("w") > 0)
    spans = items.select("item", "w", F.explode(F.sequence(F.lit(1), F.greatest(F.size("w") - width + 1, F.lit(1)))).alias("at"))
    cut = spans.select("item", F.slice("w", F.col("at"), width).alias("p"))
    return (
        cut.groupBy(F.size("p").alias("length"), F.xxhash64(F.size("p"), *[F.get("p", F.lit(k)) for k in range(width)]).alias("code"), F.array_join("p", " ").alias("phrase"))
        .agg(F.collect_set("item").alias("items"))
    )


def scan(docs: DataFrame, benchmark: DataFrame, width: int = WINDOW) -> DataFrame:
    """``(doc_id, text hash, n_words, n_hit, items)`` for every row of ``docs(doc_id, text)``.

    Rows with equal id and text share one output row with ``copies`` of them.
    """
    table = materialize(benchmark_windows(benchmark, width), "windows")
    sizes = [r["length"] for r in table.groupBy("length").count().collect()]  # at most ``width`` rows
    bounded = table.count() <= MAX_BROADCAST_WINDOWS
    if len(sizes) == 0:
        sizes = [width]
    got = lambda k: F.get("w", F.col("pos") + k)
    code = {n: F.xxhash64(F.lit(n), *[got(k) if k < n else F.lit(None).cast("string") for k in range(width)]) for n in sizes}
    fit = lambda n: F.col("pos") + n <= F.col("n_words")
    base = docs.select("doc_id", F.xxhash64("text").alias("text_hash"), words(F.col("text")).alias("w")).withColumn("n_words", F.size("w").cast("long"))
    at = base.select("doc_id", "text_hash", "n_words", "w", F.posexplode_outer("w").alias("pos", "_word"))
    if len(sizes) == 1:
        n = sizes[0]
        at = at.withColumns({"len": F.lit(n), "code_": F.when(fit(n), code[n])})
    else:
        each = F.array(*[F.struct(F.lit(n).alias("len"), F.when(fit(n), code[n]).alias("code_")) for n in sizes])
        at = at.select("doc_id", "text_hash", "n_words", "w", "pos", F.inline(each))
    windows = table.select("code", "phrase", F.col("items").alias("found"))
    if bounded:
        probed = at.join(F.broadcast(windows), F.col("code") == F.col("code_"), "left")
    else:
        # ids, places and codes alone are shuffled; only places that meet a window fetch its words again
        spots = at.filter("code_ is not null").select("doc_id", "text_hash", F.col("pos").alias("at_pos"), F.col("len").alias("at_len"), "code_")
        met = spots.join(windows, F.col("code") == F.col("code_")).drop("code_").distinct().withColumnsRenamed({"doc_id": "at_doc", "text_hash": "at_hash"})
        same = F.col("doc_id").eqNullSafe(F.col("at_doc")) & F.col("text_hash").eqNullSafe(F.col("at_hash"))
        by_doc = met.groupBy("at_doc", "at_hash").agg(F.collect_list(F.struct("at_pos", "at_len", "code", "phrase", "found")).alias("met"))
        head = F.array(F.struct(F.lit(0).alias("at_pos"), F.lit(sizes[0]).alias("at_len"), F.lit(None).cast("long").alias("code"), F.lit(None).cast("string").alias("phrase"), F.lit(None).cast("array<string>").alias("found")))
        found = base.join(by_doc, same, "left").select("doc_id", "text_hash", "n_words", "w", F.inline(F.concat(head, F.coalesce("met", F.slice(head, 2, 1)))))
        probed = found.withColumnsRenamed({"at_pos": "pos", "at_len": "len"})
    true_hit = F.col("phrase") == F.array_join(F.slice("w", F.col("pos") + 1, F.col("len")), " ")
    kept = probed.withColumn("hit", F.coalesce(F.col("code").isNotNull() & true_hit, F.lit(False)))
    if bounded:
        kept = kept.filter("pos is null or pos = 0 or code is not null")
        first = F.coalesce(F.col("pos") == 0, F.lit(True)) & (F.col("len") == sizes[0])
    else:
        first = F.col("code").isNull()
    # one long line of hits per document: positions are gathered as a set, so a window held by several items counts once
    per_doc = kept.groupBy("doc_id", "text_hash", "n_words").agg(
        F.sum(F.when(first, 1).otherwise(0)).alias("copies_"),
        F.collect_set(F.when(F.col("hit"), F.struct("pos", "len"))).alias("spans"),
        F.array_distinct(F.flatten(F.collect_set(F.when(F.col("hit"), F.col("found"))))).alias("items"),
    )
    return per_doc.withColumn("spans", F.array_sort("spans"))


def covered(spans, end=lambda s: s["pos"] + s["len"]):
    """Number of words in the union of sorted spans."""
    zero = F.struct(F.lit(0).cast("long").alias("total"), F.lit(0).cast("long").alias("upto"))
    def step(acc, s):
        fresh = F.greatest(end(s).cast("long") - F.greatest(acc["upto"], s["pos"].cast("long")), F.lit(0).cast("long"))
        return F.struct((acc["total"] + fresh).alias("total"), F.greatest(acc["upto"], end(s).cast("long")).alias("upto"))
    return F.aggregate(spans, zero, step, lambda acc: acc["total"])


@shielded
def decontaminate(docs: DataFrame, benchmark: DataFrame, width: int = WINDOW, remove: str = "documents") -> DataFrame:
    """``docs`` without its contaminated documents, or with the hit words cut out (``remove="spans"``).

    Cutting a span also cuts the separators that follow each of its words. Other columns are kept as they are.
    """
    hits = scan(docs.select("doc_id", "text"), benchmark, width).filter(F.size("spans") > 0).select(
        F.col("doc_id").alias("_hit_id"), F.col("text_hash").alias("_hit_hash"), F.col("spans").alias("_spans"))
    if remove == "documents":
        hits = few(hits.drop("_spans"))
    same = F.col("doc_id").eqNullSafe(F.col("_hit_id")) & (F.xxhash64("text") == F.col("_hit_hash"))
    if remove == "documents":
        return docs.join(hits, same, "left_anti")
    lead = F.regexp_extract("text", f"^[{RAW_SEPARATORS}]*", 0)
    tokens = F.regexp_extract_all("text", F.lit(f"([^{RAW_SEPARATORS}]+[{RAW_SEPARATORS}]*)"), 1)
    left = F.filter(F.transform(tokens, lambda t, i: F.struct(t.alias("t"), i.alias("i"))), lambda x: ~F.exists("_spans", lambda s: (s["pos"] <= x["i"]) & (x["i"] < s["pos"] + s["len"])))
    cleaned = F.concat(lead, F.array_join(F.transform(left, lambda x: x["t"]), ""))
    joined = docs.join(hits, same, "left")
    return joined.withColumn("text", F.when(F.col("_spans").isNull(), F.col("text")).otherwise(cleaned)).drop("_hit_id", "_hit_hash", "_spans")
