"""Every stage of the corpus pipeline on clashing columns and empty tables, and the whole against its operators' brute force."""

import numpy as np
import pytest
from pyspark.sql import functions as F
from test_operators import DOCS, brute_lines, brute_links, components, documents, prose

import corpus_pipeline
from seedspread.llm import stages
from seedspread.llm.stages import STAGES

CLASHING = ["score", "predicted", "n_removed", "doc", "th", "gone", "_d", "_t", "_gone", "target", "weight", "source_size", "taken", "_size", "_hash", "_slice", "_hit_id", "epoch", "node", "component_id", "kept"]


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    """Documents with good and bad prose, repeated lines, copies and passages of the benchmark."""
    rng = np.random.default_rng(21)
    root = tmp_path_factory.mktemp("tables")
    good = ["\n".join(prose(rng, 25, 300) for _ in range(4)) for _ in range(60)]
    bad = [" ".join("".join(rng.choice(list("!#$%&*+=<>?"), 6)) for _ in range(60)) for _ in range(40)]
    item = prose(rng, 40, 5_000)
    texts = good + bad + [good[3], good[5] + " and more", good[7] + "\n" + good[8].split("\n")[0], prose(rng, 60, 300) + " " + item, None, ""]
    documents(spark, texts, [f"s{k % 4}" for k in range(len(texts))]).write.parquet(f"file://{root}/documents.parquet")
    spark.createDataFrame([(k, int(k < 60), 0) for k in range(100)], "doc_id long, quality int, toxic int").write.parquet(f"file://{root}/labels.parquet")
    spark.createDataFrame([(0, item)], "item_id long, text string").write.parquet(f"file://{root}/benchmark.parquet")
    return f"file://{root}", texts


@pytest.mark.parametrize("k", range(len(STAGES)))
def test_stage_keeps_clashing_columns(spark, folder, k):
    root, _ = folder
    docs = spark.read.parquet(f"{root}/documents.parquet").limit(30)
    plain = STAGES[k][1](spark, docs, root)
    more = STAGES[k][1](spark, docs.select("*", *[F.lit(-7 - i).alias(c) for i, c in enumerate(CLASHING)]), root)
    assert more.columns[: len(docs.columns) + len(CLASHING)] == [*docs.columns, *CLASHING]
    values = [tuple(-7 - i for i in range(len(CLASHING)))] * more.count()
    assert [tuple(r) for r in more.select(*CLASHING).collect()] == values
    assert sorted(map(str, more.select(*docs.columns).collect())) == sorted(map(str, plain.select(*docs.columns).collect()))


@pytest.mark.parametrize("k", range(len(STAGES)))
def test_stage_on_empty_documents(spark, folder, k):
    root, _ = folder
    assert STAGES[k][1](spark, spark.createDataFrame([], DOCS), root).count() == 0


def test_stages_in_turn_match_brute_force(spark, folder):
    root, texts = folder
    docs = spark.read.parquet(f"{root}/documents.parquet")
    kept = {r["doc_id"]: r["text"] for r in stages.quality_stage(spark, docs, root).collect()}
    assert set(range(60)) <= set(kept) and len(set(kept) & set(range(60, 100))) <= 4
    ids = sorted(kept)
    want = {k: t for k, t in zip(ids, brute_lines([kept[k] for k in ids]), strict=True) if t == kept[k] or (t or "").strip()}
    after = spark.createDataFrame([(k, kept[k], "en", "s", 1) for k in ids], DOCS)
    cut = {r["doc_id"]: r["text"] for r in stages.line_stage(spark, after, root).collect()}
    assert cut == want
    ids = sorted(cut)
    low = components(len(ids), brute_links([cut[k] for k in ids]))
    once = [ids[k] for k in range(len(ids)) if low[k] == k]
    left = {r["doc_id"] for r in stages.minhash_stage(spark, spark.createDataFrame([(k, cut[k], "en", "s", 1) for k in ids], DOCS), root).collect()}
    assert sorted(left) == once
    clean = {r["doc_id"] for r in stages.benchmark_stage(spark, docs.filter(F.col("doc_id").isin(once)), root).collect()}
    assert clean == set(once) - {103}


def test_whole_pipeline(spark, folder):
    root, texts = folder
    rows = corpus_pipeline.run(spark, root)
    assert rows.columns == ["doc_id", "text", "lang", "source", "n_chars", "epoch"]
    got = rows.collect()
    by = {}
    for r in got:
        by.setdefault(r["doc_id"], []).append(r["epoch"])
    assert all(sorted(v) == list(range(1, len(v) + 1)) and len(v) <= 3 for v in by.values())
    assert 103 not in by and 100 not in by and len(set(by) & set(range(60, 100))) <= 4
    assert sorted(map(str, got)) == sorted(map(str, corpus_pipeline.run(spark, root).collect()))
