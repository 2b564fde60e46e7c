"""Edge cases and brute-force checks of the text operators on small fixtures."""

import hashlib
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from seedspread.llm import decontaminate, embeddings, hashing, labelled, licenses, lines, minhash, mixing, pii, quality, tagger, toxicity, warc

FOLD = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
BLANK = re.compile("[^\x20\x09-\x0d]+")
DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def documents(spark, texts, sources=None):
    rows = [(k, t, "en", None if sources is None else sources[k], None if t is None else len(t)) for k, t in enumerate(texts)]
    return spark.createDataFrame(rows, DOCS)


def prose(rng, n, vocabulary=400):
    return " ".join(f"w{x}" for x in rng.integers(0, vocabulary, n))


def shingle_set(text):
    w = BLANK.findall((text or "").translate(FOLD))
    return {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set()


def components(n, links):
    low = list(range(n))
    changed = True
    while changed:
        changed = False
        for a, b in links:
            m = min(low[a], low[b])
            if low[a] != m or low[b] != m:
                low[a] = low[b] = m
                changed = True
    return low


@pytest.fixture(scope="module")
def corpus():
    """Copies, near copies by chains, shared passages, nulls, empties, short and long texts."""
    rng = np.random.default_rng(1)
    base = [prose(rng, 120) for _ in range(25)]
    texts = list(base)
    for k in range(8):
        words = base[k].split(" ")
        for step in range(6):
            words[(step * 17 + k) % 100] = f"x{step}"
            texts.append(" ".join(words))
    passage = prose(rng, 60)
    texts += [passage + " " + prose(rng, int(m)) for m in rng.integers(15, 60, 12)]
    texts += [base[0], base[0], base[0].upper(), None, "", "   ", "one", "one", "Two words", "two  words", "a b c d e", prose(rng, 20_000)]
    return texts


def brute_links(texts, percent=75):
    sets = [shingle_set(t) for t in texts]
    return [(a, b) for a in range(len(texts)) for b in range(a) if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b])]


@pytest.mark.parametrize("hot", [20_000, 3])
def test_near_duplicates_match_brute_force(spark, corpus, hot):
    got = {r["doc_id"]: r for r in minhash.near_duplicates(documents(spark, corpus), hot_bucket=hot).collect()}
    want = components(len(corpus), brute_links(corpus))
    for k, text in enumerate(corpus):
        assert got[k]["n_shingles"] == len(shingle_set(text))
        assert (got[k]["component_id"], got[k]["kept"]) == (want[k], want[k] == k), k


@pytest.mark.parametrize(("cell_docs", "apart"), [(10_000, 1), (7, 1), (4, 9)])
def test_links_across_components(spark, corpus, cell_docs, apart):
    """One hub tied to every document: in one cell, by prefixes where much is outside the main team, in chunks where little is."""
    links = brute_links(corpus)
    want = components(len(corpus), links)
    ids = [k for k, t in enumerate(corpus) if shingle_set(t)]
    # with ``apart`` 9, all but three documents are already in their component or in one large team
    team = {k: k if apart == 1 or k in (26, 30, 33) else 0 for k in ids}
    ties = spark.createDataFrame([(ids[0], k) for k in ids[1:]], "a long, b long")
    comps = spark.createDataFrame([(k, team[k]) for k in ids], "node long, component long")
    sizes = spark.createDataFrame([(k, len(shingle_set(corpus[k]))) for k in ids], "node long, n_shingles long")
    texts = documents(spark, corpus).select(F.col("doc_id").alias("node"), "text")
    found = [tuple(r) for r in minhash.across_components(ties, comps, sizes, texts, 75, 5, cell_docs=cell_docs).collect()]
    assert {tuple(sorted(x)) for x in found} <= {tuple(sorted(x)) for x in links}
    inside = [(k, next(o for o in ids if team[o] == team[k])) for k in ids]
    assert components(len(corpus), inside + found) == components(len(corpus), inside + links)
    if apart == 1:
        assert components(len(corpus), found) == want


def test_one_doc_id_with_two_texts(spark):
    rng = np.random.default_rng(5)
    one, two = prose(rng, 80), prose(rng, 80)
    rows = [(7, one), (7, two), (3, two + " end"), (9, one), (9, one)]
    docs = spark.createDataFrame([(k, t, "en", "s", 1) for k, t in rows], DOCS)
    got = sorted((r["doc_id"], r["component_id"], r["kept"]) for r in minhash.near_duplicates(docs).collect())
    assert got == [(3, 3, True), (7, 3, False), (7, 7, True), (9, 7, False), (9, 7, False)]
    assert sorted(r["doc_id"] for r in minhash.keep_one(docs.withColumn("th", F.lit(1)).withColumn("node", F.lit(2))).collect()) == [3, 7]


def test_long_text_is_split_in_parts(monkeypatch):
    data = ("alpha beta  gamma delta " * 50 + "x" * 300 + " end").encode()
    column = pa.array([data.decode(), "two words", data.decode() + " more"])
    (row, end, raw, cuts), = hashing.pieces(column)
    whole = hashing.Splitter().words(raw, cuts)
    monkeypatch.setattr(hashing, "PART_BYTES", 97)
    parts = hashing.Splitter().words(raw, cuts)
    assert np.array_equal(whole[0], parts[0]) and np.array_equal(whole[1], parts[1])


def test_near_duplicates_empty_null_and_repeated(spark):
    none = spark.createDataFrame([], DOCS)
    assert minhash.near_duplicates(none).count() == 0
    odd = spark.createDataFrame([(None, "a b c d e f", "en", "s", 1), (5, "a b c d e f", "en", "s", 1), (5, "a b c d e f", "en", "s", 1)], DOCS)
    rows = minhash.near_duplicates(odd).collect()
    assert sorted((r["doc_id"] is None, r["component_id"]) for r in rows if r["doc_id"] is not None) == [(False, 5), (False, 5)]
    assert len(rows) == 3
    assert minhash.keep_one(odd.withColumn("component_id", F.lit(7))).columns == [*odd.columns, "component_id"]


def brute_lines(texts, percent=75):
    seen, out = [], []
    for t in texts:
        kept = []
        for line in [] if t is None else t.split("\n"):
            words = BLANK.findall(line.translate(FOLD))
            if len(words) < lines.MIN_WORDS:
                kept.append(line)
                continue
            s = shingle_set(line)
            if not any(100 * len(s & o) >= percent * len(s | o) for o in seen):
                kept.append(line)
            seen.append(s)
        out.append(None if t is None else "\n".join(kept))
    return out


@pytest.mark.parametrize("hot", [8192, 4])
def test_line_dedup_matches_brute_force(spark, hot):
    rng = np.random.default_rng(3)
    pool = [prose(rng, int(n), 60) for n in rng.integers(4, 40, 30)]
    for k in range(60):
        w = pool[k % 30].split(" ")
        w[rng.integers(len(w))] = f"z{k}"
        pool.append(" ".join(w))
    texts = ["\n".join([pool[x] for x in rng.integers(0, len(pool), 8)] + ["", "x y", "  "]) for _ in range(40)] + [None, "", "\n\n", "tail\n"]
    got = {r["doc_id"]: r["text"] for r in lines.dedup_lines(documents(spark, texts), hot_group=hot).collect()}
    assert [got[k] for k in range(len(texts))] == brute_lines(texts)
    assert lines.dedup_lines(spark.createDataFrame([], DOCS)).count() == 0


def test_line_dedup_takes_short_lines(spark):
    texts = ["All rights reserved.\nok\na b c d e f", "all  rights reserved.\nrights reserved.\n\nok", "ok\nAll rights reserved.", "rights\nok then", None, "ok\n \n"]
    seen, want = [], []
    for t in texts:
        kept = []
        for line in [] if t is None else t.split("\n"):
            s = shingle_set(line)
            if not s or not any(100 * len(s & o) >= 75 * len(s | o) for o in seen):
                kept.append(line)
            seen += [s] if s else []
        want.append(None if t is None else "\n".join(kept))
    rows = {r["doc_id"]: (r["text"], r["n_removed"]) for r in lines.dedup_lines(documents(spark, texts)).collect()}
    assert [rows[k][0] for k in range(len(texts))] == want
    assert [rows[k][1] for k in range(len(texts))] == [0, 2, 2, 0, 0, 1]


@pytest.mark.parametrize("limit", [1_000_000, 0])
def test_decontamination_matches_brute_force(spark, limit, monkeypatch):
    monkeypatch.setattr(decontaminate, "MAX_BROADCAST_WINDOWS", limit)
    rng = np.random.default_rng(4)
    items = [prose(rng, 30, 50), prose(rng, 12, 50), "Tiny ITEM", "", None, "w1 w1"]
    texts = [prose(rng, 80, 50) for _ in range(10)] + [prose(rng, 9) + " " + items[0].upper() + "! " + items[0], "a tiny,item b", None, "", "w1 w1 w1", "É tiny item"]
    word = re.compile("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+")
    split = lambda t: word.findall((t or "").translate(FOLD))
    windows = {k: {tuple(w[i : i + 10]) for i in range(max(1, len(w) - 9))} if (w := split(t)) else set() for k, t in enumerate(items)}
    bench = spark.createDataFrame(list(enumerate(items)), "item_id long, text string")
    docs = documents(spark, texts)
    got = {r["doc_id"]: r for r in decontaminate.scan(docs.select("doc_id", "text"), bench).withColumn("n_hit", decontaminate.covered(F.col("spans"))).collect()}
    for k, text in enumerate(texts):
        w, hit, who = split(text), set(), set()
        for item, ws in windows.items():
            for p in ws:
                for i in range(len(w) - len(p) + 1):
                    if tuple(w[i : i + len(p)]) == p:
                        hit |= set(range(i, i + len(p)))
                        who.add(str(item))
        assert (got[k]["n_words"], got[k]["n_hit"], set(got[k]["items"])) == (len(w), len(hit), who), k
    clean = decontaminate.decontaminate(docs, bench)
    assert clean.columns == docs.columns and {r["doc_id"] for r in clean.collect()} == {k for k in got if got[k]["n_hit"] == 0}
    cut = {r["doc_id"]: r["text"] for r in decontaminate.decontaminate(docs, bench, remove="spans").collect()}
    assert cut[11] == "a b" and cut[12] is None
    assert decontaminate.scan(docs.select("doc_id", "text"), bench.filter("item_id < 0")).filter(F.size("spans") > 0).count() == 0


def test_license_scan(spark):
    grant = "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation, to deal in the software without restriction"
    wrapped = grant.replace("free of charge, to", "free of charge,\n to").replace("of this software", "of this\nsoftware")
    gpl = "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation"
    texts = [
        "Released under the MIT License.", "mit license mit LICENSE", "CC-BY", "gnu general public", None, "", "x\nThis work is licensed under the GNU General Public License, version 3.\ny", grant,
        "Released under the GNU General Public License.", "licensed under CC BY SA 4.0", "Licensed under the BSD license, version 2.0", gpl, wrapped, "released " + "filler " * 40 + "under the license", gpl.replace("General", "Lesser General"),
    ]
    rows = {r["doc_id"]: r for r in licenses.license_scan(documents(spark, texts)).collect()}
    assert (rows[1]["n_words"], rows[1]["n_base"], rows[1]["first_word"], rows[1]["last_word"]) == (4, 2, 0, 2)
    assert [rows[k]["base_labels"] for k in range(8)] == ["mit", "mit", "cc-by", "", "", "", "gpl", ""]
    assert rows[7]["labels"] == "mit" and 0.8 <= rows[7]["score"] < 1
    assert [rows[k]["labels"] for k in range(8, 15)] == ["gpl", "cc-by,cc-by-sa", "", "gpl", "mit", "", "lgpl"]
    assert rows[12]["score"] == rows[7]["score"] and rows[13]["score"] == 0
    assert rows[4]["n_words"] == 0 and rows[4]["first_word"] is None and rows[5]["score"] == 0
    assert licenses.license_scan(spark.createDataFrame([], DOCS)).count() == 0
    assert licenses.license_scan(documents(spark, ["word " * 300_000 + "released under the mit license"])).first()["labels"] == "mit"


def test_license_blocks_stand_around_every_anchor(spark):
    grant = "Permission is hereby given, free of charge, to any person obtaining a copy of this software and associated documentation files, to deal in the software without restriction"
    spread = "This Source Code Form " + "filler " * 10 + "is subject to the terms of the Mozilla Public License, v. 2.0."
    bsd = "Redistributions and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"
    texts = [grant, spread, bsd, grant.replace("software", "thing").replace("any person", "you").replace("free of charge", "gratis").replace("documentation files", "papers"), spread.replace("Mozilla", "")]
    rows = {r["doc_id"]: r for r in licenses.license_scan(documents(spark, texts)).collect()}
    assert [rows[k]["labels"] for k in range(5)] == ["mit", "mpl", "bsd", "", ""]
    assert all(0.8 <= rows[k]["score"] <= 1 for k in range(3)) and rows[3]["score"] == rows[4]["score"] == 0
    for t in licenses.TEMPLATES:
        own = set(t[1].split(" "))
        assert len(own & set(licenses.anchors(t))) > len(own) - licenses.needed(len(own), licenses.PERCENT)


def test_mixing_targets(spark):
    rng = np.random.default_rng(5)
    sizes = rng.integers(1, 60, 400)
    texts = [" ".join(["w"] * int(s)) for s in sizes] + [None, ""]
    sources = [["a", "b", "c", "d", None][k % 5] if k % 50 else "small" for k in range(402)]
    rows = mixing.mix(mixing.with_size_and_hash(documents(spark, texts, sources))).collect()
    total = sum(int(s) for s in sizes)
    by = {}
    for r in rows:
        x = by.setdefault(r["source"], [0, 0, r["target"], 0])
        x[0] += r["_size"]
        x[1] += r["taken"]
        x[3] = max(x[3], r["_size"])
        assert r["taken"] <= 3 * r["_size"] and (r["_size"] == 0 or r["taken"] % r["_size"] == 0)
    assert abs(sum(x[2] for x in by.values()) - total) < 1e-6 * total
    assert all(abs(x[1] - x[2]) <= x[3] and x[2] <= 3 * x[0] + 1e-9 for x in by.values())
    assert by["small"][2] == 3 * by["small"][0]
    again = mixing.mix(mixing.with_size_and_hash(documents(spark, texts, sources))).collect()
    assert sorted(map(str, rows)) == sorted(map(str, again))
    assert mixing.mix(mixing.with_size_and_hash(spark.createDataFrame([], DOCS))).count() == 0


def test_embeddings_match_brute_force(spark):
    rng = np.random.default_rng(6)
    base = rng.standard_normal((40, 16))
    vectors = [base[k % 40] + rng.standard_normal(16) * [0.02, 0.05, 0.09][k % 3] for k in range(200)] + [base[0], base[0], np.zeros(16), np.full(16, np.nan)]
    rows = [(k, [float(x) for x in v], k % 2) for k, v in enumerate(vectors)]
    rows += [(len(rows), None, 0), (len(rows) + 1, [1.0, None], 0), (len(rows) + 2, [1.0, 2.0], None), (len(rows) + 3, [], 1), (len(rows) + 4, [3.0, 4.0], 1), (len(rows) + 5, [6.0, 8.0], 1)]
    ok = {i: np.array(v, float) / np.linalg.norm(v) for i, v, y in rows if v and y is not None and None not in v and np.isfinite(v).all() and any(v)}
    label = {i: y for i, _, y in rows}
    links = [(a, b) for a in ok for b in ok if b < a and label[a] == label[b] and len(ok[a]) == len(ok[b]) and ok[a] @ ok[b] >= 0.98]
    want = components(len(rows), links)
    for hot in (4096, 3):
        got = {r["vec_id"]: r for r in embeddings.near_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int"), hot_bucket=hot).collect()}
        for i in range(len(rows)):
            assert got[i]["n_links"] == sum(i in x for x in links), i
            assert got[i]["component_id"] == want[i]


def test_estimates_are_unbiased_and_bounds_hold():
    rng = np.random.default_rng(7)
    x = rng.standard_normal((300, 64))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    coder = embeddings.Coder(64)
    packed = coder.pack(x)
    assert packed.shape == (300, 256 // 8 + 64 // 2 + 12)
    codes, rough, (spread, inverse, noise) = coder.unpack(packed)
    slack = embeddings.Z * np.sqrt(spread[:, None] + (inverse[:, None] * noise[None]) ** 2)
    gap = codes @ rough.T - x @ x.T
    off = ~np.eye(300, dtype=bool)
    assert abs(gap[off].mean()) < 0.003
    assert (np.abs(gap) <= slack)[off].all()
    near = x + 0.02 * rng.standard_normal(x.shape)  # close pairs too, where errors of both forms could add up
    near /= np.linalg.norm(near, axis=1, keepdims=True)
    gap = (codes * coder.unpack(coder.pack(near))[1]).sum(1) - (x * near).sum(1)
    assert abs(gap.mean()) < 0.01 and (np.abs(gap) <= np.diag(slack)).all()
    i, j = coder.candidates(np.concatenate([packed, coder.pack(near)]), np.array([0]), np.array([600]), 0.98, embeddings.Z)
    found = set(zip(i.tolist(), j.tolist(), strict=True))
    assert {(k, 300 + k) for k in range(300) if x[k] @ near[k] >= 0.98} <= found and len(found) < 400


def test_embeddings_odd_lengths_recall_and_exact_counts(spark):
    rng = np.random.default_rng(8)
    base = rng.standard_normal((300, 33))
    x = np.concatenate([base, base + 0.17 * rng.standard_normal(base.shape)])
    rows = [(k, [float(v) for v in r], 0, "mine") for k, r in enumerate(x)]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int, code string")
    got = embeddings.near_vectors(frame, counts=True).collect()
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    close = (unit @ unit.T >= 0.98) & ~np.eye(600, dtype=bool)
    assert {r["vec_id"]: r["n_links"] for r in got} == dict(enumerate(close.sum(1).tolist()))
    exact = sum(r["n_exact"] for r in got)
    assert close.sum() // 2 <= exact < 600 * 599 // 2 // 100
    assert embeddings.near_vectors(frame.limit(0)).count() == 0


def brute_spans(text):
    found = [(0, *m.span()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", text)]
    found += [(1, *m.span()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", text) if all(int(p) <= 255 for p in m[0].split("."))]
    digits = lambda s: re.sub("[^0-9]", "", s)
    found += [(2, *m.span()) for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", text) if 16 <= len(digits(m[0])) <= 19 and pii.luhn(digits(m[0]))]
    found += [(3, *m.span()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", text) if 8 <= len(digits(m[0])) <= 15]
    return found


def test_pii_base_spans_match_plain_patterns():
    rng = np.random.default_rng(8)
    alphabet = list("ab.@-+1 2(345)_é\n%")
    for _ in range(4000):
        text = "".join(rng.choice(alphabet, int(rng.integers(0, 60))))
        assert pii.base_spans(text) == brute_spans(text), text
    assert pii.base_spans("a" * 200_000) == [] and pii.base_spans("1" * 100_000) == []
    assert pii.render(pii.base_spans("x 4111 1111 1111 1111 a.b@c.d.e 1.2.3.4 +1 (988) 555-2485")) == "email:22:31,ip:32:39,card:2:21,phone:40:57"


def test_tagger_learns_and_windows_reconcile():
    rng = np.random.default_rng(9)
    texts = [f"{'lorem ' * int(rng.integers(0, 12))}mail u{k}@h{k % 7}.org now" for k in range(160)]
    parts = [(t, pii.windows(t), pii.base_spans(t)) for t in texts]
    x = np.concatenate([pii.encode_windows(t, w) for t, w, _ in parts])
    y = np.concatenate([pii.tag_rows(w, s) for _, w, s in parts])
    model = tagger.Tagger(1 + 2 * len(pii.ALL))
    history = model.fit(x, y, epochs=12)
    assert history[-1] < history[0] / 5
    good = sum(pii.reconcile(w, model.decode(pii.encode_windows(t, w))) == s for t, w, s in parts)
    assert good / len(parts) > 0.9
    long = "1" + "2" * 300
    spans = pii.windows(long)
    assert spans[0][0] == 0 and spans[-1][1] == len(long) and all(b[0] < a[1] for a, b in zip(spans, spans[1:]))
    assert pii.reconcile(spans, pii.tag_rows(spans, [(2, 10, 290)])) == [(2, 10, 290)]


def test_tagged_spans_are_those_of_the_whole_text():
    def decode(x):
        """Emails wherever letters e and x or separators run between spaces, or a long run of one letter."""
        code = lambda c: x == ord(c) + 2
        return np.where(code("e") | code("x") | code("@") | code("5") | code("a") | code("t") | code(" "), np.where(code("x"), 1, 2), 0)

    rng = np.random.default_rng(12)
    kinds = [*"eeeexbbb", "e" * 60, " at ", "@", "5", " "]
    texts = ["".join(rng.choice(kinds, int(rng.integers(0, 120)))) for _ in range(300)]
    texts += ["b" * 500 + "e" * 130 + " at " + "e" * 200 + "b", "write to anna at example.org", "", "b" * 97]
    n_found = 0
    for text, got in zip(texts, pii.tagged_spans(texts, decode), strict=True):
        grid = [pii.window(k, len(text)) for k in range(pii.owner(len(text) - 1, len(text)) + 1)] if text else []
        every = pii.reconcile(grid, decode(pii.encode_windows(text, grid)))
        assert got == [f for f in every if pii.plausible(f[0], text[f[1] : f[2]])], text
        n_found += len(got)
    assert n_found > 100
    assert (0, 500, 834) in pii.tagged_spans(texts[300:301], decode)[0]


def test_pii_finds_spelled_out_email_without_digit(spark):
    rng = np.random.default_rng(13)
    names = lambda n: "".join(rng.choice(list("abcdefghijklmnop"), n))
    texts = [f"{prose(rng, 30, 40).translate(str.maketrans('', '', '0123456789'))} they met at noon, write to {names(5)}@{names(6)}.org now" for _ in range(150)]
    model = pii.fit(documents(spark, texts).select("doc_id", "text"))
    new = [f"please write to {names(5)} at {names(6)}.org now" for _ in range(20)] + ["they met at noon, all of them"]
    rows = {r["doc_id"]: r["spans"] for r in pii.find(documents(spark, new).select("doc_id", "text"), model).collect()}
    assert sum(rows[k] == f"email:16:{len(new[k]) - 4}" for k in range(20)) >= 15
    assert rows[20] == ""


def test_pii_find_cases(spark):
    docs = documents(spark, ["mail a@b.co x", None, "", "no", "a@b.co"])
    rows = {r["doc_id"]: r for r in pii.find(docs, None).collect()}
    assert rows[0]["spans"] == "email:5:11" and rows[0]["n_email"] == 1
    assert rows[1]["base_sha256"] == hashlib.sha256(b"").hexdigest() and rows[1]["spans"] == ""
    assert {r["doc_id"]: r["text"] for r in pii.redact(docs, None).collect()}[0] == "mail [email] x"
    twice = spark.createDataFrame([(1, "mail a@b.co"), (1, "call x@y.org"), (None, None)], "doc_id long, text string").withColumn("spans", F.lit(3))
    assert sorted((r["text"] or "", r["spans"]) for r in pii.redact(twice, None).collect()) == [("", 3), ("call [email]", 3), ("mail [email]", 3)]
    assert pii.find(docs.filter("false"), None).count() == 0 and pii.redact(docs.filter("false"), None).count() == 0
    assert pii.fit(docs.filter("doc_id = 3")) is None


def test_tagger_finds_secrets_that_no_pattern_gives(spark):
    rng = np.random.default_rng(14)
    key = lambda: "".join(rng.choice(list("0123456789abcdef"), 40))
    plain = lambda n: prose(rng, n, 40).translate(str.maketrans("0123456789", "abcdefghij"))
    train = [f"{plain(25)} token = \"{key()}\" {plain(9)}" for _ in range(200)] + [plain(30) + " year 1999 and 2004" for _ in range(100)]
    model = pii.fit(documents(spark, train).select("doc_id", "text"))
    new = [f"{plain(int(rng.integers(3, 30)))} api_key: {key()} {plain(5)}" for _ in range(40)] + [plain(40) + " in 1987 or 12 of 2005" for _ in range(40)]
    rows = {r["doc_id"]: r for r in pii.find(documents(spark, new).select("doc_id", "text"), model).collect()}
    assert sum("secret:" in rows[k]["spans"] for k in range(40)) >= 34
    assert sum(rows[k]["private"] for k in range(40, 80)) <= 2


def test_warc_append_and_overwrite(spark, tmp_path):
    page = lambda k: spark.createDataFrame([(k, "http://h", "<p>" + "y" * 150)], "page_id long, url string, html string")
    path = f"file://{tmp_path}/a"
    warc.archive(page(1), path)
    warc.archive(page(2), path)
    assert sorted(warc_id(r["record_id"]) for r in warc.read_archive(spark, path).collect()) == [1, 2]
    warc.page_records(page(3)).write.format("warc").mode("overwrite").save(path)
    assert [warc_id(r["record_id"]) for r in warc.read_archive(spark, path).collect()] == [3]
    warc.archive(page(4).filter("false"), f"file://{tmp_path}/none")
    assert warc.read_archive(spark, f"file://{tmp_path}/none").count() == 0


def test_warc_round_trip(spark, tmp_path):
    html = ["<p>" + "x" * 200, None, "short", "short", "<p>" + "x" * 200, "é" * 60, "<p>" + "x" * 200]
    pages = spark.createDataFrame([(k, None if k == 2 else f"http://h/{k}\r\nX: y", h) for k, h in enumerate(html)], "page_id long, url string, html string")
    path = f"file://{tmp_path}/w"
    warc.archive(pages.repartition(3), path)
    rows = {warc_id(r["record_id"]): r for r in warc.read_archive(spark, path).collect()}
    assert len(rows) == 7 and [rows[k]["record_type"] for k in range(7)] == ["response"] * 4 + ["revisit", "response", "revisit"]
    for k, h in enumerate(html):
        body = (h or "").encode()
        assert rows[k]["payload_length"] == len(body)
        assert rows[k]["payload_digest"] == "sha256:" + hashlib.sha256(body).hexdigest()
        if rows[k]["record_type"] == "response":
            assert bytes(rows[k]["payload"]) == body
    assert warc_id(rows[6]["refers_to"]) == 0 and rows[2]["target_uri"] is None
    some = warc.read_archive(spark, path, "record_id string, record_type string").filter("record_type = 'revisit'")
    assert some.count() == 2
    assert warc.read_archive(spark, path).filter(F.col("record_id").isin("<urn:page:1>")).count() == 1


def warc_id(urn):
    return int(urn[len("<urn:page:") : -1])


def test_warc_foreign_members_and_plain_archives():
    import gzip
    import io

    one = warc.record("response", "<urn:page:1>", "http://a", "d", b"body", 4, None)
    for stream in (io.BytesIO(gzip.compress(one) * 2), io.BytesIO(warc.member(one) * 2), warc._squeezed(io.BytesIO(one * 2))):
        assert [(n, p) for _, n, p in warc.records(stream, lambda f: True, True)] == [(4, b"body")] * 2
    skipped = list(warc.records(io.BytesIO(warc.member(one) * 3), lambda f: f["warc-type"] == "revisit", True))
    assert skipped == []


def test_ordinal_fit_orders_grades():
    rng = np.random.default_rng(10)
    x = rng.standard_normal((600, 3))
    grade = np.digitize(x @ [1.5, -1, 0] + rng.logistic(size=600), [-1, 0.5, 2])
    w, theta = toxicity.fit_ordinal(x, grade, 4)
    assert (np.diff(theta) > 0).all() and w[0] > 1 and w[1] < -0.5 and abs(w[2]) < 0.4


def test_toxicity_and_quality_learn(spark):
    rng = np.random.default_rng(11)
    texts, labels = [], []
    for k in range(400):
        bad, toxic = k % 4 == 0, k % 3 == 0
        body = prose(rng, 60) if not bad else " | ".join(prose(rng, 2, 30).upper() + "!!" for _ in range(30))
        texts.append(body + (" grumblefoo" + "abcdef"[k % 6] if toxic else ""))
        labels.append((k, 0 if bad else 1, 1 if toxic else 0))
    docs = documents(spark, [*texts, None, ""])
    table = spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    found = {r["doc_id"]: r for r in toxicity.severity(docs, toxicity.fit(docs, table)).collect()}
    assert np.mean([found[k]["toxic"] == bool(y[2]) for k, y in enumerate(labels)]) > 0.98
    assert not found[400]["toxic"] and 0 <= found[401]["severity"] <= 3
    rows = quality.score(docs, quality.fit(docs, table)).select("*", labelled.is_held_out(F.col("doc_id")).alias("held")).collect()
    held = [r for r in rows if r["held"] and r["doc_id"] < 400]
    assert all((zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0) == r["held"] for r in rows)
    assert np.mean([r["predicted"] == labels[r["doc_id"]][1] for r in held]) > 0.95
    empty = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert {r["score"] for r in quality.score(docs, quality.fit(docs, empty)).collect()} == {0.5}
    assert toxicity.severity(docs, toxicity.fit(docs, empty)).filter("toxic").count() == 0


def test_word_hashes_equal_for_equal_words_only():
    splitter = hashing.Splitter()
    texts = ["", "Ab aB\tcd", "ab", "\n", "é É ab", None, "x" * 300_000]
    seen = {}
    for row, _, data, cuts in hashing.pieces(pa.array(texts)):
        codes, of = splitter.words(data, cuts)
        words = [(k, w) for k in range(row, row + len(cuts) - 1) for w in BLANK.findall((texts[k] or "").translate(FOLD))]
        assert [k - row for k, _ in words] == of.tolist()
        for (_, w), c in zip(words, codes.tolist(), strict=True):
            assert seen.setdefault(w, c) == c
    assert len(set(seen.values())) == len(seen)
