"""Nearest vectors in bounded tiles against brute force."""

import numpy as np

from seedspread.sources import builders


def brute(ids, x, k):
    unit = x.astype(float) / np.linalg.norm(x.astype(float), axis=1, keepdims=True)
    s = np.round(unit @ unit.T, 9)
    out = set()
    for i in range(len(ids)):
        order = sorted((j for j in range(len(ids)) if ids[j] != ids[i]), key=lambda j: (-s[i, j], ids[j]))[:k]
        out |= {(int(ids[i]), int(ids[j])) for j in order}
    return out


def data(n=300):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(n, 8)).astype(np.float32)
    x[50:130] = x[50]  # many equal cosines
    return rng.permutation(n * 2)[:n], x


def test_tiles_give_the_best_of_all(monkeypatch):
    monkeypatch.setattr(builders, "TILE", (32, 16))
    ids, x = data()
    unit = x.astype(float) / np.linalg.norm(x.astype(float), axis=1, keepdims=True)
    row, far, _ = builders.nearest(ids, unit, ids, unit, 5)
    assert {(int(ids[i]), int(j)) for i, j in zip(row, far, strict=True)} == brute(ids, x, 5)


def test_blocks_grow_in_number_not_in_size(spark, monkeypatch):
    monkeypatch.setattr(builders, "BLOCK_ROWS", 20)
    ids, x = data()
    rows = [(int(i), v.tolist()) for i, v in zip(ids, x, strict=True)] + [(9_001, [0.0] * 8), (9_002, None), (9_003, [float("nan")] * 8)]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got = builders.knn(frame, 5, blocks=1)
    assert {(r["src"], r["dst"]) for r in got.select("src", "dst").collect()} == brute(ids, x, 5)
