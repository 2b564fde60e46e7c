"""Severity of toxicity by cumulative-link ordinal regression over sparse text features.

Features are whole words and their first 4, 5 and 6 bytes, so inflected forms share weight. Features whose
presence is associated with the label (chi-square) enter one linear score; ordered thresholds on that same
score give P(grade >= k) = sigmoid(score - threshold k), and the sum of these is the expected severity.

The labels only say toxic or not, so the grades used for fitting are derived: 0 for rows that are not toxic,
and 1 to 3 for thirds of the toxic rows by the score that two-grade models, fitted on the other two folds of the
sample, give them; no row's grade comes from a model that saw it. The
fit uses at most ``PER_CLASS`` labelled texts of each class; all rows are scored. Cases: null and empty texts
have no features and the severity of a text without any; without labels of both classes every severity is
the share of toxic labels (0 without labels); repeated rows score alike.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seedspread.llm import hashing
from seedspread.llm.labelled import sample

PER_CLASS, MAX_FEATURES, GRADES = 2_500, 1_000, 4
PREFIXES = (4, 5, 6)
#: Chi-square with one degree of freedom beyond which an association is not chance among very many features.
ASSOCIATED = 40.0
SEPARATORS = bytes([*range(0x00, 0x30), *range(0x3A, 0x41), *range(0x5B, 0x61), *range(0x7B, 0x80)])


def _features(texts: pa.Array) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    splitter = hashing.Splitter(SEPARATORS)
    for row, end, data, cuts in hashing.pieces(texts):
        codes, of = splitter.words_and_prefixes(data, cuts, PREFIXES)
        yield row, end, codes >> np.uint64(16) << np.uint64(16), of  # as many bits as distinct() keeps


def _counts(texts: pa.Array, vocabulary: np.ndarray) -> np.ndarray:
    """Texts × features matrix of counts."""
    out = np.zeros((len(texts), len(vocabulary)), np.float32)
    for row, _, codes, of in _features(texts):
        if len(codes) == 0 or len(vocabulary) == 0:
            continue
        place = np.searchsorted(vocabulary, codes)
        place[place == len(vocabulary)] = 0
        hit = vocabulary[place] == codes
        np.add.at(out, (row + of[hit], place[hit]), 1)
    return out


def select_features(texts: pa.Array, y: np.ndarray) -> np.ndarray:
    """Sorted hashes of the features most associated with label 1."""
    seen, label = [], []
    for row, end, codes, of in _features(texts):
        values, owner = hashing.distinct(codes, of)
        seen.append(values)
        label.append(y[row + owner])
    codes, marks = np.concatenate(seen), np.concatenate(label)
    vocabulary, at = np.unique(codes, return_inverse=True)
    n, n1 = len(y), y.sum()
    total, with1 = np.bincount(at), np.bincount(at, weights=marks)
    a, b, c, d = with1, total - with1, n1 - with1, n - n1 - (total - with1)
    chi = n * (a * d - b * c) ** 2 / np.maximum((a + b) * (c + d) * (a + c) * (b + d), 1e-9)
    good = (chi >= min(ASSOCIATED, 0.02 * n + 4)) & (a / max(n1, 1) > b / max(n - n1, 1)) & (total >= 3)
    best = np.flatnonzero(good)
    best = best[np.argsort(-chi[best], kind="stable")][:MAX_FEATURES]
    return np.sort(vocabulary[best])


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


def fit_ordinal(x: np.ndarray, grade: np.ndarray, n_grades: int, steps: int = 300, rate: float = 0.1, ridge: float = 1e-4) -> tuple[np.ndarray, np.ndarray]:
    """(weights, ordered thresholds) that maximise the penalised likelihood of the grades.

    Thresholds are a first value plus positive steps, so they stay in order; weights are shared by all of them.
    """
    n, m = x.shape
    w, raw = np.zeros(m), np.zeros(n_grades - 1)
    first, second = np.zeros(m + n_grades - 1), np.zeros(m + n_grades - 1)
    wide = np.arange(n_grades - 1)
    for step in range(1, steps + 1):
        gaps = np.exp(raw[1:])
        theta = raw[0] + np.concatenate([[0.0], np.cumsum(gaps)])
        up = _sigmoid((x @ w)[:, None] - theta[None, :])
        edge = np.concatenate([np.ones((n, 1)), up, np.zeros((n, 1))], 1)
        at = np.arange(n)
        p = np.maximum(edge[at, grade] - edge[at, grade + 1], 1e-9)
        slope = up * (1 - up)
        lower = np.where(grade > 0, slope[at, np.maximum(grade - 1, 0)], 0)
        upper = np.where(grade < n_grades - 1, slope[at, np.minimum(grade, n_grades - 2)], 0)
        eta = (lower - upper) / p / n
        at_theta = np.zeros(n_grades - 1)
        np.add.at(at_theta, np.maximum(grade - 1, 0), -lower / p / n)
        np.add.at(at_theta, np.minimum(grade, n_grades - 2), upper / p / n)
        tail = np.array([at_theta[k:].sum() for k in wide])
        g = np.concatenate([x.T @ eta - ridge * w, [tail[0]], tail[1:] * gaps])
        first, second = 0.9 * first + 0.1 * g, 0.999 * second + 0.001 * g * g
        move = rate * (first / (1 - 0.9**step)) / (np.sqrt(second / (1 - 0.999**step)) + 1e-8)
        w, raw = w + move[:m], raw + move[m:]
    return w, raw[0] + np.concatenate([[0.0], np.cumsum(np.exp(raw[1:]))])


def _grades(texts: pa.Array, y: np.ndarray, folds: int = 3) -> np.ndarray:
    """0 for label 0; 1 to ``GRADES - 1`` for label 1, by thirds of the score that models of the other folds give the text."""
    part = np.arange(len(y)) % folds  # rows come in hash order within each class
    score = np.zeros(len(y))
    for k in range(folds):
        own, others = np.flatnonzero(part == k), np.flatnonzero(part != k)
        if len(set(y[others].tolist())) < 2:
            continue
        vocabulary = select_features(texts.take(pa.array(others)), y[others])
        w, _ = fit_ordinal(np.log1p(_counts(texts.take(pa.array(others)), vocabulary)).astype(float), y[others], 2, steps=100)
        score[own] = np.log1p(_counts(texts.take(pa.array(own)), vocabulary)) @ w
    grade = np.where(y == 1, 1, 0)
    edges = np.quantile(score[y == 1], [k / (GRADES - 1) for k in range(1, GRADES - 1)])
    grade[y == 1] += np.searchsorted(edges, score[y == 1], side="left")
    return grade


def fit(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS) -> dict:
    """Vocabulary, weights and thresholds from a bounded labelled sample."""
    found = sample(docs, labels, "toxic", per_class)
    y = np.array([r[2] for r in found], np.int64)
    if len(set(y.tolist())) < 2:
        share = labels.agg(F.avg("toxic")).first()[0]
        return {"constant": float(share or 0.0)}
    texts = pa.array([r[1] for r in found], pa.large_string())
    grade = _grades(texts, y)
    vocabulary = select_features(texts, y)
    counts = _counts(texts, vocabulary)
    w, theta = fit_ordinal(np.log1p(counts).astype(float), grade, GRADES)
    return {"vocabulary": vocabulary, "weights": w, "thresholds": theta}


def severity(docs: DataFrame, model: dict) -> DataFrame:
    """``docs(doc_id, text)`` → ``(doc_id, severity, grade, toxic)`` for every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = batch.num_rows
            if "constant" in model:
                up = np.full((n, GRADES - 1), model["constant"] / (GRADES - 1))
            else:
                eta = np.zeros(n)
                vocabulary, weights = model["vocabulary"], model["weights"]
                for row, end, codes, of in _features(batch.column(1)):
                    if len(codes) == 0 or len(vocabulary) == 0:
                        continue
                    place = np.searchsorted(vocabulary, codes)
                    place[place == len(vocabulary)] = 0
                    hit = vocabulary[place] == codes
                    pair, count = np.unique((of[hit] << 20) | place[hit], return_counts=True)
                    np.add.at(eta, row + (pair >> 20), weights[pair & 0xFFFFF] * np.log1p(count))
                up = _sigmoid(eta[:, None] - model["thresholds"][None, :])
            grade = (up >= 0.5).sum(1)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(up.sum(1)), pa.array(grade.astype(np.int32)), pa.array(grade > 0)], names=["doc_id", "severity", "grade", "toxic"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, severity double, grade int, toxic boolean")
