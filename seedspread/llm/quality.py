"""Quality classifier by compression: which of two zstandard dictionaries makes a text smaller.

One dictionary is built from good and one from bad labelled texts. A text is cut into blocks of
``BLOCK`` bytes, so a long text's own history does not drown the dictionaries; every block of the whole text
is compressed with both, and the difference of the two sums over their total becomes, through a logistic
curve fitted on labelled texts that the dictionaries have not seen, the probability of label 1.

The fit uses at most ``PER_CLASS`` labelled texts of each class; scoring covers all rows. Cases: null and
empty texts are scored as the empty string; with one class or none labelled the score is the labels' mean
(0.5 without labels); repeated rows score alike.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seedspread.llm.labelled import is_held_out, sample
from seedspread.llm.text import shielded

PER_CLASS, BLOCK, DICTIONARY, LEVEL, ACCEPT = 1_600, 512, 112_640, 3, 0.3


def _blocks(text: bytes) -> list[bytes]:
    return [text[i : i + BLOCK] for i in range(0, max(len(text), 1), BLOCK)]


def _dictionary(texts: list[bytes]) -> bytes:
    """Trained content, or the texts themselves where they are too few to train on."""
    try:
        return zstandard.train_dictionary(DICTIONARY, [b for t in texts for b in _blocks(t)], k=64, d=8).as_bytes()
    except zstandard.ZstdError:
        share = max(1, DICTIONARY // max(1, len(texts)))
        return b"".join(t[:share] for t in texts) or b"\n" * 64


class Compressors:
    """Both dictionaries, ready to use; built once per task from the model's bytes."""

    def __init__(self, good: bytes, bad: bytes):
        self.pair = []
        for content in (good, bad):
            d = zstandard.ZstdCompressionDict(content)
            d.precompute_compress(level=LEVEL)
            self.pair.append(zstandard.ZstdCompressor(dict_data=d, level=LEVEL, write_content_size=False, write_dict_id=False))

    def difference(self, text: str) -> float:
        """(bad size - good size) / (both sizes) over all blocks: positive where the good dictionary fits better."""
        good, bad = self.pair
        a = b = 0
        for block in _blocks(text.encode("utf-8", "surrogatepass")):
            a += len(good.compress(block))
            b += len(bad.compress(block))
        return (b - a) / (a + b)


def _logistic(x: np.ndarray, y: np.ndarray, share: float) -> tuple[float, float]:
    """Intercept and slope by Newton steps, classes reweighted to the labels' share of 1."""
    w = np.where(y == 1, share / max(y.mean(), 1e-9), (1 - share) / max((1 - y).mean(), 1e-9))
    design, theta = np.stack([np.ones_like(x), x], 1), np.zeros(2)
    for _ in range(60):
        p = 1 / (1 + np.exp(-np.clip(design @ theta, -30, 30)))
        slope = design.T @ (w * (y - p)) - 1e-3 * theta
        curve = (design * (w * p * (1 - p))[:, None]).T @ design + 1e-3 * np.eye(2)
        theta += np.clip(np.linalg.solve(curve, slope), -5, 5)
    return float(theta[0]), float(theta[1])


def fit(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS) -> dict:
    """Dictionaries and calibration from labelled rows that are not held out."""
    open_rows = ~is_held_out(F.col("_id"))
    found = sample(docs, labels, "quality", per_class, open_rows)
    share = labels.filter(~is_held_out(F.col("doc_id")) & F.col("quality").isin(0, 1)).agg(F.avg("quality")).first()[0]
    by = {y: [t.encode("utf-8", "surrogatepass") for _, t, z in found if z == y] for y in (0, 1)}
    if not by[0] or not by[1]:
        return {"constant": 0.5 if share is None else float(share)}
    split = {y: max(1, len(v) * 3 // 4) for y, v in by.items()}
    model = {"good": _dictionary(by[1][: split[1]]), "bad": _dictionary(by[0][: split[0]])}
    unseen = [(t, y) for y, v in by.items() for t in (v[split[y] :] or v)]
    both = Compressors(model["good"], model["bad"])
    x = np.array([20 * both.difference(t.decode("utf-8", "surrogatepass")) for t, _ in unseen])
    model["line"] = _logistic(x, np.array([y for _, y in unseen], float), float(share))
    return model


@shielded
def score(docs: DataFrame, model: dict, accept: float = ACCEPT) -> DataFrame:
    """``docs`` with ``score`` (0 to 1) and ``predicted`` added last, under free names; other columns stay."""

    @F.pandas_udf("double")
    def probability(texts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        both = None if "constant" in model else Compressors(model["good"], model["bad"])
        for column in texts:
            if both is None:
                yield pd.Series(np.full(len(column), model["constant"]))
                continue
            x = np.array([20 * both.difference(t or "") for t in column], float)
            yield pd.Series(1 / (1 + np.exp(-np.clip(model["line"][0] + model["line"][1] * x, -30, 30))))

    scored = docs.withColumn("score", probability(F.col("text")))
    return scored.withColumn("predicted", F.when(F.col("score") >= accept, 1).otherwise(0))
