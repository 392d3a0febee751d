"""Toxicity: a linear classifier over character n-grams scaled by naive Bayes log-count ratios.

Texts are lower-cased and stand between two blanks; every run of 3 to 5
characters (code points) is a feature, present or not, hashed into 2**18 slots. Features are scaled
by the log ratio of their smoothed shares among toxic and other training texts,
and a regularised logistic regression is fitted over them.

The fit uses at most ``N_TOXIC`` and ``N_OTHER`` labelled rows outside the
held-out fifth (common.labelled_sample); scoring covers every whole text. Null
and empty texts get the score of a text without features. Rows that repeat are
each scored. Without labels of both classes every score is the share of toxic
labels (0.5 without labels). Other columns pass through ``filter_toxic``.
"""

from __future__ import annotations

import io
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import held, held_out, labelled_sample, released, table, train_once

N_TOXIC, N_OTHER = 2500, 4000
ORDERS = (3, 4, 5)
BITS = 18
THRESHOLD = 0.5


class Grams:
    """The distinct n-gram slots of a text."""

    def __init__(self):
        self.seen = np.zeros(1 << BITS, np.int64)

    def __call__(self, text: str | None) -> np.ndarray:
        raw = np.frombuffer(f" {(text or '').lower()} ".encode("utf-32-le", "surrogatepass"), "<u4")
        found = []
        for lo in range(0, len(raw), 1 << 20):  # long texts in spans that overlap by what an n-gram needs
            part = raw[lo:lo + (1 << 20) + ORDERS[-1] - 1] + np.uint32(1)
            code = np.zeros(len(part), np.uint32)
            for n in range(1, ORDERS[-1] + 1):
                if len(part) < n:
                    break
                code = code[:len(part) - n + 1] * np.uint32(0x01000193) + part[n - 1:] * np.uint32(0x9E3779B1)
                if n in ORDERS:
                    found.append(((code ^ (code >> np.uint32(15))) * np.uint32(0x85EBCA6B + 2 * n)) >> np.uint32(32 - BITS))
        if not found:
            return np.zeros(0, np.int64)
        slots = np.concatenate(found).astype(np.int64)
        order = np.arange(len(slots))
        self.seen[slots] = order  # of equal slots the last stays
        return slots[self.seen[slots] == order]


def fit(texts: list[str], ys: list[int], epochs: int = 25, rate: float = 0.05, decay: float = 1e-5, smooth: float = 1.0, least: int = 3) -> bytes:
    """Weights of the slots, ratios multiplied in, and the bias."""
    y = np.array(ys, np.float64)
    grams, size = Grams(), 1 << BITS
    if len(set(ys)) < 2:
        share = (y.sum() + 1) / (len(y) + 2) if len(y) else 0.5
        return _dump(np.zeros(size), float(np.log(share / (1 - share))))
    rows = [grams(t).astype(np.int32) for t in texts]
    counts = {c: np.bincount(np.concatenate([r for r, v in zip(rows, ys, strict=True) if v == c]), minlength=size) for c in (0, 1)}
    p, q = counts[1] + smooth, counts[0] + smooth
    ratio = np.log(p / (y.sum() + 2 * smooth)) - np.log(q / (len(y) - y.sum() + 2 * smooth))
    ratio[counts[0] + counts[1] < least] = 0
    rows = [r[ratio[r] != 0] for r in rows]
    w, bias, g2, gb2 = np.zeros(size), 0.0, np.full(size, 1e-3), 1e-3
    rng = np.random.default_rng(5)
    for _ in range(epochs):
        order = rng.permutation(len(rows))
        for lo in range(0, len(order), 128):
            some = order[lo:lo + 128]
            idx = np.concatenate([rows[i] for i in some])
            n = np.array([len(rows[i]) for i in some])
            of = np.repeat(np.arange(len(some)), n)
            z = np.bincount(of, weights=w[idx] * ratio[idx], minlength=len(some)) + bias
            g = (1 / (1 + np.exp(-np.clip(z, -30, 30))) - y[some]) / len(some)
            grad = np.bincount(idx, weights=g[of] * ratio[idx], minlength=size) + decay * w
            g2 += grad * grad
            gb2 += g.sum() ** 2
            w -= rate * grad / np.sqrt(g2)
            bias -= rate * g.sum() / np.sqrt(gb2)
    return _dump(w * ratio, bias)


def _dump(weights: np.ndarray, bias: float) -> bytes:
    out = io.BytesIO()
    np.savez_compressed(out, weights=weights.astype(np.float32), bias=np.array([bias]))
    return out.getvalue()


class Scorer:
    def __init__(self, model: bytes):
        held = np.load(io.BytesIO(model))
        self.weights, self.bias, self.grams = held["weights"], float(held["bias"][0]), Grams()

    def __call__(self, text: str | None) -> float:
        z = float(self.weights[self.grams(text)].astype(np.float64).sum()) + self.bias
        return float(1 / (1 + np.exp(-np.clip(z, -500, 500))))


def train(docs: DataFrame, labels: DataFrame) -> bytes:
    return train_once(labelled_sample(docs, labels, "toxic", {1: N_TOXIC, 0: N_OTHER}), fit, "toxicity")


def score_of(model: bytes):
    """The toxicity of a column of whole texts."""
    @F.pandas_udf("double")
    def score(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        scorer = held("toxicity", model, Scorer)
        for texts in released(batches):
            yield pd.Series([scorer(t) for t in texts], dtype="float64")

    return score(F.coalesce(F.col("text"), F.lit("")))


def with_score(docs: DataFrame, model: bytes, name: str = "score") -> DataFrame:
    return docs.withColumn(name, score_of(model))


def filter_toxic(docs: DataFrame, model: bytes) -> DataFrame:
    """The documents that the classifier does not reject, with their own columns."""
    return docs.filter(score_of(model) < THRESHOLD)


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    model = train(docs, table(spark, sf_dir, "labels"))
    scored = with_score(docs, model)
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
