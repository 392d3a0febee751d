"""Quality: a convolutional network over bytes, written in numpy.

Every learned filter spans ``WIDTH`` bytes and runs over the whole UTF-8 text.
Responses are max-pooled over overlapping chunks (blocks of ``BLOCK`` bytes,
taken two by two), a small dense layer rates each chunk, and the mean, largest
and smallest rating of a document's chunks combine into one probability.

A filter over one-hot bytes is a sum of table rows, one table for each offset,
so a response is ``WIDTH`` look-ups. Only the places that won a maximum carry a
gradient.

The fit uses at most ``N_BAD`` and ``N_GOOD`` labelled rows outside the held-out
fifth, whole texts each; scoring covers every whole text. Null texts count as
empty; an empty text is one chunk of padding. Rows that repeat are each scored.
Without labels of both classes every score is the share of good labels (0.5
without labels). Other columns are ignored.
"""

from __future__ import annotations

import io
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import held, held_out, labelled_sample, released, table, train_once

N_BAD, N_GOOD = 1500, 3000
WIDTH, FILTERS, HIDDEN, BLOCK = 6, 16, 16, 128
SPAN = 512 * BLOCK
THRESHOLD = 0.3


def _bytes(text: str | None) -> np.ndarray:
    """Bytes 1 to 256, padded with 0 to whole blocks and at least two of them."""
    raw = np.frombuffer((text or "").encode("utf-8", "replace"), np.uint8).astype(np.int16) + 1
    blocks = max(2, -(-len(raw) // BLOCK))
    out = np.zeros(blocks * BLOCK + WIDTH - 1, np.int16)
    out[:len(raw)] = raw
    return out


class Network:
    SHAPES = {"tables": (WIDTH, 257, FILTERS), "w1": (FILTERS, HIDDEN), "b1": (HIDDEN,), "w2": (HIDDEN,), "b2": (1,), "w3": (3,), "b3": (1,)}

    def __init__(self, seed: int = 3):
        rng = np.random.default_rng(seed)
        self.p = {k: (rng.normal(0, 0.25, s) if k in ("tables", "w1", "w2") else np.zeros(s)).astype(np.float32) for k, s in self.SHAPES.items()}
        self.p["w3"][:] = (1, 0.3, 0.3)

    def respond(self, data: np.ndarray, where: bool = False):
        """Block maxima (blocks x filters), and where they were found."""
        tops, places = [], []
        tables, n = self.p["tables"], len(data) - WIDTH + 1
        for lo in range(0, n, SPAN):
            part = data[lo:min(lo + SPAN, n) + WIDTH - 1]
            m = len(part) - WIDTH + 1
            acc = tables[0].take(part[:m], axis=0)
            for j in range(1, WIDTH):
                acc += tables[j].take(part[j:m + j], axis=0)
            cut = acc.reshape(-1, BLOCK, FILTERS)
            if where:
                at = cut.argmax(1)
                places.append(at + (np.arange(len(cut)) * BLOCK + lo)[:, None])
                tops.append(np.take_along_axis(cut, at[:, None], 1)[:, 0])
            else:
                tops.append(cut.max(1))
        return (np.concatenate(tops), np.concatenate(places)) if where else np.concatenate(tops)

    def head(self, tops: np.ndarray) -> dict:
        pooled = np.maximum(tops[:-1], tops[1:])
        a = np.maximum(pooled, 0)
        h = a @ self.p["w1"] + self.p["b1"]
        rating = np.maximum(h, 0) @ self.p["w2"] + self.p["b2"]
        summary = np.array([rating.mean(), rating.max(), rating.min()], np.float32)
        return {"pooled": pooled, "a": a, "h": h, "rating": rating, "summary": summary, "z": float(summary @ self.p["w3"] + self.p["b3"][0])}

    def score(self, text: str | None) -> float:
        z = self.head(self.respond(_bytes(text)))["z"]
        return float(1 / (1 + np.exp(-np.clip(z, -500, 500))))

    def gradient(self, data: np.ndarray, y: float, into: dict) -> None:
        tops, places = self.respond(data, where=True)
        f = self.head(tops)
        g = 1 / (1 + np.exp(-np.clip(f["z"], -30, 30))) - y
        into["w3"] += g * f["summary"]
        into["b3"] += g
        n = len(f["rating"])
        d_rating = np.full(n, g * self.p["w3"][0] / n, np.float32)
        d_rating[f["rating"].argmax()] += g * self.p["w3"][1]
        d_rating[f["rating"].argmin()] += g * self.p["w3"][2]
        into["w2"] += np.maximum(f["h"], 0).T @ d_rating
        into["b2"] += d_rating.sum()
        d_h = d_rating[:, None] * self.p["w2"] * (f["h"] > 0)
        into["w1"] += f["a"].T @ d_h
        into["b1"] += d_h.sum(0)
        d_pool = (d_h @ self.p["w1"].T) * (f["pooled"] > 0)
        left = tops[:-1] >= tops[1:]
        d_tops = np.zeros_like(tops)
        d_tops[:-1] += d_pool * left
        d_tops[1:] += d_pool * ~left
        columns = np.arange(FILTERS)
        for j in range(WIDTH):
            flat = data[places + j].astype(np.int64) * FILTERS + columns
            into["tables"][j] += np.bincount(flat.ravel(), weights=d_tops.ravel(), minlength=257 * FILTERS).reshape(257, FILTERS)

    def dump(self) -> bytes:
        out = io.BytesIO()
        np.savez_compressed(out, **self.p)
        return out.getvalue()

    @classmethod
    def load(cls, model: bytes) -> Network:
        net = cls()
        held = np.load(io.BytesIO(model))
        net.p = {k: held[k] for k in cls.SHAPES}
        return net


def fit(texts: list[str], ys: list[int], epochs: int = 8, batch: int = 16, rate: float = 0.006) -> bytes:
    net = Network()
    if len(set(ys)) < 2:
        share = (sum(ys) + 1) / (len(ys) + 2) if ys else 0.5
        for k in net.p:
            net.p[k][:] = 0
        net.p["b3"][:] = np.log(share / (1 - share))
        return net.dump()
    data = [_bytes(t) for t in texts]
    rng = np.random.default_rng(11)
    m = {k: np.zeros_like(v) for k, v in net.p.items()}
    v = {k: np.zeros_like(x) for k, x in net.p.items()}
    step, steps = 0, max(1, epochs * -(-len(data) // batch))
    for _ in range(epochs if len(data) > 1000 else 3 * epochs):
        order = rng.permutation(len(data))
        for lo in range(0, len(order), batch):
            grads = {k: np.zeros(x.shape, np.float64) for k, x in net.p.items()}
            some = order[lo:lo + batch]
            for i in some:
                net.gradient(data[i], ys[i], grads)
            step += 1
            pace = rate * max(0.05, 1 - step / steps)
            for k, g in grads.items():
                g = (g / len(some)).astype(np.float32)
                m[k] = 0.9 * m[k] + 0.1 * g
                v[k] = 0.99 * v[k] + 0.01 * g * g
                net.p[k] = (net.p[k] - pace * (m[k] / (1 - 0.9 ** step)) / (np.sqrt(v[k] / (1 - 0.99 ** step)) + 1e-7)).astype(np.float32)
    return net.dump()


def train(docs: DataFrame, labels: DataFrame) -> bytes:
    return train_once(labelled_sample(docs, labels, "quality", {0: N_BAD, 1: N_GOOD}), fit, "quality")


def with_score(docs: DataFrame, model: bytes, name: str = "score") -> DataFrame:
    @F.pandas_udf("double")
    def score(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        net = held("quality", model, Network.load)
        for texts in released(batches):
            yield pd.Series([net.score(t) for t in texts], dtype="float64")

    return docs.withColumn(name, score(F.coalesce(F.col("text"), F.lit(""))))


def op4_quality_cnn(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    model = train(docs, table(spark, sf_dir, "labels"))
    scored = with_score(docs, model)
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
