"""Approximate nearest neighbours by inner product: one vantage-point tree per shard.

Inner products become distances by giving every vector one more coordinate,
the square root of what its squared norm lacks to the shard's largest; queries
get 0 there. Then the squared distance is a constant less twice the inner
product, and the triangle inequality holds. A subtree is left out when
``relax`` times the bound it gives is no nearer than the nearest found so far;
``relax`` 1 restores exact search.

Shards are dealt by a hash of the id, so each holds about ``shard_rows`` rows
whatever the data. Equal vectors of a shard are one point of its tree that
lists the smallest ids it may need. Queries come in blocks; a task keeps one
block with the ``k`` nearest of each query so far and lets the trees of all
shards pass by one after the other, so what it holds does not grow, the bound
that prunes a tree is the best of all trees before it, and each query leaves
with ``k`` rows, to be gathered by no one. Blocks hold at most ``block_rows``
queries, fewer where there are more tasks than blocks.

Rows with a null id, and vectors that are null, empty, zero or hold null or
non-finite components take no part. Vectors are compared with those of their
own length. Of rows that repeat a (vec_id, vector) one counts; a query id that
stands for several vectors takes the smallest. An empty table gives no rows.
Other columns are ignored.
"""

from __future__ import annotations

import io

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialize, released, shuffle_parts, table

K = 20
LEAF = 512
RELAX = 1.5


class VantageTree:
    def __init__(self, points: np.ndarray, id_lists: list[np.ndarray]):
        self.m2 = float((points * points).sum(1).max()) if len(points) else 0.0
        self.order = np.arange(len(points))
        self.nodes: list[tuple] = []  # (first, last, vantage, inner far, outer near, inner node, outer node)
        self._points = points
        self._lift = np.sqrt(np.maximum(self.m2 - (points * points).sum(1), 0))
        self.root = self._grow(0, len(points), np.random.default_rng(1)) if len(points) else -1
        self.points = points[self.order]
        self.first_ids = np.array([id_lists[i][0] for i in self.order], np.int64)
        self.lengths = np.array([len(id_lists[i]) for i in self.order], np.int64)
        self.ids = np.concatenate([id_lists[i] for i in self.order]) if len(points) else np.zeros(0, np.int64)

    def _grow(self, a: int, b: int, rng) -> int:
        if b - a <= LEAF:
            self.nodes.append((a, b, -1, 0.0, 0.0, -1, -1))
            return len(self.nodes) - 1
        rows = self.order[a:b]
        v = int(rows[rng.integers(b - a)])
        d2 = ((self._points[rows] - self._points[v]) ** 2).sum(1) + (self._lift[rows] - self._lift[v]) ** 2
        half = (b - a) // 2
        by = np.argpartition(d2, half)
        self.order[a:b] = rows[by]
        d = np.sqrt(d2[by])
        inner_far, outer_near = float(d[:half].max()), float(d[half:].min())
        vantage = (self._points[v].copy(), float(self._lift[v]))
        me = len(self.nodes)
        self.nodes.append(())
        inner, outer = self._grow(a, a + half, rng), self._grow(a + half, b, rng)
        self.nodes[me] = (a, b, vantage, inner_far, outer_near, inner, outer)
        return me

    def search(self, queries: np.ndarray, k: int, relax: float, floor: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Scores and points of the ``k`` best points of each query; -inf and -1 where there are fewer.

        Points below a query's ``floor``, the least score that it still wants, may be left out.
        """
        self._q, self._k, self._relax = queries, k, relax
        self._floor = np.full(len(queries), -np.inf) if floor is None else floor
        self._q2 = (queries * queries).sum(1) + self.m2
        self.best = np.full((len(queries), k), -np.inf)
        self.at = np.full((len(queries), k), -1, np.int64)
        self.seen = 0
        if self.root >= 0 and len(queries):
            self._visit(self.root, np.arange(len(queries)))
        return self.best, self.at

    def _reach(self, rows: np.ndarray) -> np.ndarray:
        kth = np.maximum(self.best[rows].min(1), self._floor[rows])
        kth -= np.where(np.isinf(kth), 0, 1e-9 * (1 + np.abs(kth)))  # ties are not left out
        return np.where(np.isinf(kth), np.inf, np.sqrt(np.maximum(self._q2[rows] - 2 * np.where(np.isinf(kth), 0, kth), 0)))

    def _visit(self, node: int, rows: np.ndarray) -> None:
        if not len(rows):
            return
        a, b, vantage, inner_far, outer_near, inner, outer = self.nodes[node]
        if inner < 0:
            self._leaf(a, b, rows)
            return
        v, lift = vantage
        d = np.sqrt(np.maximum(self._q2[rows] - self.m2 + (v * v).sum() + lift * lift - 2 * self._q[rows] @ v, 0))
        near = d <= (inner_far + outer_near) / 2
        self._visit(inner, rows[near])
        self._visit(outer, rows[~near])
        reach = self._reach(rows)
        self._visit(outer, rows[near & (self._relax * (outer_near - d) < reach)])
        self._visit(inner, rows[~near & (self._relax * (d - inner_far) < reach)])

    def _leaf(self, a: int, b: int, rows: np.ndarray) -> None:
        self.seen += len(rows) * (b - a)
        scores = self._q[rows] @ self.points[a:b].T
        hit = scores.max(1) >= np.maximum(self.best[rows].min(1), self._floor[rows]) - 1e-9
        rows, scores = rows[hit], scores[hit]
        if not len(rows):
            return
        every = np.concatenate([self.best[rows], scores], 1)
        points = np.concatenate([self.at[rows], np.broadcast_to(np.arange(a, b), scores.shape)], 1)
        top = np.argpartition(-every, self._k - 1, axis=1)[:, :self._k]
        kth = np.take_along_axis(every, top, 1).min(1)
        for r in np.flatnonzero((every >= kth[:, None]).sum(1) > self._k):  # ties at the edge: the smaller id
            ids = np.where(points[r] >= 0, self.first_ids[points[r]], np.iinfo(np.int64).max)
            top[r] = np.lexsort((ids, -every[r]))[:self._k]
        self.best[rows] = np.take_along_axis(every, top, 1)
        self.at[rows] = np.take_along_axis(points, top, 1)

    def dump(self) -> bytes:
        flat = [(a, b, f, o, i, j) for a, b, _, f, o, i, j in self.nodes]
        vantage = np.array([[*n[2][0], n[2][1]] if n[5] >= 0 else np.zeros(self.points.shape[1] + 1) for n in self.nodes])
        out = io.BytesIO()
        points = self.points.astype(np.float32) if (self.points.astype(np.float32) == self.points).all() else self.points
        np.savez(out, m2=[self.m2], root=[self.root], nodes=np.array(flat, np.float64), vantage=vantage, points=points, first_ids=self.first_ids, lengths=self.lengths, ids=self.ids)
        return out.getvalue()

    @classmethod
    def load(cls, data: bytes) -> VantageTree:
        held, tree = np.load(io.BytesIO(data)), cls.__new__(cls)
        tree.m2, tree.root = float(held["m2"][0]), int(held["root"][0])
        tree.points = held["points"].astype(np.float64)
        tree.nodes = [(int(a), int(b), (v[:-1], float(v[-1])), f, o, int(i), int(j)) for (a, b, f, o, i, j), v in zip(held["nodes"], held["vantage"], strict=True)]
        tree.first_ids, tree.lengths, tree.ids = held["first_ids"], held["lengths"], held["ids"]
        return tree


def _build(k: int):
    def build(pdf: pd.DataFrame) -> pd.DataFrame:
        vectors = np.array(pdf["vector"].tolist(), np.float64).reshape(len(pdf), -1)
        distinct, back = np.unique(vectors, axis=0, return_inverse=True)
        ids, back = pdf["vec_id"].to_numpy(np.int64), back.ravel()
        order = np.lexsort((ids, back))
        edges = np.searchsorted(back[order], np.arange(len(distinct) + 1))
        lists = [np.unique(ids[order[edges[i]:edges[i + 1]]])[:k + 1] for i in range(len(distinct))]
        return pd.DataFrame({"dim": [int(pdf["dim"].iloc[0])], "shard": [int(pdf["shard"].iloc[0])], "tree": [VantageTree(distinct, lists).dump()]})

    return build


def _pack(pdf: pd.DataFrame) -> pd.DataFrame:
    out = io.BytesIO()
    np.savez(out, ids=pdf["vec_id"].to_numpy(np.int64), vectors=np.array(pdf["vector"].tolist(), np.float64).reshape(len(pdf), -1))
    return pd.DataFrame({"dim": [int(pdf["dim"].iloc[0])], "block": [int(pdf["block"].iloc[0])], "payload": [out.getvalue()]})


class Nearest:
    """The ``k`` nearest so far of a block of queries."""

    def __init__(self, block: bytes, k: int, relax: float):
        held = np.load(io.BytesIO(block))
        self.queries, self.ids, self.k, self.relax = held["vectors"], held["ids"], k, relax
        self.scores = np.full((len(self.ids), k), -np.inf)
        self.found = np.full((len(self.ids), k), np.iinfo(np.int64).max)

    def pass_by(self, tree: VantageTree) -> None:
        _, at = tree.search(self.queries, self.k + 1, self.relax, self.scores.min(1) if self.k else None)
        q, c = np.nonzero(at >= 0)
        points = at[q, c]
        # the measure itself, summed in one fixed order for every pair
        exact = np.concatenate([(self.queries[q[i:i + 65536]] * tree.points[points[i:i + 65536]]).sum(1) for i in range(0, max(1, len(q)), 65536)])
        upto, n = np.concatenate([[0], np.cumsum(tree.lengths)]), tree.lengths[points]
        rows = np.repeat(np.arange(len(points)), n)
        ids = tree.ids[np.arange(len(rows)) - np.repeat(np.cumsum(n) - n, n) + np.repeat(upto[points], n)]
        other = ids != self.ids[q[rows]]
        q, ids, scores = q[rows][other], ids[other], exact[rows][other]
        some = np.unique(q)  # the others keep what they have
        place = np.concatenate([np.repeat(some, self.k), q])
        ids, scores = np.concatenate([self.found[some].ravel(), ids]), np.concatenate([self.scores[some].ravel(), scores])
        order = np.lexsort((ids, -scores, place))
        nth = np.arange(len(order)) - np.repeat(np.searchsorted(place[order], some), np.bincount(place, minlength=len(self.ids))[some])
        order, nth = order[nth < self.k], nth[nth < self.k]
        self.found[place[order], nth], self.scores[place[order], nth] = ids[order], scores[order]

    def rows(self) -> pd.DataFrame:
        q, c = np.nonzero(np.isfinite(self.scores))
        return pd.DataFrame({"query_id": self.ids[q], "rank": (c + 1).astype(np.int32), "vec_id": self.found[q, c], "score": self.scores[q, c]})


def _meet(k: int, relax: float):
    def meet(batches):
        """Rows come by block: its queries first, then every tree."""
        now, nearest_ = None, None
        for pdf in released(batches):
            for dim, block, shard, payload in zip(pdf["dim"], pdf["block"], pdf["shard"], pdf["payload"], strict=True):
                if (dim, block) != now:
                    if nearest_ is not None:
                        yield nearest_.rows()
                    now, nearest_ = (dim, block), None
                if shard < 0:
                    nearest_ = Nearest(payload, k, relax)
                elif nearest_ is not None:
                    nearest_.pass_by(VantageTree.load(payload))
        if nearest_ is not None:
            yield nearest_.rows()

    return meet


def usable(rows: DataFrame, vector: str = "embedding", key: str = "vec_id") -> DataFrame:
    """dim, vec_id and vector (doubles) of the rows that take part."""
    v = F.col(vector).cast("array<double>")
    bad = F.exists("vector", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    out = rows.select(F.col(key).cast("long").alias("vec_id"), v.alias("vector")).filter("vec_id is not null and vector is not null")
    return out.filter(~bad & F.exists("vector", lambda x: x != 0)).select(F.size("vector").alias("dim"), "vec_id", "vector")


def nearest(rows: DataFrame, queries: DataFrame, k: int = K, relax: float = RELAX, shard_rows: int = 16384, block_rows: int = 16384, least_rows: int = 1024) -> DataFrame:
    """The ``k`` nearest rows of each query: query_id, rank, vec_id, score. Both inputs come from ``usable``."""
    spark = rows.sparkSession
    tasks = shuffle_parts(spark)
    queries = queries.groupBy("dim", "vec_id").agg(F.min("vector").alias("vector"))
    counts = rows.groupBy("dim").agg(F.count("*").alias("n")).join(queries.groupBy("dim").agg(F.count("*").alias("q")), "dim").collect()
    # a row for each length of vector, of which a table has one or a few
    sizes = spark.createDataFrame([(r["dim"], -(-r["n"] // shard_rows), max(-(-r["q"] // block_rows), min(tasks, -(-r["q"] // least_rows)))) for r in counts], "dim int, shards int, blocks int")
    sized = F.broadcast(sizes)
    dealt = rows.join(sized, "dim").withColumn("shard", F.pmod(F.xxhash64("vec_id"), "shards").cast("int"))
    trees = materialize(dealt.groupBy("dim", "shard").applyInPandas(_build(k), "dim int, shard int, tree binary"), "vantage-trees")
    packed = queries.join(sized, "dim").withColumn("block", F.pmod(F.xxhash64("vec_id"), "blocks").cast("int")).groupBy("dim", "block").applyInPandas(_pack, "dim int, block int, payload binary")
    each = trees.join(sized, "dim").select("dim", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("block"), "shard", F.col("tree").alias("payload"))
    met = packed.select("dim", "block", F.lit(-1).alias("shard"), "payload").unionByName(each)
    parts = max(1, sum(max(-(-r["q"] // block_rows), min(tasks, -(-r["q"] // least_rows))) for r in counts))
    met = met.repartition(parts, "dim", "block").sortWithinPartitions("dim", "block", "shard")
    return met.mapInPandas(_meet(k, relax), "query_id long, rank int, vec_id long, score double")


def op3_vantage_trees(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = usable(table(spark, sf_dir, "embeddings"))
    return nearest(rows, rows.filter("vec_id % 20 = 0"))
