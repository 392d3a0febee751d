"""N-gram Jaccard join by a MinHash LSH forest with exact verification.

Texts are lower-cased and cut at white space; every run of five words is a
shingle (a text of fewer words is one shingle; a text without words has none and
links to copies of itself only). Each of ``TREES`` trees orders the distinct
texts by a path of ``LONGEST`` MinHash values, kept as one number whose leading
bytes are the prefixes, so a level of the trie is an aggregate over a shifted
path.

Texts under one prefix are candidates. Prefixes start at ``LONGEST`` values and
are shortened value by value until the estimated recall is met (``forest_ties``):
pairs that are met by one tree only, against those met by two, tell how many are
met by none. Shortening ends at the depth at which a pair at the threshold is met
with probability ``RECALL`` whatever the data (``prefix_length``).

Exact copies are one node. Nodes under a prefix are tied to its smallest node,
so a bucket of any size gives one edge for each member, and the components of
these ties hold every candidate pair. Inside a component all pairs are verified
exactly on their shingle sets, in blocks of at most about ``BLOCK`` texts and
``BLOCK_BYTES``: a task holds two blocks, whatever the component's size, and
gives counts of links and a spanning forest, never the pairs.

``join_documents`` gives one row per input row: doc_id, class_id (the smallest
id of all texts linked directly or in steps) and n_links (other rows whose
similarity is at least the threshold, copies included). Null texts count as
empty. Null ids keep their rows; a class of null ids only has a null class_id.
Rows that repeat are copies. An empty table gives no rows. Other columns are
ignored there and pass through ``keep_one``.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from clipforge.operators.graph import connected

from .common import give_back, materialize, only_likely, released, shuffle_parts, table

WORDS, THRESHOLD = 5, 0.8
TREES, LONGEST, RECALL = 24, 8, 0.999
BLOCK, BLOCK_BYTES = 512, 4 << 20


def prefix_length(threshold: float = THRESHOLD, trees: int = TREES, longest: int = LONGEST, recall: float = RECALL) -> int:
    """The longest prefix at which a pair of ``threshold`` is met with probability ``recall``: nothing shorter is needed, whatever the data."""
    for depth in range(longest, 1, -1):
        if 1 - (1 - threshold ** depth) ** trees >= recall:
            return depth
    return 1


class Shingler:
    """Sets of 64-bit shingle hashes, by prefix sums over the bytes of a text."""

    def __init__(self, words: int = WORDS):
        rng = np.random.default_rng(99)
        self.words = words
        self.value = rng.integers(1, 1 << 63, 256, np.uint64)
        self.base = np.uint64(0x9E3779B97F4A7C15)
        self.inverse = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))
        self.white = np.zeros(256, bool)
        self.white[[9, 10, 11, 12, 13, 32]] = True
        self._grow(1 << 16)

    def _grow(self, n: int) -> None:
        self.up, self.down = np.cumprod(np.full(n, self.base)), np.cumprod(np.full(n, self.inverse))

    @staticmethod
    def _mix(h: np.ndarray) -> np.ndarray:
        h = (h ^ (h >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)
        return h ^ (h >> np.uint64(29))

    def __call__(self, text: str | None) -> np.ndarray:
        raw = np.frombuffer((text or "").lower().encode("utf-8", "replace"), np.uint8)
        if len(raw) >= len(self.up):
            self._grow(2 * len(raw))
        edge = np.flatnonzero(np.diff(np.concatenate([[True], self.white[raw], [True]]).view(np.int8)))
        first, last = edge[::2], edge[1::2]
        if not len(first):
            return np.zeros(0, np.uint64)
        total = np.concatenate([[np.uint64(0)], np.cumsum(self.value[raw] * self.up[:len(raw)])])
        word = self._mix((total[last] - total[first]) * self.down[first] + (last - first).astype(np.uint64))
        span = min(self.words, len(word))
        code = np.zeros(len(word) - span + 1, np.uint64)
        for j in range(span):
            code = code * self.base + word[j:j + len(code)]
        return np.unique(self._mix(code + np.uint64(span)))


class Forest:
    """The path of a set of shingles in each tree: ``LONGEST`` MinHash values of eight bits, the first in the leading byte."""

    def __init__(self, trees: int = TREES):
        rng = np.random.default_rng(4242)
        self.trees = trees
        self.a = rng.integers(0, 1 << 31, trees * LONGEST, np.uint32) * np.uint32(2) + np.uint32(1)
        self.b = rng.integers(0, 1 << 32, trees * LONGEST, np.uint32)

    def paths(self, shingles: np.ndarray) -> np.ndarray:
        low = np.full(len(self.a), np.iinfo(np.uint32).max, np.uint32)
        code = (shingles >> np.uint64(32)).astype(np.uint32)
        for i in range(0, len(code), 256):
            np.minimum(low, ((code[i:i + 256, None] ^ self.b) * self.a).min(0), out=low)
        values = ((low * np.uint32(0x9E3779B1)) >> np.uint32(24)).astype(np.uint8)
        return np.ascontiguousarray(values.reshape(self.trees, LONGEST)).view(">u8").ravel().astype(np.uint64).view(np.int64)


def _prefix(path: Column, depth: int) -> Column:
    return F.shiftrightunsigned(path, 8 * (LONGEST - depth))


def _marked(docs: DataFrame) -> DataFrame:
    """doc_id, text and the 128-bit hash of the text."""
    text = F.coalesce(F.col("text"), F.lit(""))
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("text"), F.xxhash64(text).alias("t1"), F.xxhash64(F.lit(29), text).alias("t2"))


def _nodes(docs: DataFrame, trees: int, words: int) -> DataFrame:
    """A row for each distinct text: node, t1, t2, its bytes, its smallest id, how many rows it has (and of that id), and the paths."""
    def sign(batches):
        cut, forest, known = Shingler(words), Forest(trees), {}
        for pdf in released(batches):
            paths = []
            for key, text in zip(zip(pdf["t1"].tolist(), pdf["t2"].tolist(), strict=True), pdf["text"], strict=True):
                if key not in known:  # copies are signed once in a while
                    if len(known) >= 4096:
                        known.clear()
                    known[key] = forest.paths(s) if len(s := cut(text)) else None
                paths.append(known[key])
            yield pd.DataFrame({"t1": pdf["t1"], "t2": pdf["t2"], "size": pdf["size"], "paths": paths})

    marked = _marked(docs)
    copies = marked.groupBy("t1", "t2", "doc_id").agg(F.count("*").alias("n")).groupBy("t1", "t2").agg(F.min("doc_id").alias("doc"), F.sum("n").alias("copies"), F.min_by("n", F.struct(F.col("doc_id").isNull(), "doc_id")).alias("same"))
    sized = marked.select("t1", "t2", F.octet_length("text").alias("size"), "text")
    signed = sized.mapInPandas(sign, "t1 long, t2 long, size int, paths array<long>").groupBy("t1", "t2").agg(F.first("size").alias("size"), F.first("paths").alias("paths"))
    return materialize(copies.join(signed, ["t1", "t2"]).withColumn("node", F.monotonically_increasing_id()), "forest-nodes")


def forest_ties(nodes: DataFrame, threshold: float = THRESHOLD, trees: int = TREES, recall: float = RECALL) -> tuple[DataFrame, int]:
    """(node, head) pairs that share a prefix in some tree, and the depth to which prefixes had to be shortened.

    At each depth the pairs are counted by the number of trees that tie them. Of
    those that no tree ties there are about f1 (f1 - 1) / 2 (f2 + 1), from the
    pairs tied once and twice; the depth stands if what is tied is at least
    ``recall`` of the sum. Pairs below the threshold count as well, so the
    estimate errs towards shorter prefixes.
    """
    paths = nodes.select("node", F.posexplode("paths").alias("tree", "path"))
    floor = prefix_length(threshold, trees)
    for depth in range(LONGEST, floor - 1, -1):
        under = paths.select("node", "tree", _prefix(F.col("path"), depth).alias("prefix"))
        heads = under.groupBy("tree", "prefix").agg(F.min("node").alias("head"), F.count("*").alias("n")).filter("n > 1").drop("n")
        heads = materialize(heads, "forest-heads")
        place = F.xxhash64("tree", "prefix")
        tied = only_likely(under, place, heads, place).join(heads, ["tree", "prefix"]).filter("node <> head")
        ties = materialize(tied.groupBy("node", "head").agg(F.count("*").cast("int").alias("met")), "forest-ties")
        if depth == floor:
            break
        n, once, twice = ties.agg(F.count("*"), F.count_if(F.col("met") == 1), F.count_if(F.col("met") == 2)).first()
        if n >= recall * (n + once * (once - 1) / (2 * (twice + 1))):
            break
    return ties, depth


def _pairs(left: list[np.ndarray], right: list[np.ndarray] | None, threshold: float) -> np.ndarray:
    """Boolean matrix: which sets of left and right (or of left alone) are similar enough."""
    sets = left + (right or [])
    sizes = np.array([len(s) for s in sets])
    owner, every = np.repeat(np.arange(len(sets)), sizes), np.concatenate(sets)
    order = np.argsort(every, kind="stable")
    every, owner = every[order], owner[order]
    fresh = np.concatenate([[True], every[1:] != every[:-1]])
    column = np.cumsum(fresh) - 1
    shared = np.bincount(column) > 1
    keep = shared[column]
    owner, column = owner[keep], (np.cumsum(shared) - 1)[column[keep]]
    common = np.zeros((len(left), len(sets) - len(left) if right is not None else len(sets)), np.float64)
    width = max(1, (1 << 22) // len(sets))
    cuts = np.searchsorted(column, np.arange(0, int(shared.sum()) + width, width))
    for k in range(len(cuts) - 1):  # columns in spans, so memory is bounded
        a, b = cuts[k], cuts[k + 1]
        grid = np.zeros((len(sets), width), np.float32)
        grid[owner[a:b], column[a:b] - k * width] = 1
        common += grid[:len(left)] @ (grid[len(left):] if right is not None else grid).T
    other = sizes[len(left):] if right is not None else sizes
    union = sizes[:len(left), None] + other[None, :] - common
    return common >= threshold * union - 1e-9


def _spanning(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The root of each of n places after joining a[i] with b[i]: least labels until nothing moves."""
    label = np.arange(n)
    while len(a):
        low = label.copy()
        np.minimum.at(low, a, label[b])
        np.minimum.at(low, b, label[a])
        low = low[low]
        if (low == label).all():
            break
        label = low
    return label


def _verify(threshold: float, words: int):
    def verify(pdf: pd.DataFrame) -> pd.DataFrame:
        cut, rows = Shingler(words), []
        give_back()
        for _, part in pdf.groupby(["comp", "i", "j"], sort=False):
            node, copies = part["node"].to_numpy(np.int64), part["copies"].to_numpy(np.int64)
            sets = [cut(t) for t in part["text"]]
            i, j = int(part["i"].iloc[0]), int(part["j"].iloc[0])
            if i == j:
                hit = _pairs(sets, None, threshold)
                np.fill_diagonal(hit, False)
                links = hit @ copies
                a, b = np.nonzero(np.triu(hit))
            else:
                own = part["blk"].to_numpy() == i
                l, r = np.flatnonzero(own), np.flatnonzero(~own)
                if not len(l) or not len(r):
                    continue
                hit = _pairs([sets[k] for k in l], [sets[k] for k in r], threshold)
                links = np.zeros(len(node), np.int64)
                links[l], links[r] = hit @ copies[r], copies[l] @ hit
                a, b = np.nonzero(hit)
                a, b = l[a], r[b]
            root = _spanning(len(node), a, b)
            rows.append(pd.DataFrame({"node": node, "links": links, "root": node[root]}))
        return pd.concat(rows) if rows else pd.DataFrame({"node": pd.Series(dtype="int64"), "links": pd.Series(dtype="int64"), "root": pd.Series(dtype="int64")})

    return verify


def _components(ties: DataFrame) -> DataFrame:
    """(node, comp). Each node starts from the least of its heads, so a bucket's edges are a few before they meet any other row."""
    first = materialize(ties.groupBy("node").agg(F.min("head").alias("low"), F.collect_set("head").alias("heads")), "forest-first")  # a head for each tree at most
    heads = materialize(first.select("low", F.explode("heads").alias("head")).distinct(), "forest-heads")
    # a head may have lower heads of its own
    own = first.select("low", F.col("node").alias("head")).join(heads.select("head").distinct(), "head", "left_semi").select("low", "head")
    labels = connected(heads.unionByName(own).select(F.col("low").alias("a"), F.col("head").alias("b")), "candidates")
    alone = heads.select(F.col("head").alias("node")).distinct().join(first.select("node"), "node", "left_anti")
    every = first.select("node", "low").unionByName(alone.select("node", F.col("node").alias("low")))
    return every.join(labels.withColumnRenamed("node", "low"), "low", "left").select("node", F.coalesce("label", "low").alias("comp"))


def _classes(docs: DataFrame, threshold: float, trees: int, words: int) -> DataFrame:
    """Nodes with their links and the root node of their class."""
    nodes = _nodes(docs, trees, words)
    ties, _ = forest_ties(nodes, threshold, trees)
    parts = _components(ties).join(nodes.select("node", "t1", "t2", "doc", "copies", "size"), "node")
    parts = materialize(parts, "forest-parts")
    sizes = parts.groupBy("comp").agg(F.greatest(F.ceil(F.count("*") / F.lit(BLOCK)), F.ceil(F.sum("size") / F.lit(BLOCK_BYTES))).cast("int").alias("blocks"))
    placed = parts.join(sizes, "comp").withColumn("blk", F.pmod(F.xxhash64("node"), "blocks").cast("int"))
    placed = materialize(placed, "forest-members")
    n, size = parts.agg(F.count("*"), F.coalesce(F.sum("size"), F.lit(0))).first()
    packs = max(1, n // BLOCK, size // BLOCK_BYTES)
    likely = only_likely(_marked(docs), F.col("t1"), placed, F.col("t1"))
    texts = likely.join(placed, ["t1", "t2"]).filter(F.col("doc_id").eqNullSafe(F.col("doc")))
    texts = texts.groupBy("node", "comp", "blocks", "blk", "copies").agg(F.min("text").alias("text"))
    pairs = F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), lambda k: F.struct(F.least(k, F.col("blk")).alias("i"), F.greatest(k, F.col("blk")).alias("j")))
    dealt = texts.withColumn("pair", F.explode(pairs)).select("node", "comp", "blk", "copies", "text", "pair.i", "pair.j", "blocks")
    # small components share a task, a large one has a task for each pair of blocks
    dealt = dealt.withColumn("pack", F.when(F.col("blocks") == 1, F.pmod(F.xxhash64("comp"), F.lit(packs))).otherwise(F.xxhash64("comp")))
    # as many tasks as packs: they are long for their bytes, so small ones are not put together
    tasks = min(100_000, max(shuffle_parts(docs.sparkSession), packs))
    checked = dealt.repartition(tasks, "pack", "i", "j").groupBy("pack", "i", "j").applyInPandas(_verify(threshold, words), "node long, links long, root long")
    checked = materialize(checked, "forest-links")
    links = checked.groupBy("node").agg(F.sum("links").alias("links"))
    steps = checked.filter("node <> root").select(F.col("node").alias("a"), F.col("root").alias("b"))
    roots = connected(steps, "classes")
    return nodes.drop("paths").join(links, "node", "left").join(roots, "node", "left").withColumn("root", F.coalesce("label", "node"))


def _named(docs: DataFrame, threshold: float, trees: int, words: int) -> DataFrame:
    """Per text hash: class_id, n_links, and whether the text is the one that stands for its class."""
    nodes = _classes(docs, threshold, trees, words)
    chief = nodes.groupBy("root").agg(F.min("doc").alias("class_id"), F.min_by("node", F.struct(F.col("doc").isNull(), "doc", "node")).alias("chief"))
    return nodes.join(chief, "root").select("t1", "t2", "class_id", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links"), (F.col("node") == F.col("chief")).alias("stands"), "doc", "same")


def join_documents(docs: DataFrame, threshold: float = THRESHOLD, trees: int = TREES, words: int = WORDS) -> DataFrame:
    named = _named(docs, threshold, trees, words).select("t1", "t2", "class_id", "n_links")
    return _marked(docs).select("doc_id", "t1", "t2").join(named, ["t1", "t2"]).select("doc_id", "class_id", "n_links")


def keep_one(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """The rows of ``docs`` that stand for their class, one for each."""
    named = _named(docs, threshold, TREES, WORDS).filter("stands").select("t1", "t2", "doc", "same")
    text = F.coalesce(F.col("text"), F.lit(""))
    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns])  # so that no column meets one of the same name
    tagged = docs.select(row.alias("row"), F.xxhash64(text).alias("k1"), F.xxhash64(F.lit(29), text).alias("k2"), F.col("doc_id").cast("long").alias("id"))
    out = tagged.join(named, (F.col("k1") == F.col("t1")) & (F.col("k2") == F.col("t2")) & F.col("id").eqNullSafe(F.col("doc")))
    once = out.filter("same = 1").select("row")
    again = out.filter("same > 1").dropDuplicates(["t1", "t2"]).select("row")
    return once.unionByName(again).select(*[F.col("row")[c].alias(c) for c in docs.columns])


def op1_shingle_forest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return join_documents(table(spark, sf_dir, "documents").select("doc_id", "text"))
