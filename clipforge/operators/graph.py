"""Connected components over edges of longs, by contraction."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from clipforge.sources.scratch import materialize


def _ranked(node: Column) -> Column:
    """Nodes in the order of a hash, so that no order of the ids makes long descents."""
    return F.struct(F.xxhash64(node).alias("h"), node.alias("node"))


def connected(edges: DataFrame, name: str = "components") -> DataFrame:
    """(node, label) for every node of ``edges`` (a, b) that are not loops; equal labels are one component.

    Every round each node moves to the least node, by hash, among itself and its
    neighbours, and edges are carried to where their ends have moved; loops and
    repeats go, so a round's edges are fewer than the last one's and a large
    component falls together fast. The moves of the rounds are then joined from
    the last to the first. Each round is a table in the shared folder, so lineage
    stays short; only aggregates cross the network, and no node's neighbours are
    gathered.
    """
    edges = materialize(edges.filter("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), f"{name}-edges")
    moves = []
    while not edges.isEmpty() or not moves:
        both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min(_ranked(F.col("b"))).alias("low"))
        moves.append(materialize(least.select(F.col("a").alias("node"), F.least("low", _ranked(F.col("a")))["node"].alias("to")), f"{name}-moves"))
        ends = {k: moves[-1].select(F.col("node").alias(k), F.col("to").alias(f"{k}_to")) for k in ("a", "b")}
        edges = edges.join(ends["a"], "a").join(ends["b"], "b").filter("a_to <> b_to")
        edges = materialize(edges.select(F.least("a_to", "b_to").alias("a"), F.greatest("a_to", "b_to").alias("b")).distinct(), f"{name}-edges")
    labels = moves[-1].select("node", F.col("to").alias("label"))
    for move in reversed(moves[:-1]):
        higher = labels.withColumnRenamed("node", "to")
        labels = move.join(higher, "to", "left").select("node", F.coalesce("label", "to").alias("label"))
    return materialize(labels, name) if len(moves) > 1 else labels
