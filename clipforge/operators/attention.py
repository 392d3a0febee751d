"""Transformer data flow in relational form: attention and its sparse variants, rotary encoding, conditioning, expert routing.

Tokens are rows (item, tok, val): queries, keys and values are the same scalar
here, or vectors through ``score``. Work is bounded by the group that tokens
meet in; groups are parts of one item, never of the table.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from clipforge.functions.exprs import dot, int_div


def attend(tokens: DataFrame, group: list[Column] | None = None, weight: float = 1.0) -> DataFrame:
    """(item, tok, out, pairs): softmax-weighted mean of the values of the tokens in the same group of the same item."""
    rows = tokens.withColumn("g", F.struct(*group) if group else F.struct(F.lit(0)))
    q = rows.select("item", "g", "tok", F.col("val").alias("q"))
    k = rows.select("item", "g", F.col("val").alias("k"))
    w = F.exp(F.col("q") * F.col("k") * weight)
    return q.join(k, ["item", "g"]).groupBy("item", "tok").agg((F.sum(w * F.col("k")) / F.sum(w)).alias("out"), F.count("*").alias("pairs"))


def stride_group(tok: Column, k: int = 4) -> Column:
    return tok % k


def block_group(tok: Column, k: int = 4) -> Column:
    """Blocks of k neighbours, dealt to k groups."""
    return int_div(tok, k) % k


def attend_separated(cells: DataFrame) -> DataFrame:
    """Within each slice, then along time at each place: the separated baseline. Cells are (item, t, y, x, val)."""
    tok = F.col("t") * 16 + F.col("y") * 4 + F.col("x")
    space = attend(cells.select("item", tok.alias("tok"), "val", "t"), [F.col("t")])
    again = space.select("item", "tok", F.col("out").alias("val"), F.col("pairs").alias("space_pairs"))
    time = attend(again, [F.col("tok") % 16])
    return time.join(again.select("item", "tok", "space_pairs"), ["item", "tok"]).withColumn("pairs", F.col("pairs") + F.col("space_pairs")).drop("space_pairs")


def reach(tokens: DataFrame, groups: list[Column]) -> DataFrame:
    """(item, a, b): tokens whose value may arrive after one layer per grouping."""
    now = tokens.select("item", F.col("tok").alias("a"), F.col("tok").alias("tok"))
    for g in groups:
        keyed = tokens.select("item", "tok", g.alias("g"))
        now = now.join(keyed, ["item", "tok"]).select("item", "a", "g").distinct().join(keyed, ["item", "g"]).select("item", "a", "tok").distinct()
    return now.withColumnRenamed("tok", "b")


def cross_attend(q: DataFrame, kv: DataFrame, scale: float = 8.0) -> DataFrame:
    """Each row of ``q`` (id, vec) over the few text rows of ``kv`` (tid, key, value)."""
    w = F.exp(dot(F.col("vec"), F.col("key")) * scale)
    return q.join(F.broadcast(kv)).groupBy("id").agg((F.sum(w * F.col("value")) / F.sum(w)).alias("out"))


def joint_attend(visual: DataFrame, text: DataFrame) -> DataFrame:
    """Visual and text tokens in one sequence; the visual rows stay."""
    both = visual.withColumn("modality", F.lit("visual")).unionByName(text.withColumn("modality", F.lit("text")))
    keyed = both.select("item", F.when(F.col("modality") == "visual", F.col("tok")).otherwise(-1 - F.col("tok")).alias("tok"), "val")
    return attend(keyed).filter("tok >= 0")


# --- rotary encoding -----------------------------------------------------------------------------

def rope1d(vec: Column, pos: Column, size: int, base: float = 10_000.0) -> Column:
    """Neighbouring pairs of a vector of ``size`` turned by angles that fall with the pair's number."""
    out = []
    for p in range(size // 2):
        angle = pos.cast("double") * F.lit(base ** (-2.0 * p / size))
        a, b = F.get(vec, F.lit(2 * p)).cast("double"), F.get(vec, F.lit(2 * p + 1)).cast("double")
        out += [a * F.cos(angle) - b * F.sin(angle), a * F.sin(angle) + b * F.cos(angle)]
    return F.array(*out)


def rope3d(vec: Column, t: Column, h: Column, w: Column, split: tuple[int, int, int], base: float = 10_000.0) -> Column:
    """Channels split among three axes, each turned by its own place."""
    parts, at = [], 1
    for pos, n in zip((t, h, w), split, strict=True):
        parts.append(rope1d(F.slice(vec, at, n), pos, n, base))
        at += n
    return F.concat(*parts)


# --- conditioning --------------------------------------------------------------------------------

def modulate(x: Column, shift: Column, scale: Column, gate: Column) -> Column:
    """x plus gate times the scaled and shifted x; gate 0 leaves x."""
    return F.transform(x, lambda v: v + gate * (v * (1 + scale) + shift))


def modulation_params(blocks: Column, hidden: Column, shared: Column) -> Column:
    """Six vectors of each block from one hidden vector, or one such layer for all."""
    one = hidden * hidden * 6
    return F.when(shared, one + blocks * hidden * 6).otherwise(blocks * one)


def time_features(t: Column, size: int, base: float = 10_000.0) -> Column:
    half = size // 2
    f = [math.exp(-math.log(base) * i / half) for i in range(half)]
    return F.array(*[F.cos(t * v) for v in f], *[F.sin(t * v) for v in f])


def condition(t_emb: Column, text_vec: Column) -> Column:
    return F.zip_with(t_emb, text_vec, lambda a, b: a + b.cast("double"))


# --- experts -------------------------------------------------------------------------------------

def route_topk(df: DataFrame, key: str, scores: Column, k: int = 6, shared: int = 2) -> DataFrame:
    """(key, expert, weight): the k best-scored experts, weights by softmax over them, and the shared ones (negative numbers) with weight 1."""
    ranked = F.slice(F.sort_array(F.transform(scores, lambda s, i: F.struct(s.cast("double").alias("s"), (-i).alias("i"))), asc=False), 1, k)
    total = F.aggregate(ranked, F.lit(0.0), lambda a, x: a + F.exp(x["s"]))
    routed = F.transform(ranked, lambda x: F.struct((-x["i"]).cast("bigint").alias("expert"), (F.exp(x["s"]) / total).alias("weight")))
    fixed = F.array(*[F.struct(F.lit(-1 - i).cast("bigint").alias("expert"), F.lit(1.0).alias("weight")) for i in range(shared)])
    return df.select(key, F.explode(F.concat(routed, fixed)).alias("r")).select(key, "r.expert", "r.weight")


def expert_load(routed: DataFrame, experts: int = 64, capacity: float = 1.25) -> DataFrame:
    """Rows per routed expert, load over the mean, and what exceeds the capacity."""
    own = routed.filter("expert >= 0").groupBy("expert").agg(F.count("*").alias("load"))
    mean = F.sum("load").over(W.partitionBy()) / experts
    return own.withColumn("mean_", mean).select("expert", "load", (F.col("load") / F.col("mean_")).alias("over_mean"), F.greatest(F.lit(0), F.col("load") - F.floor(F.col("mean_") * capacity)).cast("bigint").alias("overflow"))


def expert_device(expert: Column, per_device: int = 8) -> Column:
    return int_div(expert, per_device)


def pipeline_partition(layers: DataFrame, stages: int) -> DataFrame:
    """Contiguous stages by prefix sums of cost; a model's layers are tens of rows."""
    upto = F.sum("cost").over(W.orderBy("layer").rowsBetween(W.unboundedPreceding, 0))
    total = F.sum("cost").over(W.partitionBy())
    return layers.withColumn("stage", F.least(F.lit(stages - 1).cast("bigint"), F.floor((upto - F.col("cost") / 2) * stages / total).cast("bigint")))


def layer_table(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(n).select(F.col("id").alias("layer"), (F.lit(10) + F.col("id") % 5).alias("cost"))
