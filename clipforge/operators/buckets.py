"""Bucketed data sets: token calculus, assignment, cropping, batches and their balance."""

from __future__ import annotations

import json

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from clipforge.functions.exprs import int_div, key_int

BUCKET_SCHEMA = "bucket_id bigint, batch bigint, t bigint, h bigint, w bigint"
# Example buckets as (batch, frames, height, width).
PRINTED = ((1, 29, 640, 640), (1, 29, 480, 854), (1, 29, 854, 480), (1, 125, 320, 320), (8, 29, 320, 320))


def bucket_table(spark: SparkSession, buckets) -> DataFrame:
    """A bucket configuration as a small table (a bucket per row; a configuration has tens)."""
    return spark.createDataFrame([(i, *map(int, b)) for i, b in enumerate(buckets)], BUCKET_SCHEMA)


class BucketConfig:
    """Bucket sets by stage from JSON ``{"stage": [[batch, frames, height, width], ...]}``."""

    def __init__(self, sets: dict[str, list]):
        self.sets = sets

    @classmethod
    def from_json(cls, text: str) -> BucketConfig:
        return cls(json.loads(text))

    def table(self, spark: SparkSession, stage: str) -> DataFrame:
        return bucket_table(spark, self.sets[stage])


def latent_frames(t: Column) -> Column:
    """The first frame alone, then groups of four."""
    return F.lit(1).cast("bigint") + int_div(t - 1, 4)


def latent_cells(t: Column, h: Column, w: Column) -> Column:
    return latent_frames(t) * int_div(h, 8) * int_div(w, 8)


def with_tokens(buckets: DataFrame) -> DataFrame:
    """Adds latent shape, cells of a batch, and tokens after 2 x 2 patches."""
    c = F.col
    out = buckets.withColumns({"lt": latent_frames(c("t")), "lh": int_div(c("h"), 8), "lw": int_div(c("w"), 8)})
    return out.withColumns({"cells": c("batch") * c("lt") * c("lh") * c("lw"), "tokens": c("batch") * c("lt") * int_div(c("lh"), 2) * int_div(c("lw"), 2)})


def assign_frames(df: DataFrame, lengths: list[int], rule: str = "floor") -> DataFrame:
    """Adds ``bucket_t``: a literal sorted list, so no join. Null where the rule has no length."""
    ls, t = F.array(*[F.lit(int(x)).cast("bigint") for x in sorted(set(lengths))]), F.col("frames")
    if rule == "floor":
        pick = F.array_max(F.filter(ls, lambda x: x <= t))
    elif rule == "ceil":
        pick = F.array_min(F.filter(ls, lambda x: x >= t))
    elif rule == "nearest":
        pick = F.array_min(F.transform(ls, lambda x: F.struct(F.abs(x - t).alias("d"), x.alias("x"))))["x"]
    else:
        raise ValueError(f"unknown rule {rule}")
    return df.withColumn("bucket_t", pick)


def assign_area(df: DataFrame, buckets, aspect_tiebreak: bool = True) -> DataFrame:
    """Adds ``bucket``: within the frame length, the nearest area; ties by aspect, then by id."""
    opts = F.array(*[F.struct(F.lit(i).cast("bigint").alias("id"), *[F.lit(int(v)).cast("bigint").alias(n) for n, v in zip("bthw", b, strict=True)]) for i, b in enumerate(buckets)])
    width, height = F.col("width"), F.col("height")
    fits = F.filter(opts, lambda b: b["t"] == F.col("bucket_t"))

    def rank(b: Column) -> Column:
        # cross-multiplied, so equal aspects tie exactly
        skew = F.abs(width * b["h"] - height * b["w"]) if aspect_tiebreak else F.lit(0).cast("bigint")
        return F.struct(F.abs(b["h"] * b["w"] - height * width).alias("d"), skew.alias("s"), b.alias("b"))

    return df.withColumn("bucket", F.array_min(F.transform(fits, rank))["b"])


def assign_bucket(df: DataFrame, buckets=PRINTED, rule: str = "floor", aspect_tiebreak: bool = True) -> DataFrame:
    """Frames first, then area. Media too short for every bucket get a null bucket."""
    return assign_area(assign_frames(df, [b[1] for b in buckets], rule), buckets, aspect_tiebreak)


def crop_start(key: Column, t: Column, t_b: Column, seed: str = "c") -> Column:
    """A keyed first frame among those that leave room."""
    return key_int(key, seed) % (t - t_b + 1)


def tune_batch(buckets: DataFrame, budget: int) -> DataFrame:
    """Adds the greatest batch whose cells stay within the budget, one at least."""
    cells = latent_cells(F.col("t"), F.col("h"), F.col("w"))
    return buckets.withColumn("tuned", F.greatest(F.lit(1).cast("bigint"), int_div(F.lit(budget), cells)))


def pack_batches(df: DataFrame, shards: int = 8, drop_remainder: bool = False) -> DataFrame:
    """Batches of one bucket each: keyed order within (bucket, shard), so no bucket is one partition."""
    shard = key_int(F.col("media_id"), "s") % shards
    order = W.partitionBy("bucket_id", "shard").orderBy(key_int(F.col("media_id"), "o"), "media_id")
    out = df.withColumn("shard", shard).withColumn("batch_no", int_div(F.row_number().over(order) - 1, F.col("batch")))
    if drop_remainder:
        full = F.count("*").over(W.partitionBy("bucket_id", "shard", "batch_no")) == F.col("batch")
        out = out.withColumn("full_", full).filter("full_").drop("full_")
    return out


def step_balance(batches: DataFrame, ranks: int = 8) -> DataFrame:
    """Per step of ``ranks`` batches: the longest wait. ``batches`` has seq and cells."""
    step = int_div(F.col("seq"), ranks)
    out = batches.groupBy(step.alias("step")).agg(F.count("*").alias("n"), F.max("cells").alias("most"), F.sum("cells").cast("bigint").alias("total"))
    return out.withColumn("wait", (F.col("most") * F.col("n") - F.col("total")).cast("bigint"))
