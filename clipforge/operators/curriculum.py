"""Stages of training: what a sample can serve, mixing, stopping, averaging, convergence."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from clipforge.functions.exprs import int_div, key_int

STAGE_SCHEMA = "stage string, step_no bigint, image_res bigint, frames bigint, video_res bigint, batch bigint, steps bigint, lr double"
# Stage, order, image resolution, video frames and resolution (0: none), batch, steps (order of magnitude), learning rate.
STAGES = (
    ("image", 1, 320, 0, 0, 4096, 100_000, 1e-4), ("image", 2, 640, 0, 0, 2048, 100_000, 1e-4),
    ("video", 3, 0, 29, 320, 1024, 100_000, 1e-4), ("video", 4, 0, 61, 320, 1024, 100_000, 1e-4),
    ("joint", 5, 640, 61, 640, 1024, 100_000, 1e-4), ("joint", 6, 960, 125, 640, 512, 10_000, 4e-5), ("joint", 7, 960, 125, 960, 256, 10_000, 4e-5),
    ("tune", 8, 960, 125, 960, 128, 1_000, 1e-5), ("tune", 9, 1440, 125, 960, 128, 1_000, 1e-5),
)


def stage_plan(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(STAGES, STAGE_SCHEMA)


def eligible(media: DataFrame, stages: DataFrame) -> DataFrame:
    """Pairs of media and stages that they can serve: as images (one frame) or as videos long and large enough. Stages are a table of tens of rows."""
    side = F.least("height", "width")
    as_image = (F.col("frames") == 1) & (F.col("image_res") > 0) & (side >= F.col("image_res"))
    as_video = (F.col("s_frames") > 0) & (F.col("frames") >= F.col("s_frames")) & (side >= F.col("video_res"))
    return media.join(F.broadcast(stages.withColumnRenamed("frames", "s_frames")), as_image | as_video)


def image_share(step: Column, steps: int, hi: float = 0.30, lo: float = 0.10, shape: str = "linear") -> Column:
    """The share of images at a step: falling linearly, or halfway at once."""
    if shape == "step":
        return F.when(step * 2 < steps, hi).otherwise(lo)
    return F.lit(hi) + (F.lit(lo) - F.lit(hi)) * step / F.lit(float(max(1, steps - 1)))


def mix_assign(media: DataFrame, steps: int, most: float = 0.5) -> DataFrame:
    """Each sample's step and whether that step draws it as an image; a share above ``most`` is refused."""
    step = key_int(F.col("media_id"), "step") % steps
    share = F.least(image_share(step, steps), F.lit(most))
    return media.withColumn("step", step).withColumn("as_image", (key_int(F.col("media_id"), "kind").cast("double") < share * F.lit(float(2**32))).cast("int"))


def epochs(samples: Column, batch: Column, steps: Column) -> Column:
    return batch * steps / samples


def early_stop(series: DataFrame, patience: int, by: str = "t", value: str = "v") -> DataFrame:
    """The first place after ``patience`` checks without a new low, and the low that stands there. A series has one row per check."""
    w = W.orderBy(by)
    best = F.min(value).over(w.rowsBetween(W.unboundedPreceding, 0))
    rows = series.withColumn("best", best).withColumn("n", F.row_number().over(w))
    rows = rows.withColumn("since", F.col("n") - F.max(F.when(F.col(value) == F.col("best"), F.col("n"))).over(w.rowsBetween(W.unboundedPreceding, 0)))
    return rows.filter(F.col("since") >= patience).agg(F.min_by(by, by).alias("stop_at"), F.min_by("best", by).alias("best"))


def ema(series: DataFrame, decay: float, keys: list[str], by: str, value: str) -> DataFrame:
    """Adds the exponential moving average (the first value has full weight; ``decay`` between 0 and 1).

    Series go in blocks so long that ``decay`` to a block's length is below what a
    double can tell from nothing: an average is the weighted sum of its own block
    up to its place and of the block before, so no weight overflows however long
    the series is.
    """
    if not 0 < decay < 1:
        raise ValueError("decay must be between 0 and 1")
    block = max(2, math.ceil(40 / -math.log(decay)))
    place, w = F.col("n_") % block, W.partitionBy(*keys).orderBy(by)
    rows = series.withColumn("n_", F.row_number().over(w) - 1).withColumn("block_", int_div(F.col("n_"), block))
    weight = F.when(F.col("n_") == 0, 1.0).otherwise(1 - decay)
    scaled = F.col(value) * weight / F.pow(F.lit(decay), place)
    inside = W.partitionBy(*keys, "block_").orderBy(by).rowsBetween(W.unboundedPreceding, 0)
    rows = rows.withColumn("own_", F.sum(scaled).over(inside) * F.pow(F.lit(decay), place))
    # the last average of the block before, without what lies further back
    ends = w.rowsBetween(W.unboundedPreceding, -1)
    before = F.coalesce(F.last(F.when(place == block - 1, F.col("own_")), ignorenulls=True).over(ends), F.lit(0.0))
    return rows.withColumn("ema", F.col("own_") + before * F.pow(F.lit(decay), place + 1)).drop("n_", "block_", "own_")


def inspection_points(steps: DataFrame, every: int, step: str = "step") -> DataFrame:
    return steps.filter(F.col(step) % every == 0)


def steps_to_converge(series: DataFrame, tol: float, keys: list[str], by: str, value: str) -> DataFrame:
    """Per key the first place from which every value stays within ``tol`` of the last."""
    w = W.partitionBy(*keys).orderBy(by)
    whole = w.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    gap = F.abs(F.col(value) - F.last(value).over(whole))
    after = F.max("gap_").over(w.rowsBetween(0, W.unboundedFollowing))
    return series.withColumn("gap_", gap).withColumn("after_", after).groupBy(*keys).agg(F.min(F.when(F.col("after_") <= tol, F.col(by))).alias("converged_at"))
