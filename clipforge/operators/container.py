"""Video-level filters on container metadata and payload, JVM expressions throughout."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from clipforge.functions.exprs import key_int


def aspect_ratio_ok(w: Column, h: Column, lo_tenths: int = 4, hi_tenths: int = 25) -> Column:
    """Width over height within bounds given in tenths; multiplied out, so it stays whole."""
    return (w * 10 >= h * lo_tenths) & (w * 10 <= h * hi_tenths)


def min_fps(fps: Column, least: int = 16) -> Column:
    return fps >= least


def min_sample_rate(rate: Column, least: int = 22050) -> Column:
    return rate >= least


def min_duration(frames: Column, fps: Column, seconds: int = 2) -> Column:
    return frames >= fps * seconds


def gate_checks() -> dict[str, Column]:
    """The gate's predicates by the reason that a failure is given."""
    c = F.col
    return {"aspect": aspect_ratio_ok(c("width"), c("height")), "fps": min_fps(c("fps")), "rate": min_sample_rate(c("sample_rate")),
            "duration": min_duration(c("frames"), c("fps")), "status": c("status") != "P"}


def metadata_gate(df: DataFrame) -> DataFrame:
    """Adds ``reasons``: the names of the checks that fail; null metadata fails its check."""
    return df.withColumn("reasons", F.array_compact(F.array(*[F.when(~F.coalesce(ok, F.lit(False)), F.lit(n)) for n, ok in gate_checks().items()])))


def sampled_frame_check(frames: DataFrame, flag: Column, k: int = 8, max_share: float = 0.25) -> DataFrame:
    """Per video: k frames in keyed order, how many are flagged, and whether the share is low enough."""
    order = W.partitionBy("media_id").orderBy(key_int(F.col("media_id"), "_", F.col("frame_no")), "frame_no")
    picked = frames.withColumn("pick", F.row_number().over(order)).filter(F.col("pick") <= k)
    out = picked.groupBy("media_id").agg(F.count("*").alias("sampled"), F.count_if(flag).alias("flagged"))
    return out.withColumn("keep", (F.col("flagged") <= F.col("sampled") * F.lit(max_share)).cast("int"))


def diagnose(payload: Column) -> Column:
    """One code for a payload: empty, truncated, unbalanced, encoding or ok."""
    balanced = F.regexp_count(payload, F.lit("<script")) == F.regexp_count(payload, F.lit("</script>"))
    return (F.when(payload.isNull() | (F.length(payload) == 0), "empty").when(payload.contains("�"), "encoding")
            .when(~payload.endswith("</html>"), "truncated").when(~balanced, "unbalanced").otherwise("ok"))


def video_level_report(gated: DataFrame) -> DataFrame:
    """Counts and passes by status and rate, with subtotals."""
    return gated.rollup("status", "sample_rate").agg(F.count("*").alias("n"), F.count_if(F.size("reasons") == 0).alias("passed"))
