"""Functions for SQL sessions, with the prefix cf_, and table functions for tiles and windows."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf

from clipforge.operators.fusion import window_starts
from clipforge.operators.latent import tile_starts

# Expressions as SQL functions: Catalyst inlines them, so they cost what the expression costs.
SQL_FUNCTIONS = {
    "cf_key_int": "(s string) returns bigint return cast(conv(substr(md5(s), 1, 8), 16, 10) as bigint)",
    "cf_uniform": "(s string) returns double return (cast(conv(substr(md5(s), 1, 8), 16, 10) as bigint) + 1) / 4294967298.0D",
    "cf_latent_frames": "(t bigint) returns bigint return 1 + (t - 1) div 4",
    "cf_latent_cells": "(t bigint, h bigint, w bigint) returns bigint return (1 + (t - 1) div 4) * (h div 8) * (w div 8)",
    "cf_image_share": "(step double, steps double) returns double return 0.3D - 0.2D * step / greatest(1.0D, steps - 1)",
    "cf_word_count": "(s string) returns bigint return cast(size(filter(split(s, '\\\\s+'), w -> w <> '')) as bigint)",
}


@udtf(returnType="start bigint, size bigint")
class FusionWindows:
    """Windows over a track: SELECT * FROM cf_fusion_windows(total, n, s)."""

    def eval(self, total: int, n: int, s: int):
        for a in window_starts(total, n, s):
            yield a, min(n, total)


@udtf(returnType="start bigint")
class TileCover:
    """Starts of tiles along one axis: SELECT * FROM cf_tile_cover(n, size, overlap)."""

    def eval(self, n: int, size: int, overlap: int):
        for a in tile_starts(n, size, overlap):
            yield (a,)


def scorer(fn, returns: str = "double"):
    """Any function of a pandas Series as a column function: how a learned scorer is plugged in."""
    return pandas_udf(fn, returns)


def register(spark: SparkSession) -> list[str]:
    """Makes all of them known to the session; gives their names."""
    for name, body in SQL_FUNCTIONS.items():
        spark.sql(f"create or replace temporary function {name}{body}")
    spark.udtf.register("cf_fusion_windows", FusionWindows)
    spark.udtf.register("cf_tile_cover", TileCover)
    return [*SQL_FUNCTIONS, "cf_fusion_windows", "cf_tile_cover"]
