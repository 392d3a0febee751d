"""Accuracy measures over matched values: rows (item, frame, a, b)."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from clipforge.functions.exprs import int_div

CAP = 100.0


def psnr(df: DataFrame, peak: float, per: tuple[str, ...] = ("item", "frame"), by: tuple[str, ...] = ()) -> DataFrame:
    """Mean over frames of the log ratio of squared peak to mean squared error; equal frames count ``CAP``."""
    e = df.groupBy(*by, *per).agg(F.avg((F.col("a") - F.col("b")) * (F.col("a") - F.col("b"))).alias("mse"))
    one = F.when(F.col("mse") > 0, F.least(F.lit(CAP), 10 * F.log10(F.lit(peak * peak) / F.col("mse")))).otherwise(CAP)
    return e.groupBy(*by).agg(F.avg(one).alias("psnr"))


def ssim(df: DataFrame, peak: float, per: tuple[str, ...] = ("item", "frame"), by: tuple[str, ...] = ()) -> DataFrame:
    """Mean over frames (or windows: any keys in ``per``) of luminance, contrast and structure with the published constants."""
    c1, c2 = (0.01 * peak) ** 2, (0.03 * peak) ** 2
    m = df.groupBy(*by, *per).agg(F.avg("a").alias("ma"), F.avg("b").alias("mb"), F.var_pop("a").alias("va"), F.var_pop("b").alias("vb"), F.covar_pop("a", "b").alias("cov"))
    one = (2 * F.col("ma") * F.col("mb") + c1) * (2 * F.col("cov") + c2) / ((F.col("ma") * F.col("ma") + F.col("mb") * F.col("mb") + c1) * (F.col("va") + F.col("vb") + c2))
    return m.groupBy(*by).agg(F.avg(one).alias("ssim"))


def frechet_diag(df: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Distance of Gaussians with independent features: rows (sample, feature, a, b)."""
    m = df.groupBy(*by, "feature").agg(F.avg("a").alias("ma"), F.avg("b").alias("mb"), F.var_pop("a").alias("va"), F.var_pop("b").alias("vb"))
    one = (F.col("ma") - F.col("mb")) * (F.col("ma") - F.col("mb")) + F.col("va") + F.col("vb") - 2 * F.sqrt(F.col("va") * F.col("vb"))
    return m.groupBy(*by).agg(F.sum(one).alias("frechet"))


def moments(df: DataFrame, vec: str, dim: int) -> tuple[np.ndarray, np.ndarray]:
    """Mean and covariance of vectors of ``dim`` (at most 64): one row of dim + 1 sums for each feature comes to the driver."""
    if dim > 64:
        raise ValueError("full covariance is for at most 64 features")
    v = F.slice(vec, 1, dim).cast("array<double>")
    terms = df.select(v.alias("v"), F.posexplode(v).alias("i", "x"))
    rows = terms.groupBy("i").agg(F.avg("x").alias("m"), *[F.avg(F.col("x") * F.col("v")[j]).alias(f"p{j}") for j in range(dim)]).collect()
    rows = sorted(rows, key=lambda r: r["i"])
    mean = np.array([r["m"] for r in rows])
    cov = np.array([[r[f"p{j}"] for j in range(dim)] for r in rows]) - np.outer(mean, mean)
    return mean, cov


def frechet(a: DataFrame, b: DataFrame, vec: str, dim: int) -> float:
    """With full covariances: the trace of the root of their product by eigenvalues."""
    (ma, ca), (mb, cb) = moments(a, vec, dim), moments(b, vec, dim)
    w, q = np.linalg.eigh(ca)
    root = q @ np.diag(np.sqrt(np.maximum(w, 0))) @ q.T
    cross = np.sqrt(np.maximum(np.linalg.eigvalsh(root @ cb @ root), 0)).sum()
    return float(((ma - mb) ** 2).sum() + np.trace(ca) + np.trace(cb) - 2 * cross)


def resize_area(cells: DataFrame, grid: int, to: int) -> DataFrame:
    """Mean of the cells that fall into each target cell."""
    return cells.groupBy("item", int_div(F.col("y") * to, grid).alias("y"), int_div(F.col("x") * to, grid).alias("x")).agg(F.avg("val").alias("val"))


def flicker(df: DataFrame, order: str = "i", by: tuple[str, ...] = ()) -> DataFrame:
    """Mean absolute step of b less that of a."""
    w = W.partitionBy(*by, "item").orderBy(order)
    rows = df.withColumns({"sa": F.abs(F.col("a") - F.lag("a").over(w)), "sb": F.abs(F.col("b") - F.lag("b").over(w))})
    return rows.groupBy(*by).agg((F.avg("sb") - F.avg("sa")).alias("flicker"))


def resize_pairs(pixels: DataFrame, to_cell: int = 2) -> DataFrame:
    """Both versions of every picture reduced to the mean of ``to_cell`` x ``to_cell`` pixels: rows (arm, item, i, y, x, a, b)."""
    at = [int_div(F.col(k), to_cell).alias(k) for k in ("y", "x")]
    return pixels.groupBy("arm", "item", "i", *at).agg(F.avg("a").alias("a"), F.avg("b").alias("b"))


def compare(pixels: DataFrame, peak: float, feature: Column) -> DataFrame:
    """One row for each arm: the three scores of rows (arm, item, i, a, b), from two sets of moments over rows that should be written once."""
    by = ("arm",)
    rows = pixels.withColumn("feature", feature)
    return psnr(rows, peak, ("item", "i"), by).join(ssim(rows, peak, ("item", "i"), by), "arm").join(frechet_diag(rows, by=by), "arm")


def best_of(scores: DataFrame, score: str, high: bool = True) -> Column:
    edge = (F.max if high else F.min)(score).over(W.partitionBy())
    return (F.col(score) == edge).cast("int")
