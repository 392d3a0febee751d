"""Flow matching and diffusion targets, samplers and losses over vector columns; all expressions, no shuffle but the final averages."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from clipforge.functions.exprs import gauss, int_div, lerp, mean_square, uniform, vec_add_scaled, vec_sub


def interpolate(x0: Column, x1: Column, t: Column) -> Column:
    """On the straight line from noise (t = 0) to data (t = 1)."""
    return lerp(x0, x1, t)


def velocity(x0: Column, x1: Column) -> Column:
    return vec_sub(x1, x0)


def logit_normal_t(key: Column, mu: float = 0.0, sigma: float = 1.0) -> Column:
    """A keyed time in (0, 1): the sigmoid of a normal."""
    return F.round(F.lit(1.0) / (F.lit(1.0) + F.exp(-(F.lit(mu) + F.lit(sigma) * gauss(key, "_t")))), 6)


def uniform_t(key: Column) -> Column:
    return F.round(uniform(key, "_u"), 6)


def noise_vector(key: Column, dim: int) -> Column:
    """A keyed standard normal for each of ``dim`` entries."""
    return F.transform(F.sequence(F.lit(0), F.lit(dim - 1)), lambda j: gauss(key, "_", j))


def flow_loss(df: DataFrame, pred: Column, target: Column, by: list[Column] | None = None) -> DataFrame:
    """Mean squared velocity error, overall or by groups."""
    return df.withColumn("loss_", mean_square(vec_sub(pred, target))).groupBy(*(by or [])).agg(F.count("*").alias("n"), F.avg("loss_").alias("loss"))


def t_bin(t: Column, bins: int = 4) -> Column:
    return F.least(F.floor(t * bins), F.lit(bins - 1)).cast("bigint")


def euler(x0: Column, field, steps: int) -> Column:
    """Steps of the ordinary differential equation from t = 0 to 1, unrolled; ``field(x, t)`` gives the velocity."""
    x = x0
    for i in range(steps):
        x = vec_add_scaled(x, field(x, i / steps), 1.0 / steps)
    return x


def ddpm_alpha_bar(steps: int = 1000, first: float = 1e-4, last: float = 0.02) -> list[float]:
    """Products of what a linear schedule of variances leaves."""
    out, log = [], 0.0
    for i in range(steps):
        log += math.log(1 - (first + (last - first) * i / (steps - 1)))
        out.append(math.exp(log))
    return out


def ddpm_noise(x1: Column, eps: Column, alpha_bar: Column) -> Column:
    """The variance-preserving mixture of data and noise: the baseline to the straight line."""
    return F.zip_with(x1, eps, lambda x, e: F.sqrt(alpha_bar) * x.cast("double") + F.sqrt(F.lit(1.0) - alpha_bar) * e.cast("double"))


def guide(v_cond: Column, v_free: Column, scale: float) -> Column:
    """Conditional velocity pushed away from the unconditional; two evaluations per step."""
    return F.zip_with(v_cond, v_free, lambda c, u: c + F.lit(scale) * (c - u))


def cell_noise(cells: DataFrame) -> DataFrame:
    """Adds ``eps`` to coordinate rows (item, i)."""
    return cells.withColumn("eps", gauss(F.col("item"), "_", F.col("i")))


def tenth(c: Column) -> Column:
    return int_div(c, 10)
