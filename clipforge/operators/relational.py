"""Joins and aggregates that the methods need and Spark has no operator for."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from clipforge.functions.exprs import int_div


def asof_join(left: DataFrame, right: DataFrame, by: str, on: str, value: str) -> DataFrame:
    """Adds the last value of ``right`` at or before each row of ``left``: a union and one window, no range join."""
    l = left.withColumn("side_", F.lit(1)).withColumn(value, F.lit(None).cast(right.schema[value].dataType))
    r = right.select(by, on, value).withColumn("side_", F.lit(0))
    w = W.partitionBy(by).orderBy(on, "side_").rowsBetween(W.unboundedPreceding, 0)
    both = l.unionByName(r, allowMissingColumns=True)
    return both.withColumn(value, F.last(value, True).over(w)).filter("side_ = 1").drop("side_")


def range_join(points: DataFrame, ranges: DataFrame, point: str, lo: str, hi: str, width: int) -> DataFrame:
    """Points with the ranges [lo, hi] that hold them: ranges are expanded into cells of ``width``, so the join is on equality."""
    cells = ranges.withColumn("cell_", F.explode(F.sequence(int_div(F.col(lo), width), int_div(F.col(hi), width))))
    return points.withColumn("cell_", int_div(F.col(point), width)).join(cells, "cell_").filter(F.col(point).between(F.col(lo), F.col(hi))).drop("cell_")


def interval_join(a: DataFrame, b: DataFrame, key: str, width: int) -> DataFrame:
    """Overlapping intervals (a_lo, a_hi) and (b_lo, b_hi) of one key: both expanded to cells, each pair kept in the first cell they share."""
    expand = lambda df, p: df.withColumn("cell_", F.explode(F.sequence(int_div(F.col(f"{p}_lo"), width), int_div(F.col(f"{p}_hi"), width))))
    met = expand(a, "a").join(expand(b, "b"), [key, "cell_"]).filter("a_lo <= b_hi and b_lo <= a_hi")
    return met.filter(F.col("cell_") == int_div(F.greatest("a_lo", "b_lo"), width)).drop("cell_")


def salted_join(big: DataFrame, small: DataFrame, key: str, salts: int = 8) -> DataFrame:
    """An inner join whose hot keys are dealt over ``salts`` partitions: the small side is repeated.

    Both sides are shuffled and merged, for a broadcast would hold every repeat of
    the small side in the driver, whose size Spark guesses from before the repeats.
    """
    l = big.withColumn("salt_", F.pmod(F.xxhash64(*[F.col(c) for c in big.columns]), F.lit(salts)))
    r = small.withColumn("salt_", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(salts - 1).cast("bigint"))))
    return l.join(r.hint("merge"), [key, "salt_"]).drop("salt_")


def hash_sample(df: DataFrame, key: Column, permille: int) -> DataFrame:
    from clipforge.functions.exprs import key_int

    return df.filter(key_int(key) % 1000 < permille)
