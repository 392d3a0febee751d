"""Column expressions shared by the operators: keyed randomness, vectors, exact rounding."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def key_int(*parts: Column | str) -> Column:
    """A whole number below 2**32 from the first eight hex digits of an md5: the only source of randomness, so retries agree."""
    text = F.concat(*[F.lit(p) if isinstance(p, str) else p.cast("string") for p in parts])
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("bigint")


def uniform(*parts: Column | str) -> Column:
    """Inside (0, 1): never 0 or 1."""
    return (key_int(*parts) + 1).cast("double") / F.lit(float(2**32 + 2))


def gauss(*parts: Column | str) -> Column:
    """A standard normal from two keyed uniforms, to six digits."""
    return rnd(F.sqrt(F.lit(-2.0) * F.ln(uniform(*parts, "a"))) * F.cos(F.lit(2 * math.pi) * uniform(*parts, "b")))


def rnd(c: Column, digits: int = 6) -> Column:
    """Rounded, and without a negative zero."""
    return F.round(c, digits) + F.lit(0.0)


def floor_int(c: Column) -> Column:
    return F.floor(c).cast("bigint")


def int_div(a: Column, b: Column | int) -> Column:
    """Whole division of non-negative whole numbers."""
    b = F.lit(b) if isinstance(b, int) else b
    return F.floor(a / b).cast("bigint")


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column, b: Column) -> Column:
    """Null for a zero vector."""
    n = norm(a) * norm(b)
    return F.when(n > 0, dot(a, b) / n)


def lerp(a: Column, b: Column, t: Column) -> Column:
    """Element by element (1 - t) a + t b."""
    return F.zip_with(a, b, lambda x, y: (1 - t) * x.cast("double") + t * y.cast("double"))


def vec_sub(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x.cast("double") - y.cast("double"))


def vec_add_scaled(a: Column, b: Column, scale: Column | float) -> Column:
    s = F.lit(scale) if isinstance(scale, (int, float)) else scale
    return F.zip_with(a, b, lambda x, y: x.cast("double") + s * y.cast("double"))


def vec_sum(a: Column) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda s, x: s + x.cast("double"))


def mean_square(a: Column) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double")) / F.size(a)
