"""Angle and noise expressions for DataFrames; all stay inside code generation."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

TAU = 2 * math.pi


def wrap(x: Column) -> Column:
    """Into (-pi, pi]."""
    return -(F.pmod(-x + F.lit(math.pi), F.lit(TAU)) - F.lit(math.pi))


def difference(a: Column, b: Column) -> Column:
    return wrap(a - b)


def circular_mean(x: Column) -> Column:
    return F.atan2(F.avg(F.sin(x)), F.avg(F.cos(x)))


def resultant(x: Column) -> Column:
    """Length of the mean unit vector: 1 for equal angles, 0 for balanced ones."""
    return F.hypot(F.avg(F.sin(x)), F.avg(F.cos(x)))


def uniform(*key: Column) -> Column:
    """A number in [0, 1) that any engine with md5 can repeat: its first 8 hex digits over 2^32."""
    digest = F.md5(F.concat_ws("|", *(k.cast("string") for k in key)))
    return F.conv(F.substring(digest, 1, 8), 16, 10).cast("double") / F.lit(2.0**32)


def normal(*key: Column) -> Column:
    """A standard normal from two uniforms of the key."""
    u = F.greatest(uniform(*key, F.lit("u")), F.lit(2.0**-33))
    return F.sqrt(-2 * F.ln(u)) * F.cos(F.lit(TAU) * uniform(*key, F.lit("v")))


def squared_distance(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double"))), F.lit(0.0), lambda s, x: s + x)
