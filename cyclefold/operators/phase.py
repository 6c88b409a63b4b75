"""Phases from modes: choice of the pair, angle, unwrapping, cycle count."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.angles import TAU, wrap


def zero_crossings(modes: DataFrame, by: list[str]) -> DataFrame:
    """(by), zc: sign changes along t of long modes (by, t, v); zeros take the sign before them."""
    ahead = Window.partitionBy(*by).orderBy("t")
    sign = F.last(F.when(F.col("v") != 0, F.signum("v")), ignorenulls=True).over(ahead)
    signed = modes.withColumn("s", sign)
    change = F.col("s") != F.lag("s").over(ahead)
    return signed.withColumn("c", change).groupBy(*by).agg(F.count_if("c").alias("zc"))


def mode_pair(counts: DataFrame, tol: float = 0.2, by: list[str] | None = None) -> DataFrame:
    """(by), lo, hi, fallback: neighbouring ranks whose counts agree within ``tol`` with the fewest crossings.

    counts: (by), rank, zero_cross. Ties go to the lower rank; if none agree, the first two.
    """
    by = by or []
    w = Window.partitionBy(*(by or [F.lit(0)])).orderBy("rank")
    pair = counts.select(*by, "rank", "zero_cross", F.lead("zero_cross").over(w).alias("z2")).filter("z2 IS NOT NULL")
    low, high = F.least("zero_cross", "z2"), F.greatest("zero_cross", "z2")
    good = (low >= 1) & (high <= (1 + tol) * low)
    best = pair.groupBy(*by).agg(F.min_by(F.when(good, F.col("rank")), F.when(good, F.struct((F.col("zero_cross") + F.col("z2")).alias("s"), "rank"))).alias("r"), F.min("rank").alias("first"))
    return best.select(*by, F.coalesce("r", "first").alias("lo"), (F.coalesce("r", "first") + 1).alias("hi"), F.isnull("r").alias("fallback"))


def from_modes(modes: DataFrame, pairs: DataFrame, by: str = "video_id") -> DataFrame:
    """video_id, i, phi from modes (video_id, rank, vec) and chosen pairs (video_id, lo, hi)."""
    chosen = modes.join(pairs, by).filter("rank = lo or rank = hi")
    two = chosen.groupBy(by).agg(F.max(F.when(F.col("rank") == F.col("lo"), F.col("vec"))).alias("a"), F.max(F.when(F.col("rank") == F.col("hi"), F.col("vec"))).alias("b"))
    return two.select(by, F.posexplode(F.arrays_zip("a", "b")).alias("i", "v")).select(by, "i", F.pmod(F.atan2("v.a", "v.b"), F.lit(TAU)).alias("phi"))


def unwrap(phase: DataFrame, by: str = "video_id") -> DataFrame:
    """video_id, i, phi, phi_u: oriented so that the median step is forward; unwrapped from zero.

    One exchange by video serves the step, the running sum and the direction.
    """
    order = Window.partitionBy(by).orderBy("i")
    step = wrap(F.col("phi") - F.lag("phi").over(order))
    stepped = phase.withColumn("step", step)
    back = F.coalesce(F.median("step").over(Window.partitionBy(by)) < 0, F.lit(False))
    turned = stepped.withColumn("back", back)
    sign = F.when(F.col("back"), -1.0).otherwise(1.0)
    so_far = order.rowsBetween(Window.unboundedPreceding, 0)
    return turned.select(
        by, "i", F.pmod(sign * F.col("phi"), F.lit(TAU)).alias("phi"), F.coalesce(F.sum(sign * F.col("step")).over(so_far), F.lit(0.0)).alias("phi_u")
    )


def cycle_count(phase: DataFrame, frames: int, d: int, how: str = "printed", by: str = "video_id") -> DataFrame:
    """video_id, k. printed: from the largest unwrapped phase; slope: from the regression on time."""
    if how == "printed":
        k = F.lit(frames) * F.max("phi_u") / F.lit(TAU * (frames - d + 1))
    elif how == "slope":
        k = F.regr_slope("phi_u", "i") * F.lit(frames) / F.lit(TAU)
    else:
        raise ValueError(f"unknown cycle count {how!r}")
    return phase.groupBy(by).agg(k.alias("k"))
