"""Sliding windows, as arrays or implicitly through the distances of their frames."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def stack(series: DataFrame, d: int, v: str = "v", by: list[str] | None = None) -> DataFrame:
    """(by), i, w: d successive values from i on; windows that would run over the end are left out."""
    by = by or []
    ahead = Window.partitionBy(*(by or [F.lit(0)])).orderBy("t").rowsBetween(0, d - 1)
    return series.select(*by, F.col("t").alias("i"), F.collect_list(v).over(ahead).alias("w")).filter(F.size("w") == d)


def pair_distances(pairs: DataFrame, d: int) -> DataFrame:
    """video_id, i, j, d2 of windows: running sums of d entries along each diagonal j - i.

    Diagonals are the partitions, so the window needs one exchange and no frame is stacked.
    """
    along = Window.partitionBy("video_id", F.col("j") - F.col("i")).orderBy("i").rowsBetween(0, d - 1)
    out = pairs.select("video_id", "i", "j", F.sum("d2").over(along).alias("d2"), F.count("*").over(along).alias("c"))
    return out.filter(F.col("c") == d).drop("c")


def length(period: Column, cycles: Column) -> Column:
    """Frames of a window that spans whole cycles: d - 1 is a multiple of the period."""
    return (F.round(period * cycles) + 1).cast("int")


def check_dimension(d: Column, harmonics: Column) -> Column:
    """A loop with so many harmonics needs windows of at least twice as many frames."""
    return d >= 2 * harmonics
