"""Recordings as points: tables to frames, pixels, tiles and regular series."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..schema import BadInput


def from_table(df: DataFrame, video: str | None, t: str, vec: str, shape: tuple[int, int, int]) -> DataFrame:
    """frames from a table of vectors; t becomes the rank inside the video.

    With ``video=None`` the table is one recording whose t is already dense; that plan is
    narrow. Otherwise ranks cost one exchange by video.
    """
    h, w, ch = shape
    out = df.select(
        (F.lit("0") if video is None else F.col(video).cast("string")).alias("video_id"), F.col(t).alias("_t"), F.col(vec).cast("array<float>").alias("px")
    )
    rank = F.col("_t") if video is None else F.row_number().over(Window.partitionBy("video_id").orderBy("_t")) - 1
    return out.select("video_id", rank.cast("int").alias("t"), F.lit(h).alias("h"), F.lit(w).alias("w"), F.lit(ch).alias("ch"), "px")


def check(frames: DataFrame) -> None:
    """Raises for frames of a wrong size or with missing steps; one aggregate, one row to the driver."""
    per = frames.groupBy("video_id").agg(
        F.count("*").alias("n"), F.count_distinct("t").alias("steps"), F.min("t").alias("lo"), F.max("t").alias("hi"), F.sum((F.size("px") != F.col("h") * F.col("w") * F.col("ch")).cast("int")).alias("bad")
    )
    wrong = per.filter("bad > 0 or lo <> 0 or hi <> n - 1 or steps <> n").agg(F.count("*"), F.min("video_id")).first()
    if wrong[0]:
        raise BadInput(f"{wrong[0]} videos have frames of a wrong size or missing or repeated steps, {wrong[1]} among them")


def pixels(frames: DataFrame) -> DataFrame:
    """video_id, t, y, x, ch, val: one row a value."""
    p = F.posexplode("px").alias("p", "val")
    long = frames.select("video_id", "t", "w", "ch", p)
    return long.select(
        "video_id", "t", F.floor(F.col("p") / (F.col("w") * F.col("ch"))).cast("int").alias("y"),
        F.pmod(F.floor(F.col("p") / F.col("ch")), F.col("w")).cast("int").alias("x"), F.pmod("p", "ch").cast("int").alias("c"), F.col("val").cast("double").alias("val"),
    ).withColumnRenamed("c", "ch")


def rebuild(long: DataFrame, w: int, ch: int = 1) -> DataFrame:
    """video_id, t, px: pixels back in order, one combining aggregate."""
    at = (F.col("y") * w + F.col("x")) * ch + F.col("ch")
    rows = F.array_sort(F.collect_list(F.struct(at.alias("p"), F.col("val").alias("val"))))
    return long.groupBy("video_id", "t").agg(F.transform(rows, lambda r: r["val"].cast("float")).alias("px"))


def tiles(frames: DataFrame, tile_px: int = 4096) -> DataFrame:
    """video_id, t, tile, px: slabs of the pixel axis, the unit of distribution for voting."""
    count = F.ceil(F.size("px") / tile_px).cast("int")
    slab = F.explode(F.transform(F.sequence(F.lit(0), count - 1), lambda k: F.struct(k.alias("tile"), F.slice("px", k * tile_px + 1, F.lit(tile_px)).alias("px"))))
    return frames.select("video_id", "t", slab.alias("s")).select("video_id", "t", "s.tile", "s.px")


def tile_keys(frames: DataFrame, tile_px: int = 4096) -> DataFrame:
    """video_id, tile of every slab, from the frames' shapes alone: no pixel is read."""
    size = frames.groupBy("video_id").agg(F.max(F.col("h") * F.col("w") * F.col("ch")).alias("size"))
    return size.select("video_id", F.explode(F.sequence(F.lit(0), F.ceil(F.col("size") / tile_px).cast("int") - 1)).alias("tile"))


def grayscale(frames: DataFrame) -> DataFrame:
    """Three channels to one by the luma weights; one channel stays."""
    third = lambda px, k: F.filter(px, lambda _, i: F.pmod(i, F.lit(3)) == k)
    mixed = F.zip_with(F.zip_with(third(F.col("px"), 0), third(F.col("px"), 1), lambda r, g: r * 0.299 + g * 0.587), third(F.col("px"), 2), lambda s, b: s + b * 0.114)
    return frames.withColumn("px", F.when(F.col("ch") == 3, mixed.cast(frames.schema["px"].dataType)).otherwise(F.col("px"))).withColumn("ch", F.lit(1))


def quantised(frames: DataFrame) -> DataFrame:
    """Clipped to [0, 1] and rounded to 0..255."""
    return frames.withColumn("px", F.transform("px", lambda v: F.round(F.greatest(F.least(v, F.lit(1.0)), F.lit(0.0)) * 255).cast("float")))


def regular_series(events: DataFrame, ts: str, value: str, start: str, hours: int, buckets: int) -> DataFrame:
    """t, n, v: the mean of a value in each bucket of ``hours``; empty buckets take the last mean before them.

    The aggregate combines before its shuffle; what is ordered afterwards are the buckets.
    """
    spark = events.sparkSession
    at = F.floor((F.unix_micros(F.col(ts).cast("timestamp")) - F.unix_micros(F.lit(start).cast("timestamp"))) / F.lit(hours * 3_600_000_000)).cast("int")
    means = events.groupBy(at.alias("t")).agg(F.count("*").alias("n"), F.avg(value).alias("m"))
    grid = spark.range(buckets).select(F.col("id").cast("int").alias("t"))
    joined = grid.join(means, "t", "left")
    back, ahead = Window.orderBy("t"), Window.orderBy(F.desc("t"))
    filled = F.coalesce(F.last("m", ignorenulls=True).over(back), F.last("m", ignorenulls=True).over(ahead))
    return joined.select("t", F.coalesce("n", F.lit(0)).alias("n"), filled.alias("v"))


def standardised(series: DataFrame, by: list[str] | None = None, v: str = "v") -> DataFrame:
    """Zero mean and unit (population) variance, whole or by group."""
    w = Window.partitionBy(*(by or [F.lit(0)]))
    return series.withColumn(v, (F.col(v) - F.avg(v).over(w)) / F.stddev_pop(v).over(w))
