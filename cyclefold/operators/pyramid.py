"""Gaussian pyramid: binomial blur and decimation by two."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: The 5-tap binomial kernel.
TAPS = (1 / 16, 4 / 16, 6 / 16, 4 / 16, 1 / 16)


def _reflect(k: np.ndarray, n: int) -> np.ndarray:
    """Indices mirrored at the edges without repeating them."""
    if n == 1:
        return np.zeros_like(k)
    k = np.abs(k) % (2 * (n - 1))
    return np.where(k >= n, 2 * (n - 1) - k, k)


def halve(image: np.ndarray) -> np.ndarray:
    """(..., h, w, ch) blurred along both axes and every second row and column kept."""
    for axis in (-3, -2):
        n = image.shape[axis]
        centre = np.arange(0, n, 2)
        image = sum(w * np.take(image, _reflect(centre + k - 2, n), axis=axis) for k, w in enumerate(TAPS))
    return image


def reduce(frames: DataFrame, level: int = 3) -> DataFrame:
    """Each frame's pyramid layer; layer 1 is the frame itself. Narrow, one Arrow pass."""
    if level <= 1:
        return frames

    def run(batches):
        for batch in batches:
            h, w, ch = (batch.column(c).to_pylist() for c in (2, 3, 4))
            px, heights, widths = [], [], []
            for k in range(batch.num_rows):
                image = np.asarray(batch.column(5)[k].values, np.float64).reshape(h[k], w[k], ch[k])
                for _ in range(level - 1):
                    image = halve(image)
                heights.append(image.shape[0])
                widths.append(image.shape[1])
                px.append(image.astype(np.float32).ravel())
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array(heights, pa.int32()), pa.array(widths, pa.int32()), batch.column(4), pa.array(px, pa.list_(pa.float32()))], names=batch.schema.names
            )

    return frames.select("video_id", "t", "h", "w", "ch", "px").mapInArrow(run, "video_id string, t int, h int, w int, ch int, px array<float>")


def reduce_relational(pixels: DataFrame, h: int, w: int) -> DataFrame:
    """One halving on long pixels: each source pixel is sent to the kept pixels it weighs in, and summed."""

    spark = pixels.sparkSession
    grids = []
    for axis, n in (("y", h), ("x", w)):
        rows = [(k, min(abs(2 * k + tap - 2), 2 * (n - 1) - abs(2 * k + tap - 2)), TAPS[tap]) for k in range((n + 1) // 2) for tap in range(5)]
        grids.append(spark.createDataFrame(rows, f"to_{axis} int, {axis} int, w{axis} double"))
    return (
        pixels.join(F.broadcast(grids[0]), "y")
        .join(F.broadcast(grids[1]), "x")
        .groupBy("video_id", "t", F.col("to_y").alias("y"), F.col("to_x").alias("x"), "ch")
        .agg(F.sum(F.col("val") * F.col("wy") * F.col("wx")).alias("val"))
    )
