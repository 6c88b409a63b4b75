"""Votes of overlapping windows for the frames of one cycle, and their median."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import kernels
from ..functions.angles import TAU

#: Votes of one video up to this many rows travel with its tiles; beyond, tiles meet votes by a join.
VOTE_LIMIT = 2_000_000


def theta_grid(spark: SparkSession, m: int) -> DataFrame:
    """j, theta: m equally spaced angles."""
    return spark.range(m).select(F.col("id").cast("int").alias("j"), (F.lit(TAU) * F.col("id") / m).alias("theta"))


def coverage(phase: DataFrame, k: float, frames: int, d: int) -> DataFrame:
    """video_id, i, lo, hi, wraps: the arc of angles that each window spans."""
    span = TAU * k * d / frames
    end = F.col("phi") + F.lit(span)
    return phase.select("video_id", "i", F.col("phi").alias("lo"), F.pmod(end, F.lit(TAU)).alias("hi"), (end >= TAU).alias("wraps"))


def assign(phase: DataFrame, m: int, k: float, frames: int, d: int, near: float | None = None, anchor: str = "start") -> DataFrame:
    """video_id, j, i, a, b, frac, offset: every window that covers an angle votes for it once a cycle.

    The m angles are an array column, so that a window's votes are made where it is; with
    ``near`` the far ones never leave the row.
    """
    if k <= 0:
        raise ValueError("the recording has no cycle to vote on")
    turn = frames / k
    offsets = F.transform(
        F.sequence(F.lit(0), F.lit(m - 1)),
        lambda j: F.struct(j.alias("j"), (F.pmod(F.lit(TAU) * j / m - F.col("phi"), F.lit(TAU)) * F.lit(turn / TAU)).alias("s")),
    )
    rows = phase.select("video_id", "i", F.explode(offsets).alias("o")).select("video_id", "i", "o.j", "o.s")
    laps = int((d - 1) // turn) + 1
    rows = rows.select("video_id", "i", "j", F.explode(F.array(*(F.col("s") + F.lit(c * turn) for c in range(laps)))).alias("offset")).filter(F.col("offset") <= d - 1)
    if near is not None:
        centre = 0.0 if anchor == "start" else (d - 1) / 2
        rows = rows.filter(F.abs(F.col("offset") - F.lit(centre)) <= near)
    whole = F.floor("offset").cast("int")
    return rows.select(
        "video_id", "j", "i", (F.col("i") + whole).alias("a"), F.least(F.col("i") + whole + 1, F.col("i") + F.lit(d - 1)).cast("int").alias("b"), (F.col("offset") - whole).alias("frac"), "offset"
    )


def stats(votes: DataFrame) -> DataFrame:
    """video_id, j, votes, frames: votes and distinct first frames for each angle."""
    return votes.groupBy("video_id", "j").agg(F.count("*").alias("votes"), F.count_distinct("a").alias("frames"))


def median_template(votes: DataFrame, tiles: DataFrame, m: int, median: str = "exact", lo: float = -1.0, hi: float = 1.0) -> DataFrame:
    """video_id, j, theta, tile, px, n_votes: per-pixel medians of the interpolated raw frames.

    Votes (small) and tiles are grouped together by video and tile: pixels move once and are
    never multiplied by the votes. Angles without a vote give null pixels and n_votes = 0.
    ``median``: exact; hist counts in 256 bins between lo and hi.
    """
    keys = tiles.select("video_id", "tile").distinct()
    spread = keys.join(votes.groupBy("video_id").agg(F.collect_list(F.struct("j", "a", "b", "frac")).alias("v")), "video_id").select(F.col("video_id").alias("of_video"), F.col("tile").alias("of_tile"), "v")

    def run(key, tile: pd.DataFrame, vote: pd.DataFrame) -> pd.DataFrame:
        tile = tile.sort_values("t")
        px = np.stack(tile["px"].to_numpy()).astype(np.float64)
        rows = vote["v"].iloc[0] if len(vote) else []
        j, a, b, frac = (np.array([r[c] for r in rows], np.float64 if c == "frac" else np.int64) for c in ("j", "a", "b", "frac"))
        ballots = (j, None, a, b, frac, None)
        if median == "hist":
            out, n = histogram_median(px, ballots, m, lo, hi)
        else:
            out, n = kernels.median_template(px, ballots, m)
        return pd.DataFrame(
            {
                "video_id": key[0], "j": np.arange(m, dtype="int32"), "theta": 2 * np.pi * np.arange(m) / m, "tile": np.int32(key[1]),
                "px": [row.astype(np.float32) if c else None for row, c in zip(out, n, strict=True)], "n_votes": n.astype("int64"),
            }
        )

    schema = "video_id string, j int, theta double, tile int, px array<float>, n_votes long"
    return tiles.groupBy("video_id", "tile").cogroup(spread.groupBy("of_video", "of_tile")).applyInPandas(run, schema)


def histogram_median(pixels: np.ndarray, vote: tuple, m: int, lo: float, hi: float, bins: int = 256) -> tuple[np.ndarray, np.ndarray]:
    """Medians from counts per bin: counts of parts add up, so it merges; right within half a bin."""
    j, _, a, b, frac, _ = vote
    counts = np.zeros((m, pixels.shape[1], bins), np.int32)
    columns = np.arange(pixels.shape[1])
    for k in range(len(j)):
        value = (1 - frac[k]) * pixels[a[k]] + frac[k] * pixels[b[k]]
        cell = np.clip(((value - lo) / (hi - lo) * bins).astype(np.int64), 0, bins - 1)
        counts[j[k], columns, cell] += 1
    n = np.bincount(j, minlength=m) if len(j) else np.zeros(m, np.int64)
    below = np.cumsum(counts, axis=2)
    low, high = ((np.argmax(below >= t[:, None, None], axis=2) + 0.5) * (hi - lo) / bins + lo for t in (np.maximum((n + 1) // 2, 1), np.maximum(n // 2 + 1, 1)))
    out = (low + high) / 2
    out[n == 0] = np.nan
    return out, n


def median_relational(votes: DataFrame, pixels: DataFrame) -> DataFrame:
    """video_id, j, y, x, ch, val, n_votes as two joins and a median: the plain form, for checks at small sizes."""
    at = lambda c, v: pixels.select("video_id", F.col("t").alias(c), "y", "x", "ch", F.col("val").alias(v))
    blend = votes.join(at("a", "va"), ["video_id", "a"]).join(at("b", "vb"), ["video_id", "b", "y", "x", "ch"])
    value = (1 - F.col("frac")) * F.col("va") + F.col("frac") * F.col("vb")
    return blend.groupBy("video_id", "j", "y", "x", "ch").agg(F.median(value).alias("val"), F.count("*").alias("n_votes"))
