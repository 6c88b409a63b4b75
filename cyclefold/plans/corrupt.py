"""Corruptions of planted videos, all repeatable from a text key."""

from __future__ import annotations

import zlib

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.angles import uniform

KINDS = ("none", "shake", "noise", "occlude", "jitter", "drop")


def generator(key: str) -> np.random.Generator:
    return np.random.default_rng(zlib.crc32(key.encode()))


def shake(px: np.ndarray, h: int, w: int, width: float, key: str) -> np.ndarray:
    """Each frame blurred along a random walk inside a width x width kernel, in pixels and parts of them."""
    if width <= 0:
        return px
    walk = np.cumsum(generator(key + "|shake").uniform(-width / 4, width / 4, (len(px), 32, 2)), axis=1)
    walk = np.abs((walk + width / 2) % (2 * width) - width) - width / 2  # reflected at the kernel's borders
    y, x = (np.exp(-2j * np.pi * walk[:, :, k, None] * f) for k, f in ((0, np.fft.fftfreq(h)), (1, np.fft.rfftfreq(w))))
    blur = (y.transpose(0, 2, 1) @ x / walk.shape[1])[..., None]
    f = np.fft.rfft2(px.reshape(len(px), h, w, -1), axes=(1, 2))
    return np.fft.irfft2(f * blur, (h, w), axes=(1, 2)).reshape(px.shape)


def noise(px: np.ndarray, std: float, key: str) -> np.ndarray:
    return px + generator(key + "|noise").normal(0, std, px.shape)


def occlude(px: np.ndarray, h: int, w: int, side: float, key: str) -> np.ndarray:
    """A square of ``side`` (share of the height) on a reflected random walk, each colour channel drifting slowly."""
    s = max(1, int(round(side * h)))
    draw = generator(key + "|occlude")
    out = px.reshape(len(px), h, w, -1).copy()
    lo, hi = px.min(), px.max()
    y, x, colour = draw.uniform(0, h - s), draw.uniform(0, w - s), draw.uniform(0, 1, out.shape[3])
    for t in range(len(out)):
        y, x = (abs(v + draw.normal(0, 1)) for v in (y, x))
        y, x = (v if v <= most else max(0.0, 2 * most - v) for v, most in ((y, h - s), (x, w - s)))
        colour = np.abs(colour + draw.normal(0, 0.02, len(colour)))
        colour = np.where(colour <= 1, colour, 2 - colour)
        out[t, int(y) : int(y) + s, int(x) : int(x) + s] = lo + colour * (hi - lo)
    return out.reshape(px.shape)


def drop(px: np.ndarray, rate: float, key: str) -> np.ndarray:
    """Frames lost and refilled linearly in time between their neighbours."""
    lost = generator(key + "|drop").uniform(0, 1, len(px)) < rate
    lost[[0, -1]] = False
    have, t = np.flatnonzero(~lost), np.arange(len(px))
    right = np.searchsorted(have, t).clip(1, len(have) - 1)
    a, b = have[right - 1], have[right]
    f = ((t - a) / (b - a))[:, None]
    return np.where(lost[:, None], (1 - f) * px[a] + f * px[b], px)


def apply(px: np.ndarray, h: int, w: int, kind: str, level: float, key: str) -> np.ndarray:
    """Levels: shake in pixels, noise as standard deviation, occlude as a share of the height,
    drop as a share of frames; none leaves the video."""
    if kind == "none":
        return px
    if kind == "shake":
        return shake(px, h, w, level, key)
    if kind == "noise":
        return noise(px, level, key)
    if kind == "occlude":
        return occlude(px, h, w, level, key)
    if kind == "drop":
        return drop(px, level, key)
    raise ValueError(f"unknown corruption {kind!r}")


# --- relational forms, with hashed noise that any engine repeats -------------------------------


def _folded(v, most: float):
    """A walk folded back at 0 and ``most``."""
    return F.abs(v - F.lit(2 * most) * F.floor(v / F.lit(2 * most) + 0.5))


def occluder_path(steps: DataFrame, most: float, seed: int = 42, by: list[str] | None = None) -> DataFrame:
    """(by), t, y, x, colour: a reflected walk of the occluding square, one ordered running sum a recording."""
    by = by or []
    ahead = Window.partitionBy(*by).orderBy("t").rowsBetween(Window.unboundedPreceding, 0)
    move = lambda k, size: F.sum((uniform(F.lit(seed), F.col("t"), F.lit(k)) - 0.5) * size).over(ahead)
    return steps.select(*by, "t", _folded(move("y", 4) + 3, most).alias("y"), _folded(move("x", 4) + 3, most).alias("x"), _folded(move("c", 0.1) + 0.5, 1.0).alias("colour"))


def shake_kernel(steps: DataFrame, side: int, seed: int = 42) -> DataFrame:
    """t, y, x, weight: each frame's blur kernel, the visits of a short walk kept inside side x side."""
    k = F.explode(F.sequence(F.lit(0), F.lit(2 * side - 1))).alias("k")
    rows = steps.select("t", k)
    step = lambda c: F.floor(uniform(F.lit(seed), F.col("t"), F.col("k"), F.lit(c)) * 3) - 1
    ahead = Window.partitionBy("t").orderBy("k").rowsBetween(Window.unboundedPreceding, 0)
    half = F.lit(side // 2)
    at = lambda c: F.least(F.greatest(F.sum(step(c)).over(ahead), -half), half)
    walked = rows.select("t", at("y").alias("y"), at("x").alias("x"))
    return walked.groupBy("t", "y", "x").agg((F.count("*") / F.lit(2.0 * side)).alias("weight"))
