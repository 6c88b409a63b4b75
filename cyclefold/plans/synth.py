"""Planted recordings with a known phase, built from rows of a table of vectors."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Amplitudes of the harmonics in the three scenes: one dominant; the second the stronger; many.
SCENES = {1: (1.0, 0.15), 2: (0.6, 1.2), 3: (1.0, 0.5, 0.4, 0.3)}
#: Vectors of one channel: the mean and two for each of four harmonics.
BASIS = 9
GRID = "video_id string, scene int, cycles double, corruption string, level double, trial int"


def upsample(rows: np.ndarray, h: int, w: int) -> np.ndarray:
    """Vectors of a square side tiled up to h x w by nearest neighbour."""
    side = int(round(np.sqrt(rows.shape[1])))
    y, x = np.arange(h) * side // h, np.arange(w) * side // w
    return rows.reshape(len(rows), side, side)[:, y[:, None], x[None]].reshape(len(rows), h * w)


def frames_of(basis: np.ndarray, scene: int, cycles: float, n: int, h: int, w: int, jitter: float = 0.0, seed: int = 0, ch: int = 1, drift: float = 0.0) -> np.ndarray:
    """(n, h*w*ch) frames of one planted video; each channel has ``BASIS`` vectors of its own.

    ``jitter`` varies amplitude from cycle to cycle; ``drift`` is how far the brightness wanders over the video.
    """
    angle = 2 * np.pi * cycles * np.arange(n) / n
    gain = np.ones(n)
    if jitter:
        draw = np.random.default_rng(seed)
        gain = 1 + jitter * draw.uniform(-1, 1, int(np.ceil(cycles)) + 1)[np.floor(angle / (2 * np.pi)).astype(int)]
    channels = []
    for c in range(ch):
        rows = upsample(basis[c * BASIS : (c + 1) * BASIS], h, w)
        out = np.repeat(rows[:1], n, axis=0)
        for k, a in enumerate(SCENES[scene], 1):
            out = out + (gain * a)[:, None] * (np.cos(k * angle)[:, None] * rows[2 * k - 1] + np.sin(k * angle)[:, None] * rows[2 * k])
        if scene == 3:
            out = out + (1 - 0.3 * c) * _sprites(angle, h, w)
        channels.append(out + drift * np.linspace(-0.5, 0.5, n)[:, None] * rows[:1])
    return np.stack(channels, axis=2).reshape(n, h * w * ch)


def _sprites(angle: np.ndarray, h: int, w: int) -> np.ndarray:
    """Discs on closed orbits, one turn a cycle, at different radii and places."""
    y, x = np.mgrid[:h, :w]
    out = np.zeros((len(angle), h * w))
    for k in range(6):
        cy, cx = h * (0.25 + 0.1 * k), w * (0.8 - 0.1 * k)
        r = 0.12 * min(h, w) * (1 + k % 3)
        py, px = cy + r * np.sin(angle + k), cx + r * np.cos(angle + k)
        d2 = (y[None] - py[:, None, None]) ** 2 + (x[None] - px[:, None, None]) ** 2
        out += 0.3 * np.exp(-d2 / (0.02 * h * w)).reshape(len(angle), -1)
    return out


def basis_rows(embeddings: DataFrame, n: int = 3 * BASIS) -> np.ndarray:
    """The first vectors by id, the fixed pixel basis of all scenes (a parameter, not data)."""
    rows = embeddings.orderBy("vec_id").limit(n).select("embedding").collect()
    return np.array([r.embedding for r in rows], np.float64)


def planted(spark: SparkSession, embeddings: DataFrame, grid: DataFrame, n: int = 600, h: int = 32, w: int = 32, ch: int = 1) -> DataFrame:
    """frames of every row of ``grid`` (layout GRID), corrupted as the row says.

    One narrow grouped map: a row of the grid becomes its video where it is.
    """
    from .corrupt import apply

    basis = basis_rows(embeddings)

    def run(batches):
        for pdf in batches:
            for row in pdf.itertuples():
                px = frames_of(basis, row.scene, row.cycles, n, h, w, ch=ch)
                px = apply(px, h, w, row.corruption, row.level, f"{row.video_id}|{row.trial}")
                yield pd.DataFrame({"video_id": row.video_id, "t": np.arange(n, dtype="int32"), "h": h, "w": w, "ch": ch, "px": list(px.astype(np.float32))})

    schema = "video_id string, t int, h int, w int, ch int, px array<float>"
    return grid.mapInPandas(run, schema)


def truth(grid: DataFrame, n: int = 600) -> DataFrame:
    """video_id, t, phi in closed form."""
    t = F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("t")
    return grid.select("video_id", "cycles", t).select("video_id", "t", F.pmod(2 * F.lit(np.pi) * F.col("cycles") * F.col("t") / n, 2 * F.lit(np.pi)).alias("phi"))


def season(series: DataFrame, period: float, amplitudes: tuple[float, ...]) -> DataFrame:
    """series (t, v) plus a season of the given harmonics, with the phase as phi."""
    angle = 2 * F.lit(np.pi) * F.col("t") / F.lit(float(period))
    wave = sum((F.lit(float(a)) * F.sin((k + 1) * angle) for k, a in enumerate(amplitudes)), F.lit(0.0))
    return series.withColumn("phi", 2 * F.lit(np.pi) * (F.pmod("t", F.lit(float(period))) / F.lit(float(period)))).withColumn("v", F.col("v") + wave)
