"""What the fold is compared with: plain reordering, known periods, filters, loops, jumps, orders."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import kernels
from . import gram


def sort_by_phase(phase: DataFrame) -> DataFrame:
    """video_id, pos, t: frames in order of phase, without any vote; one sort a video."""
    pos = F.row_number().over(Window.partitionBy("video_id").orderBy("phi", "i")) - 1
    return phase.select("video_id", pos.cast("int").alias("pos"), F.col("i").alias("t"))


def fold_known_period(series: DataFrame, period: float, bins: int) -> DataFrame:
    """bin, mean, med, n: values at equal phases of a period that is known."""
    b = F.floor(F.pmod("t", F.lit(float(period))) / F.lit(period / bins)).cast("int")
    return series.groupBy(b.alias("bin")).agg(F.avg("v").alias("mean"), F.median("v").alias("med"), F.count("*").alias("n"))


def power(series: DataFrame, n: int, frequencies: list[int]) -> DataFrame:
    """bin, power: squared length of chosen Fourier sums over n steps, by sums of cosines and sines."""
    f = F.explode(F.array(*(F.lit(x) for x in frequencies))).alias("bin")
    angle = F.lit(2 * np.pi) * F.col("bin") * F.col("t") / n
    sums = series.select("t", "v", f).groupBy("bin").agg(F.sum(F.col("v") * F.cos(angle)).alias("c"), F.sum(F.col("v") * F.sin(angle)).alias("s"))
    return sums.select("bin", ((F.col("c") * F.col("c") + F.col("s") * F.col("s")) / (n * n)).alias("power"))


def bandpass(tiles: DataFrame, low: float, high: float, gain: float = 1.0) -> DataFrame:
    """Tiles with the band [low, high] (cycles a frame) of every pixel over time amplified by ``gain``."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("t")
        x = np.stack(pdf["px"].to_numpy()).astype(np.float64)
        f = np.fft.rfftfreq(len(x))
        spectrum = np.fft.rfft(x, axis=0)
        spectrum[(f < low) | (f > high)] = 0
        y = x + gain * np.fft.irfft(spectrum, len(x), axis=0)
        return pdf.assign(px=list(y.astype(np.float32)))

    return tiles.groupBy("video_id", "tile").applyInPandas(run, tiles.schema)


def best_loop(pairs: DataFrame, tmin: int, tmax: int) -> DataFrame:
    """video_id, start, len, d2: the seam of least distance among loops of tmin..tmax frames."""
    length = F.col("j") - F.col("i")
    within = pairs.filter((length >= tmin) & (length <= tmax))
    best = within.groupBy("video_id").agg(F.min(F.struct("d2", F.col("i").alias("start"), length.alias("len"))).alias("b"))
    return best.select("video_id", "b.start", "b.len", "b.d2")


#: Frames of one recording that start a loop in one task.
LOOP_STARTS = 1024


def best_loop_of_frames(frames: DataFrame, tmin: int, tmax: int) -> DataFrame:
    """``best_loop`` without the table of pairs: the frames of a block of starts meet only those up to ``tmax`` behind."""
    first = F.greatest(F.floor((F.col("t") - tmax) / LOOP_STARTS), F.lit(0))
    rows = frames.select("video_id", "t", "px", F.explode(F.sequence(first, F.floor(F.col("t") / LOOP_STARTS))).alias("block"))

    def best(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("t")
        t, px = pdf["t"].to_numpy(), np.stack(pdf["px"].to_numpy()).astype(float)
        starts = np.flatnonzero(t // LOOP_STARTS == pdf["block"].iloc[0])
        found = []
        for length in range(tmin, tmax + 1):
            end = np.minimum(np.searchsorted(t, t[starts] + length), len(t) - 1)
            a, b = (x[t[end] == t[starts] + length] for x in (starts, end))
            if len(a):
                d2 = ((px[a] - px[b]) ** 2).sum(axis=1)
                k = int(np.argmin(d2))
                found.append((pdf["video_id"].iloc[0], int(t[a[k]]), length, float(d2[k])))
        return pd.DataFrame(sorted(found, key=lambda r: (r[3], r[1], r[2]))[:1], columns=["video_id", "start", "len", "d2"])

    each = rows.groupBy("video_id", "block").applyInPandas(best, "video_id string, start int, len int, d2 double")
    return each.groupBy("video_id").agg(F.min(F.struct("d2", "start", "len")).alias("b")).select("video_id", "b.start", "b.len", "b.d2")


def jump_table(pairs: DataFrame, temperature: float) -> DataFrame:
    """video_id, i, j, p: chances to go on from frame i with frame j, by how like j is to i's successor."""
    both = pairs.select("video_id", "i", "j", "d2").union(pairs.select("video_id", F.col("j").alias("i"), F.col("i").alias("j"), "d2"))
    weight = F.exp(-F.sqrt("d2") / F.lit(temperature))
    jumps = both.filter("i > 0").select("video_id", (F.col("i") - 1).alias("i"), "j", weight.alias("w"))
    total = F.sum("w").over(Window.partitionBy("video_id", "i"))
    return jumps.select("video_id", "i", "j", (F.col("w") / total).alias("p"))


def jump_table_of_frames(frames: DataFrame, temperature: float) -> DataFrame:
    """``jump_table`` from frames: the sums of a row come from a first pass over blocks of frames, so no row is regrouped."""

    def finish(i, j, d2, s_i, s_j):
        w = np.exp(-np.sqrt(d2) / temperature)
        if i[0] == j[0]:
            a, b = np.nonzero(i[:, None] != j[None])
            return {"i": i[a], "j": j[b], "w": w[a, b], "s": s_i[a]}
        a, b = np.repeat(np.arange(len(i)), len(j)), np.tile(np.arange(len(j)), len(i))
        return {"i": np.concatenate([i[a], j[b]]), "j": np.concatenate([j[b], i[a]]), "w": np.tile(w.ravel(), 2), "s": np.concatenate([s_i[a], s_j[b]])}

    total = gram.row_sums(frames, lambda d2: np.exp(-np.sqrt(d2) / temperature))
    beside = total.select("video_id", F.col("i").alias("t"), F.col("s").alias("side"))
    rows = gram.in_blocks(frames, finish, "i int, j int, w double, s double", beside=beside).filter("i > 0")
    return rows.select("video_id", (F.col("i") - 1).alias("i"), "j", (F.col("w") / F.col("s")).alias("p"))


def spectral_order(matrices: DataFrame, topology: str = "loop", sigma: float | None = None) -> DataFrame:
    """video_id, pos, i: frames without time ordered along a line (first mode) or a loop (first two)."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        n = int(pdf["n"].iloc[0])
        dist = np.sqrt(np.asarray(pdf["d2"].iloc[0]).reshape(n, n))
        s = sigma or float(np.median(np.sort(dist, axis=1)[:, min(8, n - 1)]))
        _, vectors, _ = kernels.low_modes(kernels.laplacian(kernels.adjacency(dist, s)), 2)
        key = vectors[:, 0] if topology == "line" else np.arctan2(vectors[:, 0], vectors[:, 1])
        order = np.lexsort((np.arange(n), key))
        return pd.DataFrame({"video_id": pdf["video_id"].iloc[0], "pos": np.arange(n, dtype="int32"), "i": order.astype("int32")})

    if topology not in ("line", "loop"):
        raise ValueError(f"unknown topology {topology!r}")
    return matrices.groupBy("video_id").applyInPandas(run, "video_id string, pos int, i int")
