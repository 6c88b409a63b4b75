"""The scale of the loop from one-dimensional Rips persistence."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import kernels
from . import gram

BARS = "video_id string, rank int, birth double, death double, persistence double, cover_radius double"


def bars(dist2: np.ndarray, coeff: int, max_n: int | None, landmarks: int | None = None) -> tuple[np.ndarray, float, np.ndarray]:
    """(bars, cover radius, distances used): exact up to ``max_n`` points, else on farthest-point landmarks.

    The barcode of landmarks differs by at most twice the cover radius.
    """
    m = landmarks or (max_n if max_n and len(dist2) > max_n else None)
    radius = 0.0
    if m and m < len(dist2):
        marks, radius = kernels.landmark_order(dist2, m)
        dist2 = dist2[np.ix_(marks, marks)]
    dist = np.sqrt(dist2)
    return kernels.rips_h1(dist, coeff), radius, dist


def rips_h1(matrices: DataFrame, coeff: int = 7, max_n: int = 200, landmarks: int | None = None) -> DataFrame:
    """The H1 bars of each packed (squared) distance matrix, most persistent first; one video a group."""
    kernels.field_characteristic(coeff)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        n = int(pdf["n"].iloc[0])
        found, radius, _ = bars(np.asarray(pdf["d2"].iloc[0]).reshape(n, n), coeff, max_n, landmarks)
        return pd.DataFrame(
            {"video_id": pdf["video_id"].iloc[0], "rank": np.arange(1, len(found) + 1, dtype="int32"), "birth": found[:, 0], "death": found[:, 1], "persistence": found[:, 1] - found[:, 0], "cover_radius": radius}
        )

    return matrices.groupBy("video_id").applyInPandas(run, BARS)


def h0_deaths(matrices: DataFrame) -> DataFrame:
    """video_id, rank, len: where components merge, the edges of a minimal spanning tree."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        n = int(pdf["n"].iloc[0])
        deaths = kernels.h0_deaths(np.sqrt(np.asarray(pdf["d2"].iloc[0]).reshape(n, n)))
        return pd.DataFrame({"video_id": pdf["video_id"].iloc[0], "rank": np.arange(1, n, dtype="int32"), "len": deaths})

    return matrices.groupBy("video_id").applyInPandas(run, "video_id string, rank int, len double")


def h0_deaths_of_frames(frames: DataFrame) -> DataFrame:
    """``h0_deaths`` from frames: a forest of each two blocks, then the tree of all."""
    rank = F.row_number().over(Window.partitionBy("video_id").orderBy("d2"))
    return gram.spanning_edges(frames).select("video_id", rank.alias("rank"), F.sqrt("d2").alias("len"))


def landmarks(matrices: DataFrame, m: int) -> DataFrame:
    """video_id, rank, i: farthest-point order from point 0."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        n = int(pdf["n"].iloc[0])
        order, _ = kernels.landmark_order(np.asarray(pdf["d2"].iloc[0]).reshape(n, n), m)
        return pd.DataFrame({"video_id": pdf["video_id"].iloc[0], "rank": np.arange(len(order), dtype="int32"), "i": order.astype("int32")})

    return matrices.groupBy("video_id").applyInPandas(run, "video_id string, rank int, i int")


def landmark_frames(frames: DataFrame, m: int) -> DataFrame:
    """video_id, rank, i, px: farthest-point order from frame 0, ties to the earlier frame; a pass over the frames each.

    Only the landmarks come to the driver; no distance between two other frames is computed.
    """
    marks = {r.video_id: [(r.t, r.px)] for r in frames.filter("t = 0").select("video_id", "t", "px").collect()}

    def farthest(batches):
        for pdf in batches:
            for video, rows in pdf.groupby("video_id"):
                x, near = np.stack(rows["px"].to_numpy()).astype(float), np.full(len(rows), np.inf)
                for _, p in marks[video]:
                    np.minimum(near, ((x - np.asarray(p, float)) ** 2).sum(axis=1), out=near)
                k = np.lexsort((rows["t"].to_numpy(), -near))[0]
                yield pd.DataFrame({"video_id": [video], "t": [int(rows["t"].iloc[k])], "d2": [float(near[k])], "px": [x[k]]})

    for _ in range(m - 1):
        each = frames.select("video_id", "t", "px").mapInPandas(farthest, "video_id string, t int, d2 double, px array<double>")
        best = each.groupBy("video_id").agg(F.max_by(F.struct("t", "d2", "px"), F.struct("d2", -F.col("t"))).alias("b")).collect()
        new = [r for r in best if r.b.d2 > 0]
        if not new:
            break
        for r in new:
            marks[r.video_id].append((r.b.t, r.b.px))
    rows = [(v, k, t, [float(p) for p in px]) for v, found in marks.items() for k, (t, px) in enumerate(found)]
    return frames.sparkSession.createDataFrame(rows, "video_id string, rank int, i int, px array<double>")


def strongest(pd_table: DataFrame, by: list[str] | None = None) -> DataFrame:
    """The most persistent bar of each group, ties to the earlier birth, by one combining aggregate."""
    key = F.struct((F.col("death") - F.col("birth")).alias("p"), (-F.col("birth")).alias("b"))
    best = pd_table.groupBy(*(by or [])).agg(F.max_by(F.struct("birth", "death"), key).alias("s"))
    return best.select(*(by or []), "s.birth", "s.death")


def auto_scale(pd_table: DataFrame, alphas: DataFrame, by: list[str] | None = None) -> DataFrame:
    """(by), alpha, sigma: birth weighs alpha, death the rest. The bars are computed once for all alphas."""
    one = strongest(pd_table, by)
    return one.join(F.broadcast(alphas.select("alpha"))).select(*(by or []), "alpha", (F.col("alpha") * F.col("birth") + (1 - F.col("alpha")) * F.col("death")).alias("sigma"))


def loop_strength(pd_table: DataFrame) -> DataFrame:
    """video_id, top, second, ratio: persistence of the two strongest loops."""
    rank = F.row_number().over(Window.partitionBy("video_id").orderBy(F.desc("persistence"), "birth"))
    two = pd_table.withColumn("r", rank).filter("r <= 2").groupBy("video_id")
    out = two.agg(F.max(F.when(F.col("r") == 1, F.col("persistence"))).alias("top"), F.max(F.when(F.col("r") == 2, F.col("persistence"))).alias("second"))
    return out.withColumn("second", F.coalesce("second", F.lit(0.0))).withColumn("ratio", F.when(F.col("second") > 0, F.col("top") / F.col("second")))
