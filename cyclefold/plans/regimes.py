"""Which form a recording takes at its size, and endless recordings in overlapping segments."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Frames of one local distance matrix, and pixels of a frame kept in one tile.
LOCAL_FRAMES, LOCAL_PIXELS = 2_000, 1 << 20


def regime(n: Column, pixels: Column, local_frames: int = LOCAL_FRAMES, local_px: int = LOCAL_PIXELS) -> Column:
    """many: one group a video; huge: tiles of the pixel axis are summed; endless: segments are merged."""
    return F.when(n > local_frames, "endless").when(pixels > local_px, "huge").otherwise("many")


def planned(frames: DataFrame, local_frames: int = LOCAL_FRAMES, local_px: int = LOCAL_PIXELS) -> DataFrame:
    """video_id, n, pixels, regime: one combining aggregate over the frames' shapes; pixels are not read."""
    per = frames.groupBy("video_id").agg(F.count("*").alias("n"), F.max(F.col("h") * F.col("w") * F.col("ch")).cast("long").alias("pixels"))
    return per.withColumn("regime", regime(F.col("n"), F.col("pixels"), local_frames, local_px))


def segments(frames: DataFrame, length: int = LOCAL_FRAMES, overlap: int = 200) -> DataFrame:
    """Frames as segments: video_id gets #k, t counts inside; neighbours share ``overlap`` frames."""
    step = length - overlap
    last = F.floor(F.col("t") / step).cast("int")
    first = F.greatest(F.lit(0), F.ceil((F.col("t") - length + 1) / step).cast("int"))
    rows = frames.withColumn("_k", F.explode(F.sequence(first, last)))
    return rows.withColumn("video_id", F.concat_ws("#", "video_id", F.col("_k").cast("string"))).withColumn("t", (F.col("t") - F.col("_k") * step).cast("int")).drop("_k")


def full_segments(frames: DataFrame, length: int = LOCAL_FRAMES, overlap: int = 200) -> DataFrame:
    """Segments as above, each of ``length`` frames: the last one is moved back to end at the
    recording's last frame; a shorter recording is one segment."""
    step = length - overlap
    ends = frames.groupBy("video_id").agg((F.max("t") + 1).alias("_n"))
    final = F.greatest(F.lit(0), F.ceil((F.col("_n") - length) / step)).cast("int")
    moved = F.greatest(F.lit(0), F.col("_n") - length)
    first = F.greatest(F.lit(0), F.ceil((F.col("t") - length + 1) / step).cast("int"))
    before = F.sequence(first, F.floor(F.col("t") / step).cast("int"))
    ks = F.concat(F.filter(before, lambda k: k < final), F.when(F.col("t") >= moved, F.array(final)).otherwise(F.array().cast("array<int>")))
    rows = frames.join(ends, "video_id").withColumn("_k", F.explode(ks))
    start = F.when(F.col("_k") == final, moved).otherwise(F.col("_k") * step)
    named = rows.withColumn("t", (F.col("t") - start).cast("int")).withColumn("video_id", F.concat_ws("#", "video_id", F.col("_k").cast("string")))
    return named.select(*frames.columns)


def merged(templates: DataFrame) -> DataFrame:
    """video_id, j, theta, tile, px, n_votes: the templates of a video's segments, turned to the first one
    by the best circular shift, in the better direction, then their medians. The turn is found on all
    tiles together from one summed spectrum a tile; a group is one tile of one video's templates (not
    of its frames), so that no video's pixels meet in one task."""

    whole = templates.withColumn("_video", F.substring_index("video_id", "#", 1)).withColumn("_k", F.substring_index("video_id", "#", -1).cast("int"))

    def stacked(pdf: pd.DataFrame):
        """(segment, pixels by angle, votes) in the segments' order."""
        for k, one in pdf.sort_values(["_k", "j"]).groupby("_k"):
            filled = [p for p in one["px"] if p is not None]
            zero = np.zeros(len(filled[0]) if filled else 0)
            yield int(k), np.stack([zero if p is None else np.asarray(p, float) for p in one["px"]]), one["n_votes"].to_numpy()

    def matches(pdf: pd.DataFrame) -> pd.DataFrame:
        parts = list(stacked(pdf))
        anchor = parts[0][1]
        spectrum = np.fft.fft(anchor - anchor.mean(0), axis=0)
        rows = []
        for k, px, _ in parts:
            for back in (False, True):
                turned = px[::-1] if back else px
                match = np.fft.ifft((np.conj(np.fft.fft(turned - turned.mean(0), axis=0)) * spectrum).sum(axis=1)).real
                rows.append((pdf["_video"].iloc[0], k, back, match))
        return pd.DataFrame(rows, columns=["of", "k", "back", "match"])

    by_tile = whole.groupBy("_video", "tile").applyInPandas(matches, "of string, k int, back boolean, match array<double>")
    places = by_tile.select("of", "k", "back", F.posexplode("match").alias("shift", "m")).groupBy("of", "k", "back", "shift").agg(F.sum("m").alias("m"))
    best = places.groupBy("of", "k").agg(F.max_by(F.struct("back", "shift"), F.struct("m", ~F.col("back"), -F.col("shift"))).alias("b"))
    turns = best.groupBy("of").agg(F.map_from_entries(F.collect_list(F.struct("k", "b"))).alias("turns"))

    def run(key, pdf: pd.DataFrame, about: pd.DataFrame) -> pd.DataFrame:
        turn = about["turns"].iloc[0]
        stacks, n, theta = [], 0, pdf.sort_values(["_k", "j"])["theta"].to_numpy()
        for k, px, votes in stacked(pdf):
            back, shift = (turn[k][c] for c in ("back", "shift"))
            px, votes = (x[::-1] if back else x for x in (px, votes))
            stacks.append(np.roll(px, shift, axis=0))
            n = n + np.roll(votes, shift)
        out = np.median(stacks, axis=0)
        return pd.DataFrame({"video_id": key[0], "j": np.arange(len(out), dtype="int32"), "theta": theta[: len(out)], "tile": np.int32(key[1]), "px": list(out.astype(np.float32)), "n_votes": n})

    keyed = whole.select("_video", "tile").distinct().join(turns, F.col("_video") == F.col("of")).select(F.col("of"), F.col("tile").alias("of_tile"), "turns")
    schema = "video_id string, j int, theta double, tile int, px array<float>, n_votes long"
    return whole.groupBy("_video", "tile").cogroup(keyed.groupBy("of", "of_tile")).applyInPandas(run, schema)
