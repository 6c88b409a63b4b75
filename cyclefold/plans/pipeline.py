"""The whole method: frames to phases, and frames and phases to one clean cycle.

Phases: one exchange brings a video's reduced frames together; distances, period, windows,
barcode, graph, modes and angle follow inside the same grouped function, so a video crosses
into Python once. Frames too large for one task are summed over slabs first. Templates: phases are tables of a few
numbers a window; the raw pixels move once more, by video and tile, unless they are stored so.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import FoldConfig
from ..functions import kernels
from ..operators import gram, homology, pyramid, vote
from ..operators.frames import tile_keys, tiles
from ..schema import PHASE, RUN, BadInput

FEWEST = 4


def infer(d2: np.ndarray, config: FoldConfig, raw: np.ndarray | None = None, memo: dict | None = None) -> tuple[dict, np.ndarray, np.ndarray]:
    """(diagnostics, oriented phase, unwrapped phase) from squared frame distances.

    ``raw`` is the signal itself when the recording has one channel; it is then its own surrogate.
    ``memo`` keeps periods and barcodes of these distances for the next configuration.
    """
    memo = {} if memo is None else memo
    n = len(d2)
    if n < FEWEST:
        raise BadInput(f"{n} frames are too few, {FEWEST} are needed")
    T = config.period
    if T is None and config.d is None:
        T = _once(memo, ("T", config.surrogate, config.n_neighbors, config.isomap_landmarks, config.period_method, config.tmin, config.tmax), lambda: _period(d2, config, raw))
    lost = config.d is None and not np.isfinite(T if T is not None else np.nan)
    d = config.d or (1 if lost else int(round(T * config.n_cycles_in_window)) + 1)
    d = max(1, min(d, n - 3))
    w2 = _once(memo, ("w2", d), lambda: kernels.window_distances(d2, d))
    bars, radius, some = (
        _once(memo, ("bars", d, config.coeff, config.max_n), lambda: homology.bars(w2, config.coeff, config.max_n)) if config.sigma is None else (np.zeros((0, 2)), 0.0, None)
    )
    sigma, none = (config.sigma, False) if config.sigma is not None else kernels.auto_scale(bars, config.alpha, some)
    lap = kernels.laplacian(kernels.adjacency(np.sqrt(w2), sigma, config.kernel))
    values, vectors, zero = kernels.low_modes(lap, config.q)
    if len(values) < 2:
        phi, unwrapped, flat = np.zeros(len(w2)), np.zeros(len(w2)), True
    else:
        counts = [kernels.zero_crossings(v) for v in vectors.T]
        a, b, flat = kernels.mode_pair(counts, config.tol) if config.select == "zero_cross" else (0, 1, False)
        phi, unwrapped = kernels.unwrap(kernels.phase(vectors, (a, b)))
    second = bars[1, 1] - bars[1, 0] if len(bars) > 1 else 0.0
    about = {
        "n": n, "period": float("nan") if T is None else float(T), "d": d, "sigma": float(sigma), "alpha": config.alpha, "kernel": config.kernel,
        "coeff": kernels.field_characteristic(config.coeff), "k": kernels.cycle_count(unwrapped, n, d, config.cycles),
        "loop_ratio": float((bars[0, 1] - bars[0, 0]) / second) if second > 0 else float("nan"), "n_components": zero, "fallback": bool(none or flat or lost), "cover_radius": radius,
    }
    return about, phi, unwrapped


def _once(memo: dict, key: tuple, make):
    if key not in memo:
        memo[key] = make()
    return memo[key]


def _period(d2: np.ndarray, config: FoldConfig, raw: np.ndarray | None) -> float:
    if config.surrogate == "distances":
        return kernels.matrix_period(d2, config.tmin, config.tmax)[0]
    use_raw = raw is not None and config.surrogate in ("auto", "raw")
    signal = raw if use_raw else kernels.isomap1d(d2, config.n_neighbors, config.isomap_landmarks)
    return kernels.period(signal, config.period_method, config.tmin, config.tmax)[0]


_BOTH = RUN + ", phi array<double>, phi_u array<double>"


def inferred(frames: DataFrame, config: FoldConfig | None = None) -> DataFrame:
    """One row a video: the run's diagnostics and both phase arrays."""
    config = config or FoldConfig()
    small = pyramid.reduce(frames, config.pyramid_level)

    def row(video, d2: np.ndarray) -> pd.DataFrame:
        about, phi, unwrapped = infer(d2, config)
        return pd.DataFrame([{"video_id": video, **about, "phi": phi, "phi_u": unwrapped}])[[c.split()[0] for c in _BOTH.split(", ")]]

    if config.gram_tile_px is None:  # pixels to phases in one group: one exchange

        def run(pdf: pd.DataFrame) -> pd.DataFrame:
            px = np.stack(pdf.sort_values("t")["px"].to_numpy())
            return row(pdf["video_id"].iloc[0], kernels.squared_distances(px))

        return small.select("video_id", "t", "px").groupBy("video_id").applyInPandas(run, _BOTH)

    def run_matrix(pdf: pd.DataFrame) -> pd.DataFrame:
        n = int(pdf["n"].iloc[0])
        return row(pdf["video_id"].iloc[0], np.asarray(pdf["d2"].iloc[0]).reshape(n, n))

    return gram.distance_matrices(small, config.gram_tile_px).groupBy("video_id").applyInPandas(run_matrix, _BOTH)


def inferred_series(series: DataFrame, config: FoldConfig | None = None) -> DataFrame:
    """The same for one-channel series (series_id, t, v)."""
    config = config or FoldConfig()

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        x = pdf.sort_values("t")["v"].to_numpy(float)
        about, phi, unwrapped = infer(kernels.squared_distances(x[:, None]), config, raw=x)
        return pd.DataFrame([{"video_id": pdf["series_id"].iloc[0], **about, "phi": phi, "phi_u": unwrapped}])[[c.split()[0] for c in _BOTH.split(", ")]]

    return series.select("series_id", "t", "v").groupBy("series_id").applyInPandas(run, _BOTH)


def runs(found: DataFrame) -> DataFrame:
    return found.drop("phi", "phi_u")


def phases(found: DataFrame) -> DataFrame:
    """video_id, i, phi, phi_u from ``inferred`` rows."""
    both = F.posexplode(F.arrays_zip("phi", "phi_u")).alias("i", "p")
    return found.select("video_id", both).select("video_id", "i", "p.phi", "p.phi_u").to(_schema(found, PHASE))


def _schema(df: DataFrame, layout: str):
    return df.sparkSession.createDataFrame([], layout).schema


def fold(frames: DataFrame, config: FoldConfig | None = None, found: DataFrame | None = None) -> DataFrame:
    """The template: video_id, j, theta, tile, px, n_votes. Raw frames vote, not reduced ones.

    ``found`` takes written results of ``inferred`` so that phases are not inferred again, for videos
    of one regime; without it each video takes the form that its size asks for.
    Votes are made inside the tile's group from the video's phases, a few numbers a window.
    """
    config = config or FoldConfig()
    if found is None:
        return by_regime(frames, config)
    slabs = tiles(frames, config.tile_px)
    keys = tile_keys(frames, config.tile_px)
    spread = keys.join(found.select("video_id", "n", "d", "k", "phi"), "video_id").withColumnsRenamed({"video_id": "of_video", "tile": "of_tile"})

    def run(key, tile: pd.DataFrame, about: pd.DataFrame) -> pd.DataFrame:
        tile = tile.sort_values("t")
        px = np.stack(tile["px"].to_numpy()).astype(np.float64)
        row = about.iloc[0]
        m = config.M or len(row.phi)
        angles = 2 * np.pi * np.arange(m) / m
        ballots = kernels.votes(np.asarray(row.phi), angles, max(float(row.k), 1e-9), int(row.n), int(row.d), config.F, config.anchor)
        if config.median == "exact":
            out, n = kernels.median_template(px, ballots, m)
        else:
            out, n = vote.histogram_median(px, ballots, m, float(px.min()), float(px.max()) + 1e-9)
        return pd.DataFrame(
            {
                "video_id": key[0], "j": np.arange(m, dtype="int32"), "theta": angles, "tile": np.int32(key[1]),
                "px": [r.astype(np.float32) if c else None for r, c in zip(out, n, strict=True)], "n_votes": n.astype("int64"),
            }
        )

    schema = "video_id string, j int, theta double, tile int, px array<float>, n_votes long"
    return slabs.groupBy("video_id", "tile").cogroup(spread.groupBy("of_video", "of_tile")).applyInPandas(run, schema)


def by_regime(frames: DataFrame, config: FoldConfig) -> DataFrame:
    """The template of every video in the form that its size asks for.

    Which forms occur is counted first, from the frames' shapes alone; at most three numbers come to the
    driver. Videos of ``many`` are one group each; of ``huge`` frames the distances are summed over slabs;
    ``endless`` videos are folded in overlapping segments whose templates are merged.
    """
    from . import regimes

    plan = regimes.planned(frames, config.local_frames, config.local_px)
    present = {r.regime for r in plan.select("regime").distinct().collect()}
    out = None
    for regime in ("many", "huge", "endless"):
        if regime not in present:
            continue
        own = frames if len(present) == 1 else frames.join(plan.filter(F.col("regime") == regime).select("video_id"), "video_id", "left_semi")
        if regime == "endless":
            parts = regimes.full_segments(own, config.local_frames, config.overlap)
            one = regimes.merged(_folded(parts, config.but(M=config.M or config.local_frames // 10)))
        else:
            one = _folded(own, config if regime == "many" else config.but(gram_tile_px=config.gram_tile_px or config.local_px))
        out = one if out is None else out.unionByName(one)
    return out if out is not None else _folded(frames, config)


def _folded(frames: DataFrame, config: FoldConfig) -> DataFrame:
    return fold(frames, config, inferred(frames, config))


def fold_series(series: DataFrame, config: FoldConfig | None = None) -> DataFrame:
    """series_id, j, theta, v, n_votes: the template cycle of each one-channel series."""
    config = config or FoldConfig()

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        x = pdf.sort_values("t")["v"].to_numpy(float)
        about, phi, _ = infer(kernels.squared_distances(x[:, None]), config, raw=x)
        m = config.M or len(phi)
        angles = 2 * np.pi * np.arange(m) / m
        ballots = kernels.votes(phi, angles, max(about["k"], 1e-9), about["n"], about["d"], config.F, config.anchor)
        out, n = kernels.median_template(x[:, None], ballots, m)
        return pd.DataFrame({"series_id": pdf["series_id"].iloc[0], "j": np.arange(m, dtype="int32"), "theta": angles, "v": out[:, 0], "n_votes": n.astype("int64")})

    return series.select("series_id", "t", "v").groupBy("series_id").applyInPandas(run, "series_id string, j int, theta double, v double, n_votes long")
