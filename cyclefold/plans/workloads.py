"""The experiments, re-expressed on the given tables; each is one job over a grid of conditions."""

from __future__ import annotations

import itertools

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import FoldConfig
from ..operators import metrics
from ..schema import names
from . import pipeline, synth

#: The conditions of the experiments. Shakes are pixels of a frame 300 wide.
CYCLES = (3, 5, 10, 15, 20, 25, 30, 40, 50)
SHAKES = (10, 20, 30, 40, 50)
NOISES = (0.5, 1.0, 2.0)
SIDES = (0.05, 0.10, 0.15, 0.20, 0.30)
ALPHAS = tuple(round(0.1 * a, 1) for a in range(11))


def grid(spark: SparkSession, corruption: str, levels, scenes=(1, 2, 3), cycles=(15,), trials: int = 1) -> DataFrame:
    rows = [
        (f"s{s}c{c}{corruption}{level}t{t}", s, float(c), corruption, float(level), t)
        for s, c, level, t in itertools.product(scenes, cycles, levels, range(trials))
    ]
    return spark.createDataFrame(rows, synth.GRID).repartition(max(1, min(len(rows), 4 * spark.sparkContext.defaultParallelism)))


def conditions(spark: SparkSession, workload: str, h: int = 32, trials: int = 1, scenes=(1, 2, 3)) -> DataFrame:
    """The grid of a workload; levels in pixels scale with the frame's height."""
    if workload == "cycles":
        return grid(spark, "none", [0.0], scenes, CYCLES, trials)
    if workload == "shake":
        return grid(spark, "shake", [round(s * h / 300, 6) for s in SHAKES], scenes, trials=trials)
    if workload == "noise":
        return grid(spark, "noise", NOISES, scenes, trials=trials)
    if workload == "occlude":
        return grid(spark, "occlude", SIDES, scenes, trials=trials)
    if workload == "missing":
        return grid(spark, "drop", [0.1], scenes, trials=trials)
    raise ValueError(f"unknown workload {workload!r}")


def study(spark: SparkSession, name: str, h: int = 32, trials: int = 1, scenes=(1, 2, 3), **config) -> tuple[DataFrame, dict[str, FoldConfig]]:
    """The conditions and variants of an experiment."""
    if name == "alpha":  # clean, and one moderate level of each corruption
        parts = [grid(spark, c, [level], scenes, trials=trials) for c, level in (("none", 0.0), ("shake", round(30 * h / 300, 6)), ("noise", 0.5), ("occlude", 0.1))]
        return union(parts), alpha_by_window(**config)
    if name == "kernel":
        return union([grid(spark, "none", [0.0], scenes, trials=trials), grid(spark, "noise", [0.1, 0.5], scenes, trials=trials)]), kernel_variants(**config)
    if name == "landmarks":
        changes = {f"max_n={m}": FoldConfig(**(config | {"max_n": m})) for m in (60, 90, 120, 200)} | {"exact": FoldConfig(**(config | {"max_n": None}))}
        return union([grid(spark, "none", [0.0], scenes, trials=trials), grid(spark, "noise", [0.5], scenes, trials=trials)]), changes
    return conditions(spark, name, h, trials, scenes), windowed_or_not(**config)


def union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for part in parts[1:]:
        out = out.unionByName(part)
    return out


def errors(
    spark: SparkSession, embeddings: DataFrame, conditions: DataFrame, configs: dict[str, FoldConfig], n: int = 600, h: int = 32, w: int = 32, ch: int = 1, jitter: float = 0.0, drift: float = 0.0
) -> DataFrame:
    """video_id, scene, cycles, corruption, level, trial, variant, err_deg, k, period, sigma, loop_ratio, fallback.

    Each condition's video is made once and its distances, periods and barcodes serve all variants in one group.
    """
    import pandas as pd

    from ..functions import kernels
    from ..operators.pyramid import halve
    from .corrupt import apply

    basis = synth.basis_rows(embeddings)

    def run(batches):
        for pdf in batches:
            for row in pdf.itertuples():
                made = synth.frames_of(basis, row.scene, row.cycles, n, h, w, jitter, row.trial, ch, drift)
                px = apply(made, h, w, row.corruption, row.level, f"{row.video_id}|{row.trial}")
                truth = 2 * np.pi * row.cycles * np.arange(n) / n
                rows = []
                cache: dict[int, tuple[np.ndarray, dict]] = {}
                for name, config in configs.items():
                    level = config.pyramid_level
                    if level not in cache:
                        small = px.reshape(n, h, w, ch)
                        for _ in range(level - 1):
                            small = halve(small)
                        cache[level] = kernels.squared_distances(small.reshape(n, -1)), {}
                    d2, memo = cache[level]
                    about, phi, _ = pipeline.infer(d2, config, memo=memo)
                    rows.append((name, kernels.angular_error(phi, truth[: len(phi)]), *(about[c] for c in ("k", "period", "sigma", "loop_ratio", "fallback"))))
                out = pd.DataFrame(rows, columns=["variant", "err_deg", "k", "period", "sigma", "loop_ratio", "fallback"])
                for c in names(synth.GRID):
                    out[c] = getattr(row, c)
                yield out[[c.split()[0] for c in _ERRORS.split(", ")]]

    return conditions.mapInPandas(run, _ERRORS)


_ERRORS = synth.GRID + ", variant string, err_deg double, k double, period double, sigma double, loop_ratio double, fallback boolean"


def windowed_or_not(**changes) -> dict[str, FoldConfig]:
    return {"windowed": FoldConfig(**changes), "single": FoldConfig(**(changes | {"d": 1}))}


def alpha_variants(**changes) -> dict[str, FoldConfig]:
    return {f"alpha={a}": FoldConfig(**(changes | {"alpha": a})) for a in ALPHAS}


def alpha_by_window(**changes) -> dict[str, FoldConfig]:
    return {f"{v}/{a}": c.but(alpha=a) for v, c in windowed_or_not(**changes).items() for a in ALPHAS}


def kernel_variants(**changes) -> dict[str, FoldConfig]:
    return {f"{k}/{s}": FoldConfig(**(changes | {"kernel": k, "select": s})) for k in ("gauss", "printed", "step") for s in ("zero_cross", "first")}


def table(found: DataFrame) -> DataFrame:
    """corruption, level, and the mean error of each variant beside each other, with subtotals."""
    return found.groupBy("scene", "corruption", "level").pivot("variant").agg(F.round(F.avg("err_deg"), 3)).orderBy("scene", "corruption", "level")


def stability(found: DataFrame) -> DataFrame:
    return metrics.alpha_spread(found, ["scene", "corruption", "level"])
