"""Functions and table functions for SQL: ``register(spark)`` makes them callable by name."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import AnalyzeArgument, AnalyzeResult, PartitioningColumn, OrderingColumn, pandas_udf, udtf
from pyspark.sql.types import ArrayType, DoubleType, FloatType, IntegerType, StructType

from ..config import FoldConfig
from . import kernels


@pandas_udf(DoubleType())
def angle_wrap(x: pd.Series) -> pd.Series:
    return pd.Series(kernels.wrap(x.to_numpy()))


@pandas_udf(DoubleType())
def angle_diff(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series(kernels.wrap(a.to_numpy() - b.to_numpy()))


@pandas_udf(IntegerType())
def zero_crossings(v: pd.Series) -> pd.Series:
    return v.map(lambda x: kernels.zero_crossings(np.asarray(x)))


@pandas_udf(DoubleType())
def l2(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([float(np.linalg.norm(np.asarray(x, float) - np.asarray(y, float))) for x, y in zip(a, b, strict=True)])


@pandas_udf(ArrayType(FloatType()))
def pyr_down(px: pd.Series, h: pd.Series, w: pd.Series, ch: pd.Series) -> pd.Series:
    from ..operators.pyramid import halve

    return pd.Series([halve(np.asarray(p, float).reshape(a, b, c)).astype(np.float32).ravel() for p, a, b, c in zip(px, h, w, ch, strict=True)])


@pandas_udf(DoubleType())
def circ_mean(x: pd.Series) -> float:
    return float(np.arctan2(np.sin(x).mean(), np.cos(x).mean()))


@pandas_udf(ArrayType(DoubleType()))
def vec_median(v: pd.Series) -> np.ndarray:
    return np.median(np.stack([np.asarray(x, float) for x in v]), axis=0)


@pandas_udf(DoubleType())
def acf_period(v: pd.Series) -> float:
    return float(kernels.period(np.asarray(v.iloc[0], float))[0])


@udtf(returnType=StructType().add("j", IntegerType()).add("theta", DoubleType()))
class ThetaGrid:
    def eval(self, m: int):
        for j in range(m):
            yield j, 2 * np.pi * j / m


@udtf(returnType=StructType().add("i", IntegerType()).add("j", IntegerType()).add("val", DoubleType()))
class IdealLaplacian:
    def eval(self, k: int, T: int):
        from ..operators.spectral import ideal_matrix

        lap = ideal_matrix(k, T)
        for i, j in zip(*np.nonzero(lap), strict=True):
            yield int(i), int(j), float(lap[i, j])


def _ordered(argument: AnalyzeArgument) -> dict:
    if not argument.isTable:
        raise ValueError("the first argument is a table of series_id, t, v")
    return {"partitionBy": [PartitioningColumn("series_id")], "orderBy": [OrderingColumn("t")]}


@udtf
class SlidingWindows:
    """(series_id, i, w) of every whole window of d values: sliding_windows(TABLE(s), d)."""

    def __init__(self):
        self.held: list[float] = []
        self.i = 0

    @staticmethod
    def analyze(rows: AnalyzeArgument, d: AnalyzeArgument) -> AnalyzeResult:
        schema = StructType().add("series_id", rows.dataType["series_id"].dataType).add("i", IntegerType()).add("w", ArrayType(DoubleType()))
        return AnalyzeResult(schema=schema, **_ordered(rows))

    def eval(self, row, d: int):
        self.held.append(float(row["v"]))
        if len(self.held) == d:
            yield row["series_id"], self.i, list(self.held)
            self.held.pop(0)
            self.i += 1


@udtf
class RipsH1:
    """(series_id, birth, death) of the windows of d values of a series: rips_h1(TABLE(s), d)."""

    def __init__(self):
        self.v: list[float] = []
        self.of = None
        self.d = 1

    @staticmethod
    def analyze(rows: AnalyzeArgument, d: AnalyzeArgument) -> AnalyzeResult:
        schema = StructType().add("series_id", rows.dataType["series_id"].dataType).add("birth", DoubleType()).add("death", DoubleType())
        return AnalyzeResult(schema=schema, **_ordered(rows))

    def eval(self, row, d: int):
        self.v.append(float(row["v"]))
        self.of, self.d = row["series_id"], d

    def terminate(self):
        from ..operators.homology import bars

        d2 = kernels.window_distances(kernels.squared_distances(np.array(self.v)[:, None]), self.d)
        for birth, death in bars(d2, 7, 200)[0]:
            yield self.of, float(birth), float(death)


@udtf
class Fold:
    """(series_id, j, theta, v, n_votes), the template of each series: fold(TABLE(s), m, alpha)."""

    def __init__(self):
        self.v: list[float] = []
        self.of, self.m, self.alpha = None, 0, 0.5

    @staticmethod
    def analyze(rows: AnalyzeArgument, m: AnalyzeArgument, alpha: AnalyzeArgument) -> AnalyzeResult:
        schema = StructType().add("series_id", rows.dataType["series_id"].dataType)
        schema = schema.add("j", IntegerType()).add("theta", DoubleType()).add("v", DoubleType()).add("n_votes", IntegerType())
        return AnalyzeResult(schema=schema, **_ordered(rows))

    def eval(self, row, m: int, alpha: float):
        self.v.append(float(row["v"]))
        self.of, self.m, self.alpha = row["series_id"], m, float(alpha)

    def terminate(self):
        from ..plans.pipeline import infer

        x = np.array(self.v)
        about, phi, _ = infer(kernels.squared_distances(x[:, None]), FoldConfig(alpha=self.alpha), raw=x)
        angles = 2 * np.pi * np.arange(self.m) / self.m
        out, n = kernels.median_template(x[:, None], kernels.votes(phi, angles, max(about["k"], 1e-9), about["n"], about["d"]), self.m)
        for j in range(self.m):
            yield self.of, j, float(angles[j]), float(out[j, 0]) if n[j] else None, int(n[j])


FUNCTIONS = {
    "angle_wrap": angle_wrap, "angle_diff": angle_diff, "zero_crossings": zero_crossings, "l2": l2, "pyr_down": pyr_down,
    "circ_mean": circ_mean, "vec_median": vec_median, "acf_period": acf_period,
}
TABLES = {"theta_grid": ThetaGrid, "ideal_laplacian": IdealLaplacian, "sliding_windows": SlidingWindows, "rips_h1": RipsH1, "fold": Fold}


def register(spark: SparkSession) -> None:
    for name, f in FUNCTIONS.items():
        spark.udf.register(name, f)
    for name, f in TABLES.items():
        spark.udtf.register(name, f)
