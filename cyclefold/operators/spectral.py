"""Low modes of Laplacians, and the ideal model with its closed form."""

from __future__ import annotations


import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import kernels
from ..functions.angles import TAU


def ideal_laplacian(spark: SparkSession, k: int, T: int) -> DataFrame:
    """i, j, val of k exact repeats of T frames: circulant, each window tied to its neighbours'
    and its own repeats. Entries come from the 3k - 1 offsets of a row, not from all pairs."""
    n = k * T
    offsets = sorted({(l * T + s) % n for l in range(k) for s in (-1, 0, 1)} - {0})
    row = F.explode(F.array(*(F.lit(o) for o in [0, *offsets]))).alias("o")
    return spark.range(n).select(F.col("id").cast("int").alias("i"), row).select(
        "i", F.pmod(F.col("i") + F.col("o"), F.lit(n)).cast("int").alias("j"), F.when(F.col("o") == 0, F.lit(float(len(offsets)))).otherwise(F.lit(-1.0)).alias("val")
    )


def ideal_matrix(k: int, T: int) -> np.ndarray:
    n = k * T
    lap = np.zeros((n, n))
    for l in range(k):
        for s in (-1, 0, 1):
            lap[np.arange(n), (np.arange(n) + l * T + s) % n] = -1
    np.fill_diagonal(lap, 0)
    return lap + np.diag(-lap.sum(axis=1))


def ideal_spectrum(spark: SparkSession, k: int, T: int) -> DataFrame:
    """m, lambda: the eigenvalue of the pair with m cycles over all k T windows."""
    m = F.col("id")
    value = F.when(m % k == 0, 3 * k - k * (1 + 2 * F.cos(F.lit(TAU) * m / (k * T)))).otherwise(F.lit(float(3 * k)))
    return spark.range(1, k * T // 2 + 1).select(m.cast("int").alias("m"), value.alias("lambda"))


def ideal_residual(entries: DataFrame, k: int, T: int) -> DataFrame:
    """video_id, m, resid: the largest entry of L v - lambda v over the cosine and sine vectors of each m.

    A video's rows of L, all or some, meet in one group; lambda is the closed form.
    """
    n = k * T
    values = {r.m: r["lambda"] for r in ideal_spectrum(entries.sparkSession, k, T).collect()}
    m = np.array(sorted(values))
    angle = TAU * np.outer(np.arange(n), m) / n
    vectors, scaled = np.hstack([np.cos(angle), np.sin(angle)]), np.tile([values[x] for x in m], 2)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        lap = np.zeros((n, n))
        lap[pdf["i"], pdf["j"]] = pdf["val"]
        rows = pdf["i"].unique()
        far = np.abs(lap[rows] @ vectors - vectors[rows] * scaled).max(axis=0)
        return pd.DataFrame({"video_id": pdf["video_id"].iloc[0], "m": m.astype("int32"), "resid": np.maximum(far[: len(m)], far[len(m) :])})

    kind = entries.schema["video_id"].dataType.simpleString()
    return entries.groupBy("video_id").applyInPandas(run, f"video_id {kind}, m int, resid double")


def circulant_row(entries: DataFrame, n: int) -> DataFrame:
    """video_id, o, val: the entry at each offset from the diagonal of circulant matrices, from all or some of their rows."""
    return entries.groupBy("video_id", F.pmod(F.col("j") - F.col("i"), F.lit(n)).alias("o")).agg(F.avg("val").alias("val"))


def circulant_spectrum(entries: DataFrame, n: int) -> DataFrame:
    """video_id, m, lambda of symmetric circulant matrices: the cosine sums of their rows."""
    waves = circulant_row(entries, n).withColumn("m", F.explode(F.sequence(F.lit(1), F.lit(n // 2))))
    return waves.groupBy("video_id", "m").agg(F.sum(F.col("val") * F.cos(F.lit(TAU) * F.col("m") * F.col("o") / n)).alias("lambda"))


def circulant(entries: DataFrame, n: int) -> DataFrame:
    """video_id, i, j, val: circulant matrices whole, of which some rows may be missing."""
    rows = circulant_row(entries, n).withColumn("i", F.explode(F.sequence(F.lit(0), F.lit(n - 1))))
    return rows.select("video_id", "i", F.pmod(F.col("i") + F.col("o"), F.lit(n)).alias("j"), "val")


def low_modes(laplacians: DataFrame, q: int = 10) -> DataFrame:
    """video_id, rank, lambda, vec, zero_cross, n_zero from entries (video_id, i, j, val), one video a group."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        n = int(max(pdf["i"].max(), pdf["j"].max())) + 1
        lap = np.zeros((n, n))
        lap[pdf["i"], pdf["j"]] = pdf["val"]
        values, vectors, zero = kernels.low_modes(lap, q)
        return pd.DataFrame(
            {
                "video_id": pdf["video_id"].iloc[0], "rank": np.arange(1, len(values) + 1, dtype="int32"), "lambda": values, "vec": list(vectors.T),
                "zero_cross": [kernels.zero_crossings(v) for v in vectors.T], "n_zero": zero,
            }
        )

    schema = "video_id string, rank int, lambda double, vec array<double>, zero_cross int, n_zero int"
    return laplacians.groupBy("video_id").applyInPandas(run, schema)


def block_power(laplacian: DataFrame, n: int, q: int = 4, steps: int = 60, seed: int = 42, every: int = 5) -> DataFrame:
    """rank, i, v: low modes of one giant graph, by power steps of c I - L on q vectors at once.

    A step is one join and one sum; the small q x q Gram matrix is the only thing that comes
    to the driver. Lineage is cut every few steps by a table in the checkpoint folder. The
    constant vector is projected out, so the first mode is the lowest that is not zero in a
    connected graph.
    """
    from ..functions.angles import normal
    from ..plans.storage import materialise

    spark = laplacian.sparkSession
    c = 2 * float(laplacian.filter("i = j").agg(F.max("val")).first()[0] or 0)
    names = [f"v{k}" for k in range(q)]
    vectors = spark.range(n).select(F.col("id").cast("int").alias("i"), *(normal(F.lit(seed), F.col("id"), F.lit(k)).alias(x) for k, x in enumerate(names)))
    for step in range(steps):
        product = laplacian.join(vectors.withColumnRenamed("i", "j"), "j").groupBy("i").agg(*(F.sum(F.col("val") * F.col(x)).alias(f"l{x}") for x in names))
        vectors = vectors.join(product, "i", "left").select("i", *((c * F.col(x) - F.coalesce(f"l{x}", F.lit(0.0))).alias(x) for x in names))
        if step % every == every - 1 or step == steps - 1:
            vectors = materialise(vectors)
            mean = vectors.agg(*(F.avg(x) for x in names)).first()
            vectors = vectors.select("i", *((F.col(x) - F.lit(m)).alias(x) for x, m in zip(names, mean, strict=True)))
            flat = vectors.agg(*(F.sum(F.col(a) * F.col(b)) for a in names for b in names)).first()
            gram = np.array(flat, float).reshape(q, q)
            if step == steps - 1:  # rotate to Ritz vectors of L
                mixed = laplacian.join(vectors.withColumnRenamed("i", "j"), "j").join(vectors.select("i", *(F.col(x).alias(f"w{x}") for x in names)), "i")
                rayleigh = np.array(mixed.agg(*(F.sum(F.col("val") * F.col(f"w{a}") * F.col(b)) for a in names for b in names)).first(), float).reshape(q, q)
                root = np.linalg.inv(np.linalg.cholesky(gram)).T
                values, rotate = np.linalg.eigh(root.T @ rayleigh @ root)
                root = root @ rotate
            else:
                root = np.linalg.inv(np.linalg.cholesky(gram)).T
            vectors = materialise(vectors.select("i", *(sum(F.col(a) * float(root[r, k]) for r, a in enumerate(names)).alias(x) for k, x in enumerate(names))))
    rows = F.explode(F.array(*(F.struct(F.lit(k + 1).alias("rank"), F.lit(float(values[k])).alias("lambda"), F.col(x).alias("v")) for k, x in enumerate(names))))
    return vectors.select("i", rows.alias("r")).select("r.rank", "r.lambda", "i", "r.v")

