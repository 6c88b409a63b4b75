"""Accuracy and cost measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.angles import circular_mean, wrap


def angular_error(phase: DataFrame, truth: DataFrame, by: list[str] | None = None) -> DataFrame:
    """video_id, err_deg: mean wrapped difference after the best offset, in the better direction.

    phase: video_id, i, phi; truth: video_id, t, phi. Two combining aggregates by video and direction.
    """
    by = by or ["video_id"]
    joined = phase.join(truth.withColumnRenamed("t", "i").withColumnRenamed("phi", "true_phi"), [*by, "i"])
    both = joined.select(*by, F.explode(F.array(F.lit(1), F.lit(-1))).alias("dir"), "phi", "true_phi").withColumn("e", F.col("dir") * F.col("phi") - F.col("true_phi"))
    offset = both.groupBy(*by, "dir").agg(circular_mean(F.col("e")).alias("o"))
    errors = both.join(offset, [*by, "dir"]).groupBy(*by, "dir").agg(F.degrees(F.avg(F.abs(wrap(F.col("e") - F.col("o"))))).alias("err"))
    return errors.groupBy(*by).agg(F.min("err").alias("err_deg"))


def template_rmse(template: DataFrame, truth: DataFrame) -> DataFrame:
    """video_id, rmse over template rows (video_id, j, p, val) and truth rows of the same keys."""
    both = template.join(truth.withColumnRenamed("val", "true_val"), ["video_id", "j", "p"])
    return both.groupBy("video_id").agg(F.sqrt(F.avg((F.col("val") - F.col("true_val")) * (F.col("val") - F.col("true_val")))).alias("rmse"))


def seam_energy(ordered: DataFrame, by: list[str]) -> DataFrame:
    """(by), e: mean squared step between successive rows (by, pos, px), from the last to the first too."""
    w = Window.partitionBy(*by).orderBy("pos")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    step = F.coalesce(F.lead("px").over(w), F.first("px").over(whole))
    square = F.aggregate(F.zip_with("px", step, lambda a, b: (a.cast("double") - b.cast("double")) * (a.cast("double") - b.cast("double"))), F.lit(0.0), lambda s, x: s + x)
    return ordered.withColumn("q", square).groupBy(*by).agg(F.avg("q").alias("e"))


def xt_slice(pixels: DataFrame, y: int) -> DataFrame:
    """video_id, t, x, ch, val: one line of pixels over time; the filter reaches the scan's generator."""
    return pixels.filter(F.col("y") == y).select("video_id", "t", "x", "ch", "val")


def residual_energy(template: DataFrame, clean: DataFrame) -> DataFrame:
    """video_id, e: mean squared remainder of what does not belong to the cycle."""
    both = template.join(clean.withColumnRenamed("val", "clean_val"), ["video_id", "j", "p"])
    return both.groupBy("video_id").agg(F.avg((F.col("val") - F.col("clean_val")) * (F.col("val") - F.col("clean_val"))).alias("e"))


def cycle_deviation(series: DataFrame, phase: DataFrame, template: DataFrame, m: int) -> DataFrame:
    """cycle, rms, n: each cycle's remainder against the template at the nearest angle.

    series: t, v; phase: i, phi, phi_u; template: j, v.
    """
    j = F.pmod(F.floor(F.col("phi") / F.lit(2 * 3.141592653589793) * m + 0.5), F.lit(m)).cast("int")
    rows = series.join(phase.withColumnRenamed("i", "t"), "t").select(F.floor(F.col("phi_u") / F.lit(2 * 3.141592653589793)).cast("int").alias("cycle"), j.alias("j"), "v")
    both = rows.join(F.broadcast(template.select("j", F.col("v").alias("mid"))), "j")
    return both.groupBy("cycle").agg(F.sqrt(F.avg((F.col("v") - F.col("mid")) * (F.col("v") - F.col("mid")))).alias("rms"), F.count("*").alias("n"))


def alpha_spread(errors: DataFrame, by: list[str]) -> DataFrame:
    """(by), spread: how far the error moves over alpha."""
    return errors.groupBy(*by).agg((F.max("err_deg") - F.min("err_deg")).alias("spread"))


def cycle_error(runs: DataFrame, k: float, T: float) -> DataFrame:
    return runs.select("video_id", F.abs(F.col("k") - k).alias("k_err"), (F.abs(F.col("period") - T) / T).alias("period_err"))


def spectrum_gap(modes: DataFrame, ideal: DataFrame) -> DataFrame:
    """video_id, gap: largest difference of eigenvalues of equal rank."""
    both = modes.join(ideal.withColumnRenamed("lambda", "ideal"), "rank")
    return both.groupBy("video_id").agg(F.max(F.abs(F.col("lambda") - F.col("ideal"))).alias("gap"))


def stage_cost(df: DataFrame) -> DataFrame:
    """operator, n: how often each physical operator occurs in a plan; exchanges are its cost at scale."""
    import re

    text = df._jdf.queryExecution().executedPlan().toString()
    found: dict[str, int] = {}
    for line in text.splitlines():
        if m := re.search(r"(?:\+-|:-)\s*(?:\*\(\d+\)\s*)?([A-Z]\w+)", line):
            found[m[1]] = found.get(m[1], 0) + 1
    return df.sparkSession.createDataFrame(sorted(found.items()) or [("none", 0)], "operator string, n int")
