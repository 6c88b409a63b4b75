"""Registration of queries and the form in which results are compared."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
DIGITS = 6


def query(name: str, sql: str | None = None, digits: int = DIGITS):
    def register(f):
        QUERIES[name] = lambda spark, sf_dir: exact(f(spark, sf_dir), digits)
        if sql:
            ORACLES[name] = sql
        return f

    return register


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def rounded(x: Column, digits: int) -> Column:
    """``F.round``. Only values near a half or large ones go through its decimals, which take longer than all else."""
    scaled = x * F.lit(10.0**digits)
    apart = F.abs(F.abs(scaled - F.rint(scaled)) - 0.5)
    return F.when((F.abs(scaled) < 2.0**40) & (apart > 2.0**-10), F.rint(scaled) / F.lit(10.0**digits)).otherwise(F.round(x, digits))


def exact(df: DataFrame, digits: int = DIGITS) -> DataFrame:
    """Whole numbers as bigint, others rounded, no negative zero."""
    out = []
    for c, kind in df.dtypes:
        if kind in ("int", "smallint", "tinyint"):
            out.append(F.col(c).cast("bigint").alias(c))
        elif kind in ("double", "float"):
            out.append((rounded(F.col(c).cast("double"), digits) + F.lit(0.0)).alias(c))
        else:
            out.append(F.col(c))
    return df.select(*out)
