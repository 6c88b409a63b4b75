"""Stored layouts in which the big steps need no shuffle."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def write_tiles(tiles: DataFrame, path: str) -> None:
    """Tiles partitioned by tile and sorted by video and time: a pruned scan reads whole slabs."""
    tiles.repartition("tile", "video_id").sortWithinPartitions("video_id", "t").write.partitionBy("tile").parquet(path)


def save_bucketed(tiles: DataFrame, table: str, buckets: int) -> None:
    """Tiles bucketed and sorted by (video, tile): grouping by them reads without an exchange."""
    tiles.write.bucketBy(buckets, "video_id", "tile").sortBy("video_id", "tile", "t").mode("overwrite").saveAsTable(table)


def round_trip(df: DataFrame, path: str, kind: str) -> DataFrame:
    """Write and read with the schema given: csv, json, orc or parquet."""
    spark: SparkSession = df.sparkSession
    df.write.format(kind).option("header", "true").save(path)
    return spark.read.schema(df.schema).format(kind).option("header", "true").load(path)
