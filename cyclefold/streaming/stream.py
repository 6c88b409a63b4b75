"""Streams of events: windows, sessions, joins, and phases against a frozen template as data arrives.

All functions take and return streaming DataFrames (or static ones, where state is not
needed); times are timestamps, so a stored timestamp without zone is cast in UTC first.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def events(spark: SparkSession, folder: str, files_per_batch: int = 1, late: str = "2 hours") -> DataFrame:
    """The event files of a folder as a stream with event time and a watermark."""
    rows = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_batch).parquet(folder)
    return rows.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)


def tumbling(rows: DataFrame, width: str = "2 hours") -> DataFrame:
    """w (start), n, v: closed windows become rows of a regular series."""
    out = rows.groupBy(F.window("ts", width)).agg(F.count("*").alias("n"), F.avg("value").alias("v"))
    return out.select(F.col("window.start").alias("w"), "n", "v")


def sliding(rows: DataFrame, width: str = "2 hours", step: str = "30 minutes") -> DataFrame:
    return rows.groupBy(F.window("ts", width, step)).agg(F.count("*").alias("n"), F.avg("value").alias("v")).select(F.col("window.start").alias("w"), "n", "v")


def sessions(rows: DataFrame, gap: str = "6 hours") -> DataFrame:
    out = rows.groupBy("user_id", F.session_window("ts", gap)).agg(F.count("*").alias("n"))
    return out.select("user_id", F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "n")


def deduplicated(rows: DataFrame) -> DataFrame:
    """Each event once; ids are forgotten when the watermark has passed them."""
    return rows.dropDuplicatesWithinWatermark(["event_id"])


def with_template(rows: DataFrame, template: DataFrame, period_hours: float, m: int) -> DataFrame:
    """Stream-static join: each event beside the template value of its angle; template (j, mid) is small."""
    hours = F.unix_micros("ts") / F.lit(3_600_000_000.0)
    j = F.pmod(F.floor(F.pmod(hours, F.lit(period_hours)) / F.lit(period_hours / m)), F.lit(m)).cast("int")
    return rows.withColumn("j", j).join(F.broadcast(template), "j", "left")


def clicks_before_purchases(rows: DataFrame, within: str = "1 hour") -> DataFrame:
    """Stream-stream interval join of a user's purchases with the clicks before them."""
    click = rows.filter("event_type = 'click'").select(F.col("user_id").alias("cu"), F.col("ts").alias("ct"), F.col("event_id").alias("click_id"))
    buy = rows.filter("event_type = 'purchase'").select(F.col("user_id").alias("pu"), F.col("ts").alias("pt"), F.col("event_id").alias("purchase_id"))
    return buy.join(click, F.expr(f"cu = pu AND ct >= pt - INTERVAL {within} AND ct <= pt")).select("purchase_id", "click_id", F.col("pu").alias("user_id"))


def online_phase(series: DataFrame, windows: np.ndarray, angles: np.ndarray, alert: float) -> DataFrame:
    """series_id, i, phi, deviation, alert: phases of arriving windows against a frozen template.

    ``series``: series_id, t, v in arrival order. Each series keeps a ring of the last d
    values; a full ring takes the angle of the nearest template window (rows of ``windows``)
    and its distance, per root of the values, as deviation. State is d values a series.
    """
    d = windows.shape[1]
    schema = "series_id string, i long, phi double, deviation double, alert boolean"

    def step(key, batches, state: GroupState):
        held, last = state.get if state.exists else ([], -1)
        held, out = list(held), []
        arrived = pd.concat(batches).sort_values("t")
        for t, v in zip(arrived["t"], arrived["v"], strict=True):
            if t <= last:
                continue  # late or repeated
            last = int(t)
            held = [*held[-(d - 1) :], float(v)] if d > 1 else [float(v)]
            if len(held) == d:
                far = np.sqrt(((windows - np.array(held)) ** 2).sum(axis=1))
                k = int(np.argmin(far))
                deviation = float(far[k] / np.sqrt(d))
                out.append((key[0], last - d + 1, float(angles[k]), deviation, deviation > alert))
        state.update((held, last))
        yield pd.DataFrame(out, columns=["series_id", "i", "phi", "deviation", "alert"])

    return series.groupBy("series_id").applyInPandasWithState(step, schema, "held array<double>, last long", "append", GroupStateTimeout.NoTimeout)


def upsert_latest(batch: DataFrame, path: str, key: str = "series_id", order: str = "i") -> None:
    """foreachBatch: the latest row of each key, old and new, written as a new version in ``path``.

    Versions are folders by number, so that a batch that runs again replaces only its own.
    """
    spark = batch.sparkSession
    versions = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    fs = versions.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    old = sorted(int(s.getPath().getName()) for s in fs.listStatus(versions) if fs.exists(versions)) if fs.exists(versions) else []
    rows = batch
    if old:
        rows = rows.unionByName(spark.read.schema(batch.schema).parquet(f"{path}/{old[-1]}"))
    latest = rows.groupBy(key).agg(F.max_by(F.struct(*batch.columns), order).alias("r")).select("r.*")
    latest.write.mode("overwrite").parquet(f"{path}/{old[-1] + 1 if old else 0}")
    for version in old[:-1]:
        fs.delete(spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{path}/{version}"), True)


def run_once(df: DataFrame, name: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """All that is there now, into a table in memory; for tests and looks."""
    q = df.writeStream.format("memory").queryName(name).option("checkpointLocation", checkpoint).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.table(name)


def run_to_files(df: DataFrame, folder: str, checkpoint: str) -> DataFrame:
    """All that is there now, appended to Parquet files in a shared folder by the tasks; no row goes to the driver."""
    q = df.writeStream.format("parquet").option("path", folder).option("checkpointLocation", checkpoint).outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.read.schema(df.schema).parquet(folder)
