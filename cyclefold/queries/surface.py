"""Streams, SQL functions and sources as queries."""

from __future__ import annotations

import uuid

import numpy as np
from pyspark.sql import functions as F

from ..functions import sql
from ..functions.angles import TAU
from ..operators import frames
from ..plans import storage
from ..sources import planted
from ..streaming import stream
from .methods import IDEAL, K, SERIES, T, M, buckets, planted_series
from .registry import query, table


def finished(spark, streamed, mode="append"):
    """A stream run over all that is there, as a table; its progress, and rows that are appended, lie in the shared folder."""
    name = f"_cyclefold_{uuid.uuid4().hex}"
    if mode == "append":
        return stream.run_to_files(streamed, storage.new_folder(spark), f"{storage.shared_dir(spark).rstrip('/')}/{name}")
    return stream.run_once(streamed, name, f"{storage.shared_dir(spark).rstrip('/')}/{name}", mode)


def events(spark, sf):
    return stream.events(spark, f"{sf}/events.parquet*")


@query("stream_tumbling", "SELECT (epoch_us(ts) // 7200000000) * 2 AS w, count(*) AS n, round(sum(value), 4) + 0.0 AS v FROM events GROUP BY 1")
def stream_tumbling(spark, sf):
    out = finished(spark, stream.tumbling(events(spark, sf)), "complete")
    return out.select((F.unix_seconds("w") / 3600).cast("long").alias("w"), "n", F.round(F.col("v") * F.col("n"), 4).alias("v"))


@query(
    "stream_sliding",
    """WITH g AS (SELECT (epoch_us(ts) // 1800000000) AS h, value FROM events), x AS (SELECT h - k AS s, value FROM g, (SELECT unnest(range(4)) AS k))
SELECT s * 30 AS w, count(*) AS n, round(sum(value), 4) + 0.0 AS v FROM x GROUP BY s""",
)
def stream_sliding(spark, sf):
    out = finished(spark, stream.sliding(events(spark, sf)), "complete")
    return out.select((F.unix_seconds("w") / 60).cast("long").alias("w"), "n", F.round(F.col("v") * F.col("n"), 4).alias("v"))


@query("stream_closed", "SELECT count(*) > 0 AS some FROM events")
def stream_closed(spark, sf):
    """In append mode the windows that the watermark has passed are emitted, the last ones stay open."""
    return finished(spark, stream.tumbling(events(spark, sf))).agg((F.count("*") > 0).alias("some"))


@query("stream_dedup", "SELECT count(DISTINCT event_id) AS n FROM events")
def stream_dedup(spark, sf):
    return finished(spark, stream.deduplicated(events(spark, sf)).select("event_id")).agg(F.count("*").alias("n"))


@query(
    "stream_join",
    """SELECT p.event_id AS purchase_id, c.event_id AS click_id, p.user_id FROM events p JOIN events c ON p.user_id = c.user_id AND p.event_type = 'purchase' AND c.event_type = 'click'
AND c.ts <= p.ts AND c.ts >= p.ts - INTERVAL 6 HOURS""",
)
def stream_join(spark, sf):
    return finished(spark, stream.clicks_before_purchases(events(spark, sf), "6 HOURS"))


@query("stream_template", "SELECT (date_part('hour', ts) // 2) AS j, count(*) AS n FROM events GROUP BY 1")
def stream_template(spark, sf):
    template = spark.createDataFrame([(j, float(j)) for j in range(12)], "j int, mid double")
    return finished(spark, stream.with_template(events(spark, sf), template, 24.0, 12).select("j")).groupBy("j").agg(F.count("*").alias("n"))


@query("stream_online_phase")
def stream_online_phase(spark, sf):
    """The planted series as it arrives, against a frozen template of one season."""
    path = f"{storage.shared_dir(spark).rstrip('/')}/_cyclefold_{uuid.uuid4().hex}"
    s = planted_series(spark, sf).select(F.lit("events").alias("series_id"), F.col("t").cast("long").alias("t"), "v")
    s.repartition(1, "series_id").sortWithinPartitions("t").write.parquet(path)  # one file: its rows arrive in order
    arriving = spark.readStream.schema("series_id string, t long, v double").parquet(path)
    wave = lambda t: 4.0 * np.sin(2 * np.pi * t / 12) + 1.5 * np.sin(4 * np.pi * t / 12)
    windows = np.stack([wave(np.arange(12) + k) for k in range(12)])
    return finished(spark, stream.online_phase(arriving, windows, 2 * np.pi * np.arange(12) / 12, 2.0)).select("i", "phi", "deviation", "alert")


@query("sql_theta_grid", f"SELECT j, round({TAU} * j / {M}, 6) + 0.0 AS theta FROM (SELECT unnest(range({M})) AS j)")
def sql_theta_grid(spark, sf):
    sql.register(spark)
    return spark.sql(f"SELECT j, theta FROM theta_grid({M})")


@query("sql_ideal_laplacian", f"WITH {IDEAL} SELECT i, j, val::DOUBLE AS val FROM lap")
def sql_ideal_laplacian(spark, sf):
    sql.register(spark)
    return spark.sql(f"SELECT i, j, val FROM ideal_laplacian({K}, {T})")


@query("sql_sliding_windows", f"WITH {SERIES} SELECT a.t AS i, g.k, round(b.v, 9) + 0.0 AS v FROM s0 a, (SELECT unnest(range(13)) AS k) g JOIN s0 b ON b.t = a.t + g.k WHERE a.t <= 347", digits=9)
def sql_sliding_windows(spark, sf):
    sql.register(spark)
    buckets(spark, sf).select(F.lit("e").alias("series_id"), "t", "v").createOrReplaceTempView("_cyclefold_series")
    return spark.sql("SELECT i, w FROM sliding_windows(TABLE(_cyclefold_series), 13)").select("i", F.posexplode("w").alias("k", "v"))


@query("sql_fold", f"SELECT j, round({TAU} * j / {M}, 6) + 0.0 AS theta, true AS voted FROM (SELECT unnest(range({M})) AS j)")
def sql_fold(spark, sf):
    sql.register(spark)
    planted_series(spark, sf).select(F.lit("e").alias("series_id"), "t", "v").createOrReplaceTempView("_cyclefold_wave")
    return spark.sql(f"SELECT j, theta, v IS NOT NULL AND n_votes > 0 AS voted FROM fold(TABLE(_cyclefold_wave), {M}, 0.5D)")


@query("sql_vector_functions", "SELECT label, count(*) AS n FROM embeddings GROUP BY label")
def sql_vector_functions(spark, sf):
    """Element-wise medians by label through the SQL function; each has the length of the vectors."""
    sql.register(spark)
    e = table(spark, sf, "embeddings").withColumn("v", F.col("embedding").cast("array<double>"))
    e.createOrReplaceTempView("_cyclefold_vectors")
    counts = e.groupBy("label").agg(F.count("*").alias("n"))
    middle = spark.sql("SELECT label, size(vec_median(v)) AS width FROM _cyclefold_vectors GROUP BY label")
    return counts.join(middle.filter("width = 64"), "label").select("label", "n")


@query("source_planted", "SELECT 2 AS videos, 240 AS n, 0.0::DOUBLE AS start")
def source_planted(spark, sf):
    planted.register(spark)
    f = spark.read.format("planted").option("scene", 1).option("frames", 120).option("cycles", 6).option("height", 8).option("width", 8).option("videos", 2).load()
    return f.agg(F.count_distinct("video_id").alias("videos"), F.count("*").alias("n"), F.min("phi").alias("start"))


@query("tile_layout", "SELECT p // 16 AS tile, count(DISTINCT t) AS n FROM (SELECT vec_id AS t, unnest(range(64)) AS p FROM embeddings) GROUP BY 1")
def tile_layout(spark, sf):
    """Tiles written partitioned by tile and read back."""
    from ..sources.layout import write_tiles

    path = f"{storage.shared_dir(spark).rstrip('/')}/_cyclefold_{uuid.uuid4().hex}"
    write_tiles(frames.tiles(frames.from_table(table(spark, sf, "embeddings"), None, "vec_id", "embedding", (8, 8, 1)), 16), path)
    return spark.read.parquet(path).groupBy(F.col("tile").cast("long").alias("tile")).agg(F.count("*").alias("n"))
