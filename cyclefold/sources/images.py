"""Frames as portable grey and pixel maps: a decoder for image files and a sink for templates."""

from __future__ import annotations

import os
import re

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceWriter, WriterCommitMessage

_HEAD = re.compile(rb"P([56])\s(?:\s*#[^\n]*\n)*\s*(\d+)\s+(\d+)\s+(\d+)\s", re.S)


def encode(px: np.ndarray, h: int, w: int, ch: int) -> bytes:
    """Values in [0, 1] as one byte each."""
    if ch not in (1, 3):
        raise ValueError("a frame has one or three channels")
    data = np.clip(np.rint(np.nan_to_num(np.asarray(px, float)) * 255), 0, 255).astype(np.uint8)
    return b"P%d\n%d %d\n255\n" % (6 if ch == 3 else 5, w, h) + data.tobytes()


def decode(data: bytes) -> tuple[int, int, int, np.ndarray]:
    m = _HEAD.match(data)
    if not m:
        raise ValueError("not a binary grey or pixel map")
    w, h, most = (int(m[k]) for k in (2, 3, 4))
    ch = 3 if m[1] == b"6" else 1
    kind = np.dtype(">u2") if most > 255 else np.dtype(np.uint8)
    px = np.frombuffer(data, kind, h * w * ch, m.end()).astype(np.float32) / most
    return h, w, ch, px


def read(spark: SparkSession, path: str) -> DataFrame:
    """frames from files .../<video>/<t>.pgm or .ppm below ``path``; one image a row, Spark lists the files."""
    files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").option("pathGlobFilter", "*.p[gp]m").load(path)
    named = files.select(F.regexp_extract("path", r"([^/]+)/[^/]+$", 1).alias("video_id"), F.regexp_extract("path", r"(\d+)\.p[gp]m$", 1).cast("int").alias("t"), "content")

    def run(batches):
        for pdf in batches:
            rows = [decode(bytes(c)) for c in pdf["content"]]
            yield pd.DataFrame({"video_id": pdf["video_id"], "t": pdf["t"], "h": [r[0] for r in rows], "w": [r[1] for r in rows], "ch": [r[2] for r in rows], "px": [r[3] for r in rows]})

    return named.mapInPandas(run, "video_id string, t int, h int, w int, ch int, px array<float>")


class ImageSink(DataSource):
    """``df.write.format("framefiles").mode("append").save(path)``; the folder must be one that all executors share."""

    @classmethod
    def name(cls) -> str:
        return "framefiles"

    def writer(self, schema, overwrite: bool) -> DataSourceWriter:
        return ImageWriter(self.options["path"])


class ImageWriter(DataSourceWriter):
    def __init__(self, path: str):
        self.path = path.removeprefix("file:")

    def write(self, rows) -> WriterCommitMessage:
        for r in rows:
            if r.px is None:
                continue
            folder = os.path.join(self.path, str(r.video_id))
            os.makedirs(folder, exist_ok=True)
            name = os.path.join(folder, f"{r.t:06d}.{'ppm' if r.ch == 3 else 'pgm'}")
            with open(f"{name}.part", "wb") as f:
                f.write(encode(r.px, r.h, r.w, r.ch))
            os.replace(f"{name}.part", name)  # a task that runs again leaves the same file
        return WriterCommitMessage()


def write(frames: DataFrame, path: str) -> None:
    frames.sparkSession.dataSource.register(ImageSink)
    frames.select("video_id", "t", "h", "w", "ch", "px").write.format("framefiles").mode("append").save(path)


def template_frames(template: DataFrame, h: int, w: int, ch: int = 1) -> DataFrame:
    """Whole frames from a template's tiles, in order."""
    rows = F.array_sort(F.collect_list(F.struct("tile", "px")))
    whole = template.groupBy("video_id", "j").agg(F.flatten(F.transform(rows, lambda r: r["px"])).alias("px"))
    return whole.select("video_id", F.col("j").alias("t"), F.lit(h).alias("h"), F.lit(w).alias("w"), F.lit(ch).alias("ch"), "px")
