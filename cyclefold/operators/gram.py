"""Pairwise distances and what follows from them: Gram matrices, projections, sketches."""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import kernels
from .frames import tiles

MATRIX = "video_id string, n int, d2 array<double>"


def distance_matrices(frames: DataFrame, tile_px: int | None = None) -> DataFrame:
    """video_id, n, d2 (packed rows): all squared distances of each video's frames.

    Without ``tile_px`` a video is a group, at one exchange. With it, for huge frames, a tile's
    partial matrix is made where the tile is, as squared distances are sums over tiles, and
    partial matrices are summed element by element: a video's pixels never meet in one task.
    """

    def partial(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("t")
        d2 = kernels.squared_distances(np.stack(pdf["px"].to_numpy()))
        return pd.DataFrame({"video_id": [pdf["video_id"].iloc[0]], "n": [len(pdf)], "d2": [d2.ravel()]})

    if tile_px is None:
        return frames.select("video_id", "t", "px").groupBy("video_id").applyInPandas(partial, MATRIX)
    parts = tiles(frames, tile_px).groupBy("video_id", "tile").applyInPandas(partial, MATRIX)
    return summed(parts)


def summed(parts: DataFrame) -> DataFrame:
    """Element-wise sums of packed matrices by video, combined before their shuffle."""
    rows = parts.select("video_id", "n", F.posexplode("d2").alias("p", "v")).groupBy("video_id", "n", "p").agg(F.sum("v").alias("v"))
    return rows.groupBy("video_id", "n").agg(F.transform(F.array_sort(F.collect_list(F.struct("p", "v"))), lambda r: r["v"]).alias("d2"))


def pairs(matrices: DataFrame) -> DataFrame:
    """video_id, i, j, d2 for i < j from packed matrices."""
    long = matrices.select("video_id", "n", F.posexplode("d2").alias("p", "d2"))
    return long.select("video_id", F.floor(F.col("p") / F.col("n")).cast("int").alias("i"), F.pmod("p", "n").cast("int").alias("j"), "d2").filter("i < j")


#: Frames of a recording whose distances to as many others are a matrix at a time.
BLOCK = 512
#: Numbers of one region of frames that a task holds.
HELD = 2**24


#: Rows of two regions that wait to be gathered.
GATHERED = 2**20

Found = Callable[[dict[str, np.ndarray]], dict[str, np.ndarray]]


def in_blocks(frames: DataFrame, finish: Callable[..., dict[str, np.ndarray]], schema: str, ahead: int = 0, tile_px: int | None = None, apart: bool = False, beside: DataFrame | None = None, gather: Found | None = None) -> DataFrame:
    """video_id and what ``finish(i, j, d2)`` gives for every two blocks of frames, each block with itself too.

    ``frames`` has dense t. The blocks have ``BLOCK`` frames and the first ``ahead`` of the next, i and j are
    their times, d2 their squared distances. With ``apart``, ``frames`` has tiles already, and d2 is a list of their
    squared distances. With ``beside`` (video_id, t, side), ``finish`` also gets the sides of the frames i and j. With
    ``gather``, what comes of two regions is made less by it, again and again, before it leaves the task.

    Runs of blocks are regions, and a task has two of them: a frame is sent once for each region, and their number
    grows with the cores, not with the recording. Where a region of frames would be more than ``HELD`` numbers it is
    fewer blocks; where it is one, tiles are summed as they come, so that the pixels of huge frames never meet.
    """
    spark = frames.sparkSession
    regions = math.ceil(4 * math.sqrt(spark.sparkContext.defaultParallelism))
    of = F.when(F.col("t") >= 0, F.col("video_id")).alias("of")  # no constant, so that one recording too is an equi-join
    wide = F.greatest(F.least(F.ceil((F.max("t") + 1) / (BLOCK * regions)), F.floor(HELD / (BLOCK * F.greatest(F.max(F.size("px")), F.lit(1))))), F.lit(1)) * BLOCK
    sizes = frames.groupBy(of).agg(F.max("t").alias("end"), wide.cast("long").alias("wide")).withColumn("last", F.floor(F.col("end") / F.col("wide")))
    first = F.greatest(F.ceil((F.col("t") - F.col("wide") - ahead + 1) / F.col("wide")), F.lit(0))
    px = frames if apart else tiles(frames, tile_px) if tile_px else frames.select("video_id", "t", F.lit(0).alias("tile"), "px")
    px = px.withColumn("side", F.lit(0.0)) if beside is None else px.join(beside, ["video_id", "t"])
    own = px.withColumn("of", of).join(F.broadcast(sizes), "of").withColumn("region", F.explode(F.sequence(first, F.floor(F.col("t") / F.col("wide")))))
    both = own.withColumn("partner", F.explode(F.sequence(F.lit(0).cast("long"), F.col("last"))))
    keys = ["video_id", "low", "high"]
    dealt = both.select("video_id", F.least("region", "partner").alias("low"), F.greatest("region", "partner").alias("high"), "wide", "tile", "region", "t", "side", "px")
    names = [c.split()[0] for c in schema.split(", ")]
    alone = beside is None

    def blocks(key, region, t):
        """Places of the frames of each block of a region."""
        own = np.flatnonzero(region == key[0])
        starts = np.arange(key[0] * key[1], t[own].max() + 1 if len(own) else 0, BLOCK)[: key[1] // BLOCK]
        for a, b in zip(*(np.searchsorted(t[own], x) for x in (starts, starts + BLOCK + ahead)), strict=True):
            if a < b:
                yield own[a:b]

    def matrices(key, held):
        """(key, places, d2) of each two blocks from the tiles of two regions, (region, t, side, pixels) each."""
        region, t = held[0][:2]
        two = [list(blocks((r, key[3]), region, t)) for r in (key[1], key[2])]
        for n, a in enumerate(two[0]):
            for b in two[1][n if key[1] == key[2] else 0 :]:
                d2 = [kernels.squared_differences(x[a], x[b]) for *_, x in held]
                yield a, b, d2 if apart else sum(d2[1:], d2[0])

    def summed_tiles(tables):
        """What ``finish`` makes of each two blocks, from tables of one tile each."""
        key, held, total = None, [], None

        def out():
            region, t, aside = held[0][:3]
            for a, b, d2 in matrices(key, held) if total is None else total:
                yield key, finish(t[a], t[b], d2) if alone else finish(t[a], t[b], d2, aside[a], aside[b])

        for now, *table in tables:
            if now != key:
                if key is not None:
                    yield from out()
                key, held, total = now, [], None
            held.append(table)
            if now[3] == BLOCK and not apart:
                more = list(matrices(now, [table]))
                if total is None:
                    total = more
                else:
                    for (*_, d2), (*_, far) in zip(total, more, strict=True):
                        d2 += far
                held = [[*held[0][:3], None]]
        if key is not None:
            yield from out()

    def one_tile(batches):
        """((video, low, high, frames of a region), region, t, side, pixels) of each run of rows of one tile."""
        held, at = [], None

        def out():
            return at[:4], *(np.concatenate([h[k] for h in held]) for k in range(4))

        for batch in batches:
            video = batch.column(0).to_pylist()
            low, high, wide, tile, region, t, aside = (batch.column(k).to_numpy(zero_copy_only=False) for k in range(1, 8))
            change = (low[1:] != low[:-1]) | (high[1:] != high[:-1]) | (tile[1:] != tile[:-1]) | np.array([x != y for x, y in zip(video[1:], video[:-1], strict=True)], bool)
            cuts = np.flatnonzero(np.r_[True, change, True]) if len(t) else np.zeros(0, int)
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                now = (video[a], int(low[a]), int(high[a]), int(wide[a]), int(tile[a]))
                if held and now != at:
                    yield out()
                    held = []
                flat = batch.column(8).slice(a, b - a).flatten().to_numpy(zero_copy_only=False)
                held.append((region[a:b], t[a:b], aside[a:b], flat.reshape(b - a, -1)))
                at = now
        if held:
            yield out()

    def gathered(pieces):
        """The same of two regions as one piece each."""
        key, held, most = None, [], GATHERED
        less = lambda: gather({c: np.concatenate([x[c] for x in held]) for c in names})
        for now, found in pieces:
            if now != key:
                if held:
                    yield key, less()
                key, held, most = now, [], GATHERED
            held.append(found)
            if sum(len(x[names[0]]) for x in held) > most:
                held = [less()]
                most = max(GATHERED, 2 * len(held[0][names[0]]))
        if held:
            yield key, less()

    def run(batches):
        pieces = summed_tiles(one_tile(batches))
        for key, found in gathered(pieces) if gather else pieces:
            size = len(next(iter(found.values())))
            if size:
                columns = {"video_id": pa.repeat(pa.scalar(key[0], pa.string()), size), **{c: pa.array(found[c]) for c in names}}
                yield pa.RecordBatch.from_pydict(columns)

    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), regions * (regions + 1) // 2)
    return dealt.repartition(parts, *keys).sortWithinPartitions(*keys, "tile", "region", "t").mapInArrow(run, f"video_id string, {schema}")


def _upper(i: np.ndarray, j: np.ndarray, d2: np.ndarray) -> dict[str, np.ndarray]:
    if len(i) and len(j) and i[-1] < j[0]:
        return {"i": np.repeat(i, len(j)), "j": np.tile(j, len(i)), "d2": d2.ravel()}
    a, b = np.nonzero(i[:, None] < j[None])
    return {"i": i[a], "j": j[b], "d2": d2[a, b]}


def pair_distances(frames: DataFrame, tile_px: int | None = None) -> DataFrame:
    """video_id, i, j, d2 for i < j, block by block; t is dense."""
    return in_blocks(frames, _upper, "i int, j int, d2 double", 0, tile_px)


def row_sums(frames: DataFrame, value: Callable[[np.ndarray], np.ndarray] = lambda d2: d2) -> DataFrame:
    """video_id, i, s: sums of a function of each frame's squared distances to all others."""

    def finish(i, j, d2):
        v = np.where(i[:, None] == j[None], 0.0, value(d2))
        if i[0] == j[0]:
            return {"i": i, "s": v.sum(axis=1)}
        return {"i": np.concatenate([i, j]), "s": np.concatenate([v.sum(axis=1), v.sum(axis=0)])}

    return in_blocks(frames, finish, "i int, s double").groupBy("video_id", "i").agg(F.sum("s").alias("s"))


def centred_of_frames(frames: DataFrame) -> DataFrame:
    """``centred`` from frames: row means in a first pass over the blocks, entries in a second."""

    def finish(i, j, d2, m_i, m_j):
        g = -0.5 * (d2 - m_i[:, None] - m_j[None])
        if i[-1] < j[0]:
            return {"i": np.repeat(i, len(j)), "j": np.tile(j, len(i)), "g": g.ravel()}
        a, b = np.nonzero(i[:, None] <= j[None])
        return {"i": i[a], "j": j[b], "g": g[a, b]}

    whole = Window.partitionBy("video_id")
    mean = row_sums(frames).withColumn("m", F.col("s") / F.count("*").over(whole)).withColumn("side", F.col("m") - F.avg("m").over(whole) / 2)
    return in_blocks(frames, finish, "i int, j int, g double", beside=mean.select("video_id", F.col("i").alias("t"), "side"))


def _window_pairs(i: np.ndarray, j: np.ndarray, d2: np.ndarray, d: int) -> dict[str, np.ndarray]:
    """i < j and d2 of windows of d frames, by running sums along the diagonals of two blocks."""
    n, m = len(i) - d + 1, len(j) - d + 1
    if n < 1 or m < 1:
        return _upper(i[:0], j[:0], d2[:0, :0])
    total = np.zeros((len(i) + 1, len(j) + 1))
    for k in range(len(i)):
        total[k + 1, 1:] = total[k, :-1] + d2[k]
    return _upper(i[:n], j[:m], np.maximum(total[d:, d:] - total[:-d, :-d], 0))


def window_pair_distances(frames: DataFrame, d: int) -> DataFrame:
    """video_id, i, j, d2 for i < j of windows of d frames, block by block."""
    return in_blocks(frames, lambda i, j, d2: _window_pairs(i, j, d2, d), "i int, j int, d2 double", d - 1)


#: Values that the driver counts one by one.
COUNTED = 2**22


def _counts(code: np.ndarray) -> dict[str, np.ndarray]:
    """How often each code is there."""
    least = code.min() if len(code) else 0
    if len(code) and code.max() - least < 4 * len(code):
        n = np.bincount(code - least)
        at = np.flatnonzero(n)
        return {"code": at + least, "n": n[at]}
    code, n = np.unique(code, return_counts=True)
    return {"code": code, "n": n}


def window_quantile(frames: DataFrame, d: int, q: float) -> float | None:
    """The quantile of the squared distances of all pairs of windows, between two values in proportion; exact.

    Doubles of at least zero are ordered as their bits are. A pass over the blocks counts the leading bits; the next
    look only at those that hold the two values, until these are whole. Counts come to the driver, never pairs.
    """
    wanted, low, places, shift = None, None, None, 38

    def gather(found):
        code, at = np.unique(found["code"], return_inverse=True)
        return {"code": code, "n": np.bincount(at, found["n"], len(code)).astype(np.int64)}

    while True:

        def finish(i, j, d2, wanted=wanted, low=low, shift=shift):
            bits = (_window_pairs(i, j, d2, d)["d2"] + 0.0).view(np.int64)
            if wanted is not None:
                bits = bits[np.isin(bits >> low, wanted)]
            return _counts(bits >> shift)

        counts = in_blocks(frames, finish, "code bigint, n bigint", d - 1, gather=gather).groupBy("code").agg(F.sum("n").alias("n")).toArrow()
        code, n = (counts.column(c).to_numpy() for c in ("code", "n"))
        if not len(code):
            return None
        order = np.argsort(code)
        code, n = code[order], n[order]
        if places is None:
            at = q * (n.sum() - 1)
            fraction = at - np.floor(at)
            places = [(None, int(np.floor(at))), (None, int(np.ceil(at)))]
        found = []
        for prefix, rank in places:
            inside = np.ones(len(code), bool) if prefix is None else code >> (low - shift) == prefix
            sums = np.cumsum(n[inside])
            k = int(np.searchsorted(sums, rank, side="right"))
            found.append((int(code[inside][k]), rank - int(sums[k] - n[inside][k])))
        places, wanted, low = found, np.unique([c for c, _ in found]), shift
        if shift == 0:
            lower, upper = np.array([c for c, _ in found], np.int64).view(np.float64)
            return float(lower + (upper - lower) * fraction)
        shift = 0 if n[np.isin(code, wanted)].sum() <= COUNTED else max(shift - 20, 0)


def spanning_edges(frames: DataFrame) -> DataFrame:
    """video_id, i, j, d2: the edges of a minimal spanning tree, ties to the earlier frames.

    Each two blocks of frames leave the forest of their own pairs, which has every edge of the tree between them;
    groups of 16 by 16 blocks leave theirs, at most 16 edges a frame of a group, and the tree is made of these.
    """
    schema = "video_id string, i int, j int, d2 double"

    def finish(i, j, d2):
        found = _upper(i, j, d2)
        kept = kernels.spanning_edges(found["i"], found["j"], found["d2"])
        return {c: v[kept] for c, v in found.items()}

    def merged(pdf: pd.DataFrame) -> pd.DataFrame:
        return pdf.iloc[kernels.spanning_edges(*(pdf[c].to_numpy() for c in ("i", "j", "d2")))][["video_id", "i", "j", "d2"]]

    near = in_blocks(frames, finish, "i int, j int, d2 double")
    group = lambda c: F.floor(F.col(c) / (16 * BLOCK))
    forests = near.groupBy("video_id", group("i").alias("low"), group("j").alias("high")).applyInPandas(merged, schema)
    return forests.groupBy("video_id").applyInPandas(merged, schema)


def nearest_frames(frames: DataFrame, k: int = 8) -> DataFrame:
    """``nearest`` from frames: each two blocks, and then each two regions, leave the k nearest of their frames only."""

    def finish(i, j, d2):
        sides = [(i, j, d2)] if i[0] == j[0] else [(i, j, d2), (j, i, d2.T)]
        found = {"i": [], "j": [], "d2": []}
        for own, other, far in sides:
            far = np.where(own[:, None] == other[None], np.inf, far)
            most = np.partition(far, k - 1, axis=1)[:, k - 1 : k] if k < len(other) else np.inf
            a, b = np.nonzero((far <= most) & np.isfinite(far))
            found["i"].append(own[a])
            found["j"].append(other[b])
            found["d2"].append(far[a, b])
        return gather({c: np.concatenate(v) for c, v in found.items()})

    def gather(found):
        order = np.lexsort((found["j"], found["d2"], found["i"]))
        i = found["i"][order]
        order = order[np.arange(len(i)) - np.searchsorted(i, i) < k]
        return {c: v[order] for c, v in found.items()}

    rank = F.row_number().over(Window.partitionBy("video_id", "i").orderBy("d2", "j"))
    return in_blocks(frames, finish, "i int, j int, d2 double", gather=gather).withColumn("rnk", rank).filter(F.col("rnk") <= k)


def pair_distances_relational(frames: DataFrame) -> DataFrame:
    """The same as a theta self-join in expressions; for checks, as it moves every frame to every other."""
    from ..functions.angles import squared_distance

    a, b = frames.select("video_id", F.col("t").alias("i"), F.col("px").alias("p")), frames.select("video_id", F.col("t").alias("j"), F.col("px").alias("q"))
    return a.join(b, ["video_id"]).filter("i < j").select("video_id", "i", "j", squared_distance(F.col("p"), F.col("q")).alias("d2"))


def centred(matrices: DataFrame) -> DataFrame:
    """video_id, i, j, g for i <= j: the double-centred Gram entries of the distances."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        n = int(pdf["n"].iloc[0])
        d2 = np.asarray(pdf["d2"].iloc[0]).reshape(n, n)
        g = -0.5 * (d2 - d2.mean(0) - d2.mean(1)[:, None] + d2.mean())
        i, j = np.triu_indices(n)
        return pd.DataFrame({"video_id": pdf["video_id"].iloc[0], "i": i.astype("int32"), "j": j.astype("int32"), "g": g[i, j]})

    return matrices.groupBy("video_id").applyInPandas(run, "video_id string, i int, j int, g double")


def isometric(frames: DataFrame, rank: int | None = None) -> DataFrame:
    """video_id, t, z: coordinates in at most N-1 dimensions with the frames' distances.

    Videos of no more frames than pixels are groups, and their axes come from the frames' products. Of longer ones
    the pixels' products are summed where the frames are; their axes come to the driver, at most a number for each
    two pixels of a video.
    """
    schema = "video_id string, t int, z array<double>"

    def short(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("t")
        z = kernels.isometric_projection(np.stack(pdf["px"].to_numpy()), rank)
        return pd.DataFrame({"video_id": pdf["video_id"], "t": pdf["t"], "z": list(z)})

    def products(batches):
        for pdf in batches:
            for video, rows in pdf.groupby("video_id"):
                x = np.stack(rows["px"].to_numpy()).astype(np.float64)
                mean = x.mean(axis=0)
                yield pd.DataFrame({"video_id": [video], "n": [len(x)], "mean": [mean], "s": [((x - mean).T @ (x - mean)).ravel()]})

    def axes(pdf: pd.DataFrame) -> pd.DataFrame:
        n, means = pdf["n"].to_numpy(), np.stack(pdf["mean"].to_numpy())
        mean = n @ means / n.sum()
        apart = (means - mean) * np.sqrt(n)[:, None]
        values, vectors = np.linalg.eigh(sum(s for s in pdf["s"]).reshape(len(mean), -1) + apart.T @ apart)
        keep = min(n.sum() - 1, len(mean)) if rank is None else rank
        return pd.DataFrame({"video_id": [pdf["video_id"].iloc[0]], "mean": [mean], "v": [vectors[:, np.argsort(values)[::-1][:keep]].ravel()]})

    per = frames.groupBy("video_id").agg((F.count("*") > F.max(F.size("px"))).alias("long"))
    both = frames.join(F.broadcast(per), "video_id")
    px = both.filter("long").select("video_id", "t", "px")
    sums = px.mapInPandas(products, "video_id string, n long, mean array<double>, s array<double>")
    found = {r.video_id: (np.array(r["mean"]), np.array(r.v).reshape(len(r["mean"]), -1)) for r in sums.groupBy("video_id").applyInPandas(axes, "video_id string, mean array<double>, v array<double>").collect()}

    def project(batches):
        for pdf in batches:
            for video, rows in pdf.groupby("video_id"):
                mean, v = found[video]
                yield pd.DataFrame({"video_id": video, "t": rows["t"], "z": list((np.stack(rows["px"].to_numpy()) - mean) @ v)})

    grouped = both.filter("not long").select("video_id", "t", "px").groupBy("video_id").applyInPandas(short, schema)
    return px.mapInPandas(project, schema).union(grouped)


def distance_error(frames: DataFrame, z: DataFrame) -> DataFrame:
    """video_id, err: the largest relative error of a squared distance between coordinates z; where frames are equal, the error itself."""

    def finish(i, j, d2):
        a, b = np.nonzero(i[:, None] < j[None])
        true, found = (m[a, b] for m in d2)
        far = np.abs(found - true)
        return {"err": np.divide(far, true, out=far, where=true > 0).max(keepdims=True) if len(a) else far}

    tile = lambda df, k, c: df.select("video_id", "t", F.lit(k).alias("tile"), F.col(c).cast("array<double>").alias("px"))
    return in_blocks(tile(frames, 0, "px").union(tile(z, 1, "z")), finish, "err double", apart=True).groupBy("video_id").agg(F.max("err").alias("err"))


def sketch(pixels: DataFrame, q: int, seed: int = 42) -> DataFrame:
    """video_id, t, z: each pixel is added with a hashed sign to one of q coordinates.

    Distances are kept in expectation; the sum combines before its shuffle.
    """
    key = [F.lit(seed), F.col("y"), F.col("x"), F.col("ch")]
    digest = F.md5(F.concat_ws("|", *(k.cast("string") for k in key)))
    number = F.conv(F.substring(digest, 1, 8), 16, 10).cast("long")
    signed = F.when(F.conv(F.substring(digest, 9, 1), 16, 10).cast("int") < 8, F.col("val")).otherwise(-F.col("val"))
    cells = pixels.groupBy("video_id", "t", F.pmod(number, F.lit(q)).cast("int").alias("k")).agg(F.sum(signed).alias("v"))
    have = F.map_from_entries(F.collect_list(F.struct("k", "v")))
    return cells.groupBy("video_id", "t").agg(F.transform(F.sequence(F.lit(0), F.lit(q - 1)), lambda k: F.lit(0.0)).alias("zero"), have.alias("m")).select(
        "video_id", "t", F.transform("zero", lambda z, k: F.coalesce(F.col("m")[k], z)).alias("z")
    )


def nearest(pair: DataFrame, k: int = 8) -> DataFrame:
    """video_id, i, j, rnk, d2: the k nearest of each frame, ties by index."""
    both = pair.select("video_id", "i", "j", "d2").union(pair.select("video_id", F.col("j").alias("i"), F.col("i").alias("j"), "d2"))
    rank = F.row_number().over(Window.partitionBy("video_id", "i").orderBy("d2", "j"))
    return both.withColumn("rnk", rank).filter(F.col("rnk") <= k)
