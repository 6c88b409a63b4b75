"""Connected components of an edge table, by alternating star contractions in DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common


def _towards_least(edges: DataFrame, larger_only: bool) -> DataFrame:
    """Link each node's neighbours to the least node next to it (itself included).

    The neighbours are never gathered: their minimum is an aggregate that combines before
    its shuffle and is joined back, so a hub with any number of edges is split like any
    skewed join.
    """
    if larger_only:
        both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    else:
        both = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    least = both.groupBy(F.col("u").alias("w")).agg(F.least(F.min("v"), F.first("u")).alias("m"))
    joined = both.join(least, both.u == least.w)
    moved = joined.filter("v > u") if larger_only else joined.filter("v > m")
    out = moved.select(F.col("v").alias("u"), F.col("m").alias("v"))
    if not larger_only:
        out = out.union(least.filter("w > m").select(F.col("w").alias("u"), F.col("m").alias("v")))
    return out.filter("u <> v").distinct()


def of_edges(edges: DataFrame, known: DataFrame | None = None, rounds: int = 100) -> DataFrame:
    """node, root for every node of ``edges`` (u, v) that is not the least of its component.

    ``known`` is such a result for other edges, which these join. Each round is written to the
    shared folder; it ends when a round changes nothing.
    """
    if known is not None:
        edges = common.materialise(edges)
        if edges.isEmpty():
            return known
        edges = edges.select("u", "v").unionByName(known.select(F.col("root").alias("u"), F.col("node").alias("v")))
    now = common.materialise(edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).filter("u <> v").distinct())
    seen = None
    for _ in range(rounds):
        mark = now.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if mark == seen or not mark[0]:
            return now.select(F.col("u").alias("node"), F.col("v").alias("root"))
        seen = mark
        half = common.materialise(_towards_least(now, True))
        common.forget(now)
        now = common.materialise(_towards_least(half, False))
        common.forget(half)
    raise RuntimeError(f"components did not settle in {rounds} rounds")


def one_of_each(docs: DataFrame, groups: DataFrame) -> DataFrame:
    """The rows of ``docs`` that stay if of each group (doc_id, component_id) the smallest doc_id stays.

    Rows that repeat a doc_id count as one document and leave one row, that of the least text by
    its hash. Rows without a doc_id cannot be named and all stay. What goes is the smaller list, so
    it is what is joined, and only repeated rows are regrouped.
    """
    per_id = groups.dropna(subset=["doc_id"]).groupBy("doc_id").agg(F.max(F.col("doc_id") == F.col("component_id")).alias("stays"), F.count("*").alias("rows"))
    per_id = common.materialise(per_id.filter("not stays or rows > 1"))
    single = docs.join(per_id.select("doc_id"), "doc_id", "left_anti")
    again = docs.join(per_id.filter("stays").select("doc_id"), "doc_id", "left_semi")
    row, order = F.struct(*again.columns), F.struct(F.xxhash64("text"), F.col("text"))
    again = again.groupBy("doc_id").agg(F.min_by(row, order).alias("row")).select("row.*")
    return single.unionByName(again).select(*docs.columns)
