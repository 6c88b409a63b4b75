"""SimHash near-duplicates found with BK-trees.

Method. A text's fingerprint is the bitwise majority of the 64-bit hashes of its 3-word
shingles. Fingerprints that differ in at most ``radius`` bits are linked; documents are
grouped by the connected components of these links.

The links come from BK-trees: a node's children are keyed by their integer Hamming distance
to it, and a search with radius r at distance d from a node follows only the edges
d-r .. d+r. One tree over all fingerprints would grow with the corpus and could not be
broadcast, so the trees are sharded: the 64 bits are cut into blocks, and two fingerprints
within the radius agree on at least ``blocks - radius`` whole blocks. Each fingerprint goes
to one shard per choice of that many blocks; every link therefore lies inside some shard,
and each shard's tree is built and searched in the task that holds it (no broadcast).
``blocks`` rises with the number of fingerprints so that a shard of unrelated
fingerprints stays small; every choice finds every link.

Defined results: null text = empty text; a text without words has fingerprint zero and is
linked like any other; a text of one or two words has one shingle, the whole sequence;
equal texts have equal fingerprints, so copies cost one tree node whatever their number;
a component's id is its smallest doc_id, null only if all its doc_ids are null; an empty
table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common, components

RADIUS = 3
SHINGLE = 3
SEED = 42
BLOCK_WORDS = 1 << 16


def fingerprint(text: str | None) -> int:
    """64-bit SimHash of the text; zero if it has no word."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    if len(words) < SHINGLE:
        words = [b" ".join(words), b"", b""]
        shingles = 1
    else:
        shingles = len(words) - SHINGLE + 1
    ones = np.zeros(64, np.int64)
    digest = xxhash.xxh64_intdigest
    for at in range(0, shingles, BLOCK_WORDS):
        end = min(shingles, at + BLOCK_WORDS)
        if words[-1] == b"":
            hashed = [digest(words[0], SEED)]
        else:
            hashed = [
                digest(b"%b %b %b" % t, SEED)
                for t in zip(words[at:end], words[at + 1 : end + 1], words[at + 2 : end + 2], strict=True)
            ]
        raw = np.array(hashed, dtype="<u8").view(np.uint8).reshape(-1, 8)
        ones += np.unpackbits(raw, axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    bits = (2 * ones > shingles).astype(np.uint8)
    return int(np.packbits(bits, bitorder="little").view("<u8")[0])


_FINGERPRINTS = pa.schema([("doc_id", pa.int64()), ("fp", pa.int64())])


def fingerprints(docs: DataFrame) -> DataFrame:
    """doc_id, fp (the fingerprint as a signed long)."""

    def make():
        return lambda doc_id, text: ((doc_id, v - (1 << 64) if (v := fingerprint(text)) >> 63 else v),)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(
        common.per_row(["doc_id", "text"], _FINGERPRINTS, make), "doc_id long, fp long"
    )


class Forest:
    """BK-trees over many shards at once, as arrays; level by level instead of node by node."""

    def __init__(self, shard: np.ndarray, fp: np.ndarray):
        """``shard`` is sorted; the first fingerprint of each shard is its root."""
        n = len(fp)
        self.fp, self.shard = fp, shard
        self.first_child = np.full(n, -1, np.int64)  # children of a node are contiguous in `order`
        self.n_children = np.zeros(n, np.int64)
        self.edge = np.zeros(n, np.int64)
        starts = np.flatnonzero(np.r_[True, shard[1:] != shard[:-1]]) if n else np.zeros(0, np.int64)
        lengths = np.diff(np.r_[starts, n])
        self.root = np.repeat(starts, lengths)
        kept: list[np.ndarray] = []
        placed = 0
        members, parent = np.arange(n), self.root.copy()
        mask = members != parent
        members, parent = members[mask], parent[mask]
        while len(members):
            distance = np.bitwise_count(fp[members] ^ fp[parent]).astype(np.int64)
            by = np.lexsort((members, distance, parent))
            members, parent, distance = members[by], parent[by], distance[by]
            head = np.r_[True, (parent[1:] != parent[:-1]) | (distance[1:] != distance[:-1])]
            group = np.cumsum(head) - 1
            child, of = members[head], parent[head]
            self.edge[child] = distance[head]
            new_parent = np.r_[True, of[1:] != of[:-1]]
            at = np.flatnonzero(new_parent)
            self.first_child[of[at]] = placed + at
            self.n_children[of[at]] = np.diff(np.r_[at, len(of)])
            kept.append(child)
            placed += len(child)
            parent = child[group]
            rest = ~head
            members, parent = members[rest], parent[rest]
        self.order = np.concatenate(kept) if kept else np.zeros(0, np.int64)

    def links(self, radius: int, chunk: int = 1 << 16) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Pairs (query, node) within the radius that suffice for the components.

        A subtree below an edge of at most ``radius`` lies wholly within the radius of its
        parent. Once a query is linked to that parent, the subtree is in its component and
        need not be searched: dense groups of near copies stay cheap and lose no component.
        """
        for at in range(0, len(self.fp), chunk):
            query = np.arange(at, min(at + chunk, len(self.fp)))
            node = self.root[query]
            mask = node != query
            query, node = query[mask], node[mask]
            while len(query):
                distance = np.bitwise_count(self.fp[query] ^ self.fp[node]).astype(np.int64)
                hit = distance <= radius
                if hit.any():
                    yield query[hit], node[hit]
                count = self.n_children[node]
                has = count > 0
                query, node, distance, hit, count = query[has], node[has], distance[has], hit[has], count[has]
                if not len(query):
                    break
                offset = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
                child = self.order[np.repeat(self.first_child[node], count) + offset]
                query, distance, hit = (np.repeat(x, count) for x in (query, distance, hit))
                edge = self.edge[child]
                follow = (np.abs(edge - distance) <= radius) & ~(hit & (edge <= radius)) & (child != query)
                query, node = query[follow], child[follow]


def _spanning(fp: np.ndarray, shard: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """For one run of whole shards: (fingerprint, smallest fingerprint of its group) where they differ."""
    forest = Forest(shard, fp)
    label = np.arange(len(fp))
    for a, b in forest.links(radius):
        while True:
            la, lb = label[a], label[b]
            low = np.minimum(la, lb)
            if (la == lb).all():
                break
            np.minimum.at(label, la, low)
            np.minimum.at(label, lb, low)
            while (label[label] != label).any():
                label = label[label]
    moved = label != np.arange(len(fp))
    return fp[moved], fp[label[moved]]


def shard_keys(fp, blocks: int, radius: int = RADIUS):
    """Column: one key per choice of ``blocks - radius`` blocks that two links must share."""
    edges = [64 * i // blocks for i in range(blocks + 1)]
    keys = []
    for k, chosen in enumerate(combinations(range(blocks), blocks - radius)):
        mask = sum(((1 << (edges[i + 1] - edges[i])) - 1) << edges[i] for i in chosen)
        signed = mask - (1 << 64) if mask >> 63 else mask
        keys.append(F.xxhash64(F.lit(k), fp.bitwiseAND(F.lit(signed).cast("long"))))
    return F.explode(F.array(*keys))


def blocks_for(n: int, radius: int = RADIUS) -> int:
    """Blocks so that unrelated fingerprints meet about once a shard: 4, 5 or 6 at radius 3."""
    for extra in (1, 2, 3):
        if n <= 1 << (64 * extra // (radius + extra)):
            return radius + extra
    return radius + 3


def links(distinct: DataFrame, n: int, radius: int = RADIUS) -> DataFrame:
    """u, v: enough links between distinct fingerprints (column fp) for their components.

    Shards meet by a hash of their key; two keys with equal hashes only share a tree, which
    adds comparisons and no false link, as every link is checked by its distance.
    """
    schema = pa.schema([("u", pa.int64()), ("v", pa.int64())])

    def search(batches):
        held_fp, held_shard = np.zeros(0, np.uint64), np.zeros(0, np.int64)

        def out(fp, shard):
            a, b = _spanning(fp, shard, radius)
            return pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], schema=schema)

        for batch in batches:
            fp = np.concatenate([held_fp, batch.column(0).to_numpy(zero_copy_only=False).view(np.uint64)])
            shard = np.concatenate([held_shard, batch.column(1).to_numpy(zero_copy_only=False)])
            if not len(fp):
                continue
            cut = int(np.searchsorted(shard, shard[-1]))  # the last shard may go on in the next batch
            if cut:
                yield out(fp[:cut], shard[:cut])
            held_fp, held_shard = fp[cut:], shard[cut:]
        if len(held_fp):
            yield out(held_fp, held_shard)

    return (
        distinct.select("fp", shard_keys(F.col("fp"), blocks_for(n, radius), radius).alias("shard"))
        .repartition("shard")
        .sortWithinPartitions("shard", "fp")
        .mapInArrow(search, "u long, v long")
    )


def groups(docs: DataFrame, radius: int = RADIUS) -> DataFrame:
    """doc_id, fp, component_id for every row of ``docs`` (columns doc_id, text)."""
    prints = common.materialise(fingerprints(docs))
    distinct = common.materialise(prints.groupBy("fp").agg(F.min("doc_id").alias("least")))
    found = components.of_edges(links(distinct.select("fp"), distinct.count(), radius))
    moved = (
        distinct.join(found, distinct.fp == found.node, "left")
        .select("fp", "least", F.coalesce("root", "fp").alias("root"))
    )
    named = moved.groupBy("root").agg(F.min("least").alias("component_id"))
    by_print = common.materialise(moved.join(named, "root").select("fp", "component_id"))
    return prints.join(by_print, "fp").select("doc_id", "fp", "component_id")


def deduplicate(docs: DataFrame, radius: int = RADIUS) -> DataFrame:
    """One row of each group stays, as ``components.one_of_each`` says; columns as given."""
    return components.one_of_each(docs, groups(docs, radius))


def op5_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return groups(common.table(spark, sf_dir, "documents")).select(
        "doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id"
    )
