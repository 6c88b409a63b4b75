"""Near copies: texts whose sets of 5-word shingles have a Jaccard similarity of 0.8 or more.

Method. SimHash fingerprints of the shingle sets are linked by the sharded BK-trees of
``simhash`` and every link is checked on the whole sets: that joins what is nearly equal. A
similarity of 0.8 does not bound how many bits of two fingerprints differ (5 to 10 are common),
so no radius finds all pairs; an exact set join completes the links:

* all shingles are put in one global order. Two sets of similarity t or more share a shingle
  among the first n - ceil(t n) + 1 of each, so only texts that meet there can be linked. Any
  order is exact; shingles that are frequent in a sample of texts come last, so that a common
  line or passage seldom makes unrelated texts meet;
* groups are the connected components of the links, so that not every pair of a dense group has
  to be compared: in a few rounds all texts at a shingle are checked against one of them, another
  each round, and components are joined; then, as long as that still joins some, each text at a
  shingle is checked against the one of another component that its profile is nearest to, so a
  round checks no more pairs than there are meetings; at last the pairs that still lie apart are
  checked, all of them. A shingle of many texts is cut into blocks, so that no task holds them all;
* a passage of many shingles makes the same texts meet at each of them. Shingles of the same texts
  count as one, at the first of their places in each text; that keeps every pair;
* before sets are compared, their profiles are: a bit of one that the other lacks stands for a
  shingle that the other lacks; then, of the pairs left, how many shingles fall into each of many
  bins. That rules out most pairs, and never one of similarity t. Whole sets are made for the texts
  of a round's pairs only, and go with the round.

Every link is checked on the whole shingle sets. Shingles and texts are compared by 64-bit hashes.

Defined results: null text = empty text; texts without words are copies of each other; a text of
fewer than five words has one shingle, the whole sequence; letter case (of ASCII) and the kind of
white space do not count.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import common, components, simhash

SHINGLE = 5
SEED = 42
#: Texts whose shingles are counted for the order, and the frequent shingles that are kept.
SAMPLE, FREQUENT = 20_000, 50_000
#: Rounds in which the texts at a shingle are checked against one of them.
PIVOT_ROUNDS = 2
#: Most rounds in which each text at a shingle is checked against the nearest of another component.
NEAREST_ROUNDS = 6
#: Texts of one shingle that a task pairs with as many others.
BLOCK = 4096
#: A text's profile: so many words of 64 bits, with the bits of its shingles' hashes.
PROFILE = [f"b{k}" for k in range(8)]
#: Bins over which a text's shingles are counted, and the most that a bin counts; two bins share a byte.
BINS, MOST = 1024, 15
#: Pairs or keys (16 bytes each) up to which they are broadcast; beyond, both sides of a join are dealt out.
FEW = 1_000_000


def shingles(text: str | None) -> np.ndarray:
    """The distinct hashes of the text's shingles, sorted."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    digest = xxhash.xxh64_intdigest
    runs = [words[k:] for k in range(SHINGLE)] if len(words) >= SHINGLE else [[b" ".join(words)]]
    hashed = [digest(b" ".join(t), SEED) for t in zip(*runs, strict=False)]
    return np.unique(np.array(hashed, "<u8").view(np.int64))


def prefix_length(n: int) -> int:
    """So many first shingles of n that a set of similarity 0.8 must share one of them."""
    return n - (4 * n + 4) // 5 + 1


def ordered(found: np.ndarray, frequent: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """The shingles by their weight (zero if not frequent), then by themselves; ``frequent`` is sorted."""
    if not len(frequent):
        return found
    at = np.minimum(np.searchsorted(frequent, found), len(frequent) - 1)
    return found[np.lexsort((found, np.where(frequent[at] == found, weight[at], 0)))]


def frequent_shingles(texts: DataFrame, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Shingles that occur in more than two texts of a sample, sorted, and in how many."""
    schema = pa.schema([("token", pa.int64())])
    some = texts.filter(F.pmod("key", F.lit(max(1, n // SAMPLE))) == 0).dropDuplicates(["key"])
    tokens = some.mapInArrow(common.per_row(["text"], schema, lambda: lambda text: [(int(x),) for x in shingles(text)]), "token long")
    rows = tokens.groupBy("token").count().filter("count > 2").orderBy(F.desc("count"), "token").limit(FREQUENT).collect()
    rows.sort()
    return np.array([r[0] for r in rows], np.int64), np.array([r[1] for r in rows], np.int64)


def majority(found: np.ndarray) -> int:
    """SimHash of a set of shingle hashes, as a signed long."""
    bits = np.unpackbits(found.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * bits > len(found), bitorder="little").view("<i8")[0])


def profile(found: np.ndarray) -> list[int]:
    """The bits that the shingles' hashes set, as signed longs."""
    bits = np.zeros(64 * len(PROFILE), np.uint8)
    bits[found & (len(bits) - 1)] = 1
    return np.packbits(bits, bitorder="little").view("<i8").tolist()


def summaries(texts: DataFrame, n: int) -> DataFrame:
    """key, n, fp, profile, prefix: size, fingerprint, profile and first shingles of each text, in the global order."""
    frequent, weight = frequent_shingles(texts, n)
    schema = pa.schema([("key", pa.int64()), ("n", pa.int64()), ("fp", pa.int64()), *((b, pa.int64()) for b in PROFILE), ("prefix", pa.list_(pa.int64()))])

    def make():
        seen: set[int] = set()  # exact copies in one task are summarised once

        def one(key, text):
            if key in seen:
                return ()
            seen.add(key)
            found = shingles(text)
            return ((key, len(found), majority(found), *profile(found), ordered(found, frequent, weight)[: prefix_length(len(found))].tolist()),)

        return one

    out = f"key long, n long, fp long, {', '.join(f'{b} long' for b in PROFILE)}, prefix array<long>"
    return texts.mapInArrow(common.per_row(["key", "text"], schema, make), out)


def meetings(known: DataFrame) -> DataFrame:
    """token, key, n, at: where each text's first shingles are shared by another text's first ones.

    One exchange by shingle serves the removal of copies and the search for partners. A token stands for
    all shingles that the same texts share; ``at`` is the least of their places in the text, so what
    ``_may_link`` rules out there it rules out at each of them.
    """
    rows = known.select("key", "n", F.posexplode("prefix").alias("at", "token")).repartition("token")
    rows = rows.groupBy("token", "key").agg(F.first("n").alias("n"), F.first("at").cast("long").alias("at"))
    whole = Window.partitionBy("token")
    least, most = (f("key").over(whole) for f in (F.min, F.max))
    # equal hashes of different groups of texts would only make more texts meet
    same = F.xxhash64(F.count("*").over(whole), *(F.bit_xor(F.xxhash64("key", F.lit(k))).over(whole) for k in range(2)))
    rows = rows.withColumns({"_a": least, "_b": most, "_same": same}).filter("_a < _b").select(F.col("_same").alias("token"), "key", "n", "at")
    return rows.groupBy("token", "key").agg(F.first("n").alias("n"), F.min("at").alias("at"))


def _may_link(n, at, other_n, other_at):
    """Sets of these sizes whose first common shingle stands at these places can be similar enough.

    Works on columns and on arrays alike.
    """
    least, rest = (np.minimum, (n - at, other_n - other_at)) if isinstance(n, np.ndarray) else (F.least, (n - at, other_n - other_at))
    return 9 * least(*rest) >= 4 * (n + other_n)


def _missing(own, other):
    """How many bits of one profile the other lacks; on columns or on arrays (profile word, text)."""
    if isinstance(own, np.ndarray):
        return np.bitwise_count((own & ~other).view(np.uint64)).astype(np.int64).sum(axis=0)
    return sum((F.bit_count(F.col(a).bitwiseAND(F.bitwise_not(F.col(b)))) for a, b in zip(own, other, strict=True)), F.lit(0))


def bin_counts(found: np.ndarray) -> bytes:
    """How many shingles fall into each bin, up to ``MOST``; two bins a byte."""
    counts = np.minimum(np.bincount(found & (BINS - 1), minlength=BINS), MOST).astype(np.uint8)
    return (counts[::2] | counts[1::2] << 4).tobytes()


def counts_allow(n: int, of_n: bytes, m: int, of_m: bytes) -> bool:
    """Sets of n and m shingles with these counts can be similar: what a bin of one has more, the other lacks."""
    a, b = np.frombuffer(of_n, np.uint8), np.frombuffer(of_m, np.uint8)
    a, b = (np.concatenate([x & 15, x >> 4]).astype(np.int16) for x in (a, b))
    over = int(np.maximum(a - b, 0).sum()), int(np.maximum(b - a, 0).sum())
    return 9 * min(n - over[0], m - over[1]) >= 4 * (n + m)


def alike(pairs: DataFrame, texts: DataFrame) -> DataFrame:
    """The pairs (u, v) whose whole sets have a similarity of 0.8 or more; texts: key, text.

    Counts are compared before sets are moved to each other.
    """
    schema = pa.schema([("u", pa.int64()), ("v", pa.int64())])

    def can():
        return lambda u, v, n, m, of_u, of_v: ((u, v),) if counts_allow(n, of_u, m, of_v) else ()

    def make():
        def one(u, v, of_u, of_v):
            a, b = np.frombuffer(of_u, np.int64), np.frombuffer(of_v, np.int64)
            if len(a) > len(b):
                a, b = b, a
            both = int((b[np.minimum(np.searchsorted(b, a), len(b) - 1)] == a).sum())
            return ((u, v),) if 5 * both >= 4 * (len(a) + len(b) - both) else ()

        return one

    def beside(pairs, values):
        few = F.broadcast if pairs.count() <= FEW else lambda x: x
        of = lambda k: sets.select(F.col("key").alias(k), *(c.alias(f"{name}_{k}") for name, c in values.items())).join(few(pairs), k)
        return of("u").join(of("v"), ["u", "v"]).select("u", "v", *(f"{name}_{k}" for name in values for k in "uv"))

    pairs = common.materialise(pairs)
    keys = common.materialise(pairs.select(F.explode(F.array("u", "v")).alias("key")).distinct())
    few = F.broadcast if keys.count() <= FEW else lambda x: x
    sets = common.materialise(set_table(texts.join(few(keys), "key", "left_semi")).groupBy("key").agg(F.first("found").alias("found"), F.first("counts").alias("counts")))
    counted = beside(pairs, {"n": (F.octet_length("found") / 8).cast("long"), "counts": F.col("counts")})
    left = common.materialise(counted.mapInArrow(common.per_row(["u", "v", "n_u", "n_v", "counts_u", "counts_v"], schema, can), "u long, v long"))
    both = beside(left, {"of": F.col("found")})
    found = common.materialise(both.mapInArrow(common.per_row(["u", "v", "of_u", "of_v"], schema, make), "u long, v long"))
    for done in (pairs, keys, sets, left):
        common.forget(done)
    return found


def set_table(texts: DataFrame) -> DataFrame:
    """key, found, counts: the sorted shingle hashes of each text as bytes, and how many fall into each bin."""
    schema = pa.schema([("key", pa.int64()), ("found", pa.binary()), ("counts", pa.binary())])

    def make():
        seen: set[int] = set()  # exact copies in one task are hashed once

        def one(key, text):
            if key in seen:
                return ()
            seen.add(key)
            found = shingles(text)
            return ((key, found.tobytes(), bin_counts(found)),)

        return one

    return texts.mapInArrow(common.per_row(["key", "text"], schema, make), "key long, found binary, counts binary")


def fingerprint_pairs(prints: DataFrame) -> DataFrame:
    """u, v: texts of equal fingerprints, and one text each of fingerprints that the BK-trees link."""
    first = common.materialise(prints.groupBy("fp").agg(F.min("key").alias("least")))
    equal = prints.join(first, "fp").filter("key <> least").select(F.col("least").alias("u"), F.col("key").alias("v"))
    linked = simhash.links(first.select("fp"), first.count())
    of_u, of_v = (first.select(F.col("fp").alias(k), F.col("least").alias(f"_{k}")) for k in ("u", "v"))
    near = linked.join(of_u, "u").join(of_v, "v").select(F.least("_u", "_v").alias("u"), F.greatest("_u", "_v").alias("v"))
    return equal.unionByName(near).distinct()


def apart(met: DataFrame, roots: DataFrame, profiles: DataFrame) -> DataFrame:
    """token, key, n, at, root, profile: the meetings at shingles whose texts are not all in one component yet."""
    rows = met.join(roots, met.key == roots.node, "left").select("token", "key", "n", "at", F.coalesce("root", "key").alias("root"))
    mixed = rows.groupBy("token").agg(F.min("root").alias("_a"), F.max("root").alias("_b")).filter("_a < _b").select("token")
    return common.materialise(rows.join(mixed, "token").join(profiles.select("key", *PROFILE), "key"))


def to_pivots(rows: DataFrame, k: int) -> DataFrame:
    """u, v: at each shingle, every text of another component with the one text that round ``k`` chooses."""
    pivot = rows.groupBy("token").agg(F.min(F.struct(F.xxhash64("key", F.lit(k)).alias("draw"), "key", "n", "at", "root", *PROFILE)).alias("p"))
    both = rows.join(pivot, "token").filter((F.col("root") != F.col("p.root")) & _may_link(F.col("n"), F.col("at"), F.col("p.n"), F.col("p.at")))
    theirs = [f"p.{b}" for b in PROFILE]
    common_most = F.least(F.col("n") - _missing(PROFILE, theirs), F.col("p.n") - _missing(theirs, PROFILE))
    both = both.filter(9 * common_most >= 4 * (F.col("n") + F.col("p.n")))
    return both.select(F.least("key", "p.key").alias("u"), F.greatest("key", "p.key").alias("v")).distinct()


def all_pairs(rows: DataFrame, nearest: bool = False) -> DataFrame:
    """u, v: all pairs of ``rows`` (token, key, n, at, root, profile) that meet, lie in different components and can be linked.

    The texts of a shingle are dealt into blocks of about ``BLOCK``, and each pair of blocks meets in a task.
    With ``nearest`` a text outside the largest component there leaves one of its pairs, the one whose
    profiles allow the most in common.
    """
    schema = pa.schema([("u", pa.int64()), ("v", pa.int64())])
    columns = ["token", "low", "high", "block", "key", "n", "at", "root", *PROFILE]

    def pairs(low, high, block, key, n, at, root, *bits):
        bits = np.stack(bits)
        _, group, size = np.unique(root, return_inverse=True, return_counts=True)
        main = group == int(np.argmax(size))
        if main.all():
            return
        rest = np.flatnonzero(~main)
        for k, i in enumerate(rest):  # the largest component's own pairs are not formed
            other = np.concatenate([np.flatnonzero(main), rest[k + 1 :]])
            other = other[root[other] != root[i]]
            if low[0] != high[0]:
                other = other[block[other] != block[i]]
            other = other[_may_link(n[other], at[other], np.full(len(other), n[i]), np.full(len(other), at[i]))]
            most = np.minimum(n[other] - _missing(bits[:, other], bits[:, [i]]), n[i] - _missing(np.repeat(bits[:, [i]], len(other), axis=1), bits[:, other]))
            may = 9 * most >= 4 * (n[other] + n[i])
            other, most = other[may], most[may]
            if nearest and len(other) > 1:
                other = other[[int(np.argmax(most / (n[other] + n[i])))]]
            if len(other):
                yield np.minimum(key[other], key[i]), np.maximum(key[other], key[i])

    def search(batches):
        held = [np.zeros(0, np.int64)] * len(columns)

        def out(some):
            cuts = np.flatnonzero(np.r_[True, np.any([c[1:] != c[:-1] for c in some[:3]], axis=0), True])
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                for u, v in pairs(*(c[a:b] for c in some[1:])) if b - a > 1 else ():
                    yield pa.RecordBatch.from_arrays([pa.array(u), pa.array(v)], schema=schema)

        for batch in batches:
            held = [np.concatenate([h, batch.column(k).to_numpy(zero_copy_only=False)]) for k, h in enumerate(held)]
            if len(held[0]):
                differs = np.any([c != c[-1] for c in held[:3]], axis=0)  # the last group may go on in the next batch
                cut = int(np.flatnonzero(differs)[-1]) + 1 if differs.any() else 0
                yield from out([h[:cut] for h in held]) if cut else ()
                held = [h[cut:] for h in held]
        if len(held[0]):
            yield from out(held)

    blocks = rows.groupBy("token").agg(F.ceil(F.count("*") / BLOCK).cast("long").alias("blocks"))
    dealt = rows.join(blocks, "token").withColumn("block", F.pmod(F.xxhash64("key"), F.col("blocks")))
    dealt = dealt.withColumn("partner", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)))
    dealt = dealt.withColumns({"low": F.least("block", "partner"), "high": F.greatest("block", "partner")}).select(*columns)
    return dealt.repartition("token", "low", "high").sortWithinPartitions("token", "low", "high", "key").mapInArrow(search, "u long, v long").distinct()


def groups(docs: DataFrame) -> DataFrame:
    """doc_id, component_id for every row of ``docs`` (columns doc_id, text)."""
    text = F.coalesce("text", F.lit(""))
    texts = docs.select(F.xxhash64(text).alias("key"), text.alias("text"))
    keys = common.materialise(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(text).alias("key")))
    distinct = common.materialise(keys.groupBy("key").agg(F.min("doc_id").alias("least")))
    known = common.materialise(summaries(texts, distinct.count()))
    profiles = common.materialise(known.select("key", "fp", *PROFILE).dropDuplicates(["key"]))
    met = common.materialise(meetings(known))
    common.forget(known)

    joined = components.of_edges(alike(fingerprint_pairs(profiles), texts))
    for k in range(PIVOT_ROUNDS):
        rows = apart(met, joined, profiles)
        joined = components.of_edges(alike(to_pivots(rows, k), texts), joined)
        common.forget(rows)
    for _ in range(NEAREST_ROUNDS):
        rows = apart(met, joined, profiles)
        links = alike(all_pairs(rows, nearest=True), texts)
        common.forget(rows)
        if links.isEmpty():
            break
        joined = components.of_edges(links, joined)
    rows = apart(met, joined, profiles)
    found = components.of_edges(alike(all_pairs(rows), texts), joined)
    common.forget(rows)
    common.forget(met)

    moved = distinct.join(found, distinct.key == found.node, "left").select("key", "least", F.coalesce("root", "key").alias("root"))
    named = moved.groupBy("root").agg(F.min("least").alias("component_id"))
    by_key = common.materialise(moved.join(named, "root").select("key", "component_id"))
    return keys.join(by_key, "key").select("doc_id", "component_id")


def deduplicate(docs: DataFrame) -> DataFrame:
    """One row of each group stays, as ``components.one_of_each`` says; columns as given."""
    return components.one_of_each(docs, groups(docs))
