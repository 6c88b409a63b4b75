"""Document fingerprints: bottom-k sketches of shingle hashes, in DataFrame functions only.

Method. A text's shingles are its runs of ``SHINGLE`` words (white-space separated, lower
case; a shorter text is one shingle, a text without words has none). The fingerprint is the
sorted array of the ``K`` smallest 64-bit hashes of its distinct shingles. Sketches of parts
merge into the sketch of the whole (`merge`); two sketches give estimates of resemblance and
containment, one gives the number of distinct shingles.

Defined results: null text = empty text = empty sketch; two empty sketches resemble each
other by 1, an empty and another one by 0; equal texts have equal fingerprints; an empty
table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common

K = 128
SHINGLE = 5
_SPACES = "\t\n\x0b\x0c\r"


def words(text: Column) -> Column:
    plain = F.translate(F.lower(F.coalesce(text, F.lit(""))), _SPACES, " " * len(_SPACES))
    return F.array_remove(F.split(plain, " "), "")


def with_sketches(df: DataFrame, columns: dict[str, str], k: int = K, shingle: int = SHINGLE) -> DataFrame:
    """Adds for each ``{name: text column}`` the text's sketch.

    Word hashes are a column of their own, so that the shingles of a row refer to one array.
    """
    kept = df.columns
    for name, text in columns.items():
        hashed = f"_{name}_words"
        df = df.withColumn(hashed, F.transform(words(F.col(text)), lambda w: F.xxhash64(w)))
        h = F.col(hashed)
        heads = F.slice(h, F.lit(1), F.greatest(F.size(h) - (shingle - 1), F.lit(1)))
        shingles = F.transform(heads, lambda x, i: F.xxhash64(x, *(F.get(h, i + j) for j in range(1, shingle))))
        df = df.withColumn(name, F.slice(F.sort_array(F.array_distinct(shingles)), 1, k))
        kept = [*kept, name]
    return df.select(*kept)


def merge(df: DataFrame, by: list[str], sketch: str = "sketch", k: int = K) -> DataFrame:
    """The sketch of each group's union, from its parts' sketches; at most k values a part are moved."""
    least = df.select(*by, F.explode(sketch).alias("_v")).distinct()
    rank = F.row_number().over(Window.partitionBy(*by).orderBy("_v"))
    some = least.withColumn("_r", rank).filter(F.col("_r") <= k).groupBy(*by).agg(F.sort_array(F.collect_list("_v")).alias(sketch))
    groups = df.select(*by).distinct()
    same = [groups[c].eqNullSafe(some[c]) for c in by]
    return groups.join(some, same, "left").select(*(groups[c] for c in by), F.coalesce(some[sketch], F.array().cast("array<bigint>")).alias(sketch))


def resemblance(a: Column, b: Column, k: int = K) -> Column:
    """Estimated share of common shingles among all of both texts."""
    union = F.slice(F.sort_array(F.array_union(a, b)), 1, k)
    both = F.size(F.array_intersect(union, F.array_intersect(a, b)))
    return F.when(F.size(union) == 0, F.lit(1.0)).otherwise(both / F.size(union))


def containment(a: Column, b: Column, k: int = K) -> Column:
    """Estimated share of a's shingles that b has; only hashes below b's last kept one can tell."""
    full = F.size(b) >= k
    told = F.when(full, F.filter(a, lambda x: x <= F.element_at(b, -1))).otherwise(a)
    return F.when(F.size(a) == 0, F.lit(1.0)).when(F.size(told) == 0, F.lit(0.0)).otherwise(F.size(F.array_intersect(told, b)) / F.size(told))


def distinct_shingles(a: Column, k: int = K) -> Column:
    """Estimated number of distinct shingles; exact below k."""
    share = (F.element_at(a, -1).cast("double") + F.lit(2.0**63)) / F.lit(2.0**64)
    return F.when(F.size(a) < k, F.size(a).cast("double")).otherwise(F.lit(k - 1.0) / share)


def as_text(sketch: Column) -> Column:
    return F.array_join(F.transform(sketch, lambda x: F.lower(F.lpad(F.hex(x), 16, "0"))), "")


#: What names a row: its id with null told apart from zero, and its text's hash. Plain columns, so
#: that joins and windows over them agree on one partitioning.
_KEY = ["id", "no_id", "digest"]


def keyed(docs: DataFrame) -> DataFrame:
    """The text and the row's key, from which the doc_id can be read again."""
    base = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    return base.select(F.coalesce("doc_id", F.lit(0)).alias("id"), F.isnull("doc_id").alias("no_id"), F.xxhash64("text").alias("digest"), "text")


def followers(docs: DataFrame) -> DataFrame:
    """Each keyed document with the key of the one before it in ascending doc_id (to_*), which takes
    ``quarter`` code points from it; before the first comes the last.

    Rows with the same doc_id and text count once; rows that only share a doc_id are ordered
    by their text's hash; null ids come first. Ids are dealt out by range and ordered inside
    each range; across ranges only the last row of each, one per partition, is compared.
    """
    keys = docs.select(*_KEY, F.char_length("text").alias("n")).distinct()
    order = [F.desc("no_id"), F.col("id"), F.col("digest")]
    ranged = common.materialise(keys.repartitionByRange(*order).withColumn("part", F.spark_partition_id()))
    this = F.struct((~F.col("no_id")).alias("has_id"), "id", "digest", "n")
    ends = ranged.groupBy("part").agg(F.max(this).alias("end"))
    by_part = Window.orderBy("part")
    last = F.last("end").over(by_part.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    before = ends.select("part", F.coalesce(F.lag("end").over(by_part), last).alias("before"))
    inside = ranged.withColumn("prev", F.lag(this).over(Window.partitionBy("part").orderBy(*order)))
    to = F.coalesce("prev", "before")
    return common.materialise(
        inside.join(before, "part").select(
            *_KEY, to["id"].alias("to_id"), (~to["has_id"]).alias("to_no_id"), to["digest"].alias("to_digest"), F.floor(to["n"] / 4).cast("int").alias("quarter")
        )
    )


def edited(docs: DataFrame, k: int = K) -> DataFrame:
    """Every document's sketch, its edited text's and the next document's (columns doc_id, text).

    One exchange of the texts by their keys serves both sides: the text that is edited, and
    the giver, which sends on only the prefix that is asked for and its sketch.
    """
    base = keyed(docs)
    first = F.row_number().over(Window.partitionBy(*_KEY).orderBy("id")) == 1
    given = base.join(followers(base), _KEY).withColumn("first", first).filter("first")
    given = with_sketches(given, {"next_sketch": "text"}, k).select(
        F.col("to_id").alias("id"), F.col("to_no_id").alias("no_id"), F.col("to_digest").alias("digest"), F.expr("substring(text, 1, quarter)").alias("put"), "next_sketch"
    )
    both = base.join(given, _KEY).select(
        F.when(~F.col("no_id"), F.col("id")).alias("doc_id"), F.char_length("text").cast("long").alias("n_chars"), "text",
        F.concat(F.expr("substring(text, 1, char_length(text) - int(floor(char_length(text) / 4)))"), "put").alias("edited"), "next_sketch",
    )
    both = both.withColumn("edited_sha256", F.sha2(F.col("edited").cast("binary"), 256))
    return with_sketches(both, {"sketch": "text", "edited_sketch": "edited"}, k)


def op1_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = edited(common.table(spark, sf_dir, "documents"))
    return df.select(
        "doc_id", "n_chars", "edited_sha256",
        as_text(F.col("sketch")).alias("fingerprint"), as_text(F.col("edited_sketch")).alias("edited_fingerprint"),
        resemblance(F.col("sketch"), F.col("edited_sketch")).alias("near_edited"),
        resemblance(F.col("sketch"), F.col("next_sketch")).alias("near_next"),
    )
