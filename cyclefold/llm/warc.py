"""Fixity audit of web archives: Merkle trees over records, compared between replicas.

Method. A record's digest is the SHA-256 of its bytes. A leaf hashes the record's offset, its
length and its digest; ``FANOUT`` neighbours make a node of the next level, which hashes the
offset range it covers, how many records lie in it and its children's hashes in order, up to one
root a file. Leaves and nodes are tagged, so that neither can stand for the other. The audit
compares roots of the same file in two replicas and descends only where they differ, level by
level, to the records that differ; equal branches are never joined below their top node.

Corruption that keeps the record borders is located record by record (``changed``); records that
are whole but lie at another offset are ``moved``; a cut file shows as ``missing`` records, a longer
one as ``extra`` ones. Where a record is lost inside a file, every record from there on differs.

Defined results: a null url, date or body is the empty one; repeated rows are separate records;
a file that one replica lacks is reported record by record; empty tables give empty results.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common

FANOUT = 16
#: Page ids that share an archive; an archive of more than ``CROWDED`` times as many pages, as ids repeat, is split.
FILE_RECORDS, CROWDED = 64, 4
#: Level of the archives' compression: half the seconds of the usual one for a tenth more bytes.
LEVEL = "TWO"


# --- archives ---------------------------------------------------------------------------------

#: What ends a record.
_END = "\r\n\r\n"


def record(url: Column, body: Column, name: Column) -> Column:
    """A page as the text of a resource record, without the two line ends behind it."""
    url, body = F.coalesce(url, F.lit("")), F.coalesce(body, F.lit(""))
    name = F.coalesce(name.cast("string"), F.lit(""))
    return F.concat(
        F.lit("WARC/1.1\r\nWARC-Type: resource\r\nWARC-Record-ID: <urn:page:"), name, F.lit(">\r\nWARC-Target-URI: "), url,
        F.lit("\r\nContent-Type: text/html\r\nContent-Length: "), F.octet_length(body).cast("string"), F.lit(_END), body,
    )


def write(records: DataFrame, path: str) -> None:
    """Archive files below ``path`` from rows (store, file, position, text): one a store and file, compressed.

    The records' ends are the line ends of Spark's text writer, so no record passes through Python.
    ``records`` has all rows of a file in one partition.
    """
    ordered = records.sortWithinPartitions("store", "file", "position").select("store", "file", F.col("text").alias("value"))
    ordered.write.partitionBy("store", "file").option("lineSep", _END).option("compression", "gzip").option("zlib.compress.level", LEVEL).text(path)


_HEADER = re.compile(rb"WARC/1\.[01]\r\n(.*?)\r\n\r\n", re.S)
_LENGTH = re.compile(rb"^content-length:\s*(\d+)\s*$", re.I | re.M)
_NAME = re.compile(rb"^warc-record-id:\s*(.*?)\s*$", re.I | re.M)


def split_records(data: bytes) -> Iterator[tuple[int, bytes]]:
    """(offset, bytes) of the records of one archive file; what doesn't parse is one last record."""
    at = 0
    while at < len(data):
        m = _HEADER.match(data, at)
        length = _LENGTH.search(m[1].replace(b"\r", b"")) if m else None
        end = m.end() + int(length[1]) + 4 if length else len(data)
        yield at, data[at : min(end, len(data))]
        at = end


def record_name(raw: bytes) -> str | None:
    """The record's own id, None if it has none."""
    m = _HEADER.match(raw)
    name = _NAME.search(m[1].replace(b"\r", b"")) if m else None
    return name[1].decode(errors="replace") if name else None


def read(spark: SparkSession, path: str) -> DataFrame:
    """The leaves of the archive files below a folder, plain or compressed; a task holds one file at a time.

    A file is named by its folder ``file=...`` if it lies in one, else by its own name.
    """
    schema = pa.schema([("file", pa.string()), ("position", pa.int64()), ("start", pa.int64()), ("length", pa.int64()), ("digest", pa.string()), ("name", pa.string())])

    def make():
        import gzip
        import hashlib
        from posixpath import basename, dirname

        def one(path, content):
            folder = basename(dirname(path))
            file = folder.removeprefix("file=") if folder.startswith("file=") else basename(path)
            data = gzip.decompress(content) if content[:2] == b"\x1f\x8b" else content
            for i, (at, raw) in enumerate(split_records(data)):
                yield file, i, at, len(raw), hashlib.sha256(raw).hexdigest(), record_name(raw)

        def each(batches):
            for batch in batches:
                for path, content in zip(batch.column(0), batch.column(1), strict=True):
                    rows = list(zip(*one(path.as_py(), content.as_py()), strict=True)) or [[] for _ in schema]
                    yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(rows, schema, strict=True)], schema=schema)

        return each

    files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path)
    return files.select("path", "content").mapInArrow(lambda batches: make()(batches), "file string, position long, start long, length long, digest string, name string")


# --- trees ------------------------------------------------------------------------------------


class Tree:
    """Levels of (file, node, hash, start, end, records), the leaves with digest and name; the last level are the roots."""

    def __init__(self, levels: list[DataFrame]):
        self.levels = levels

    @classmethod
    def of(cls, leaves: DataFrame, fanout: int = FANOUT) -> Tree:
        """From leaves (file, position, start, length, digest and, if known, name)."""
        name = F.col("name") if "name" in leaves.columns else F.lit(None).cast("string").alias("name")
        hashed = F.sha2(F.concat_ws("|", F.lit("leaf"), "start", "length", "digest"), 256)
        now = common.materialise(
            leaves.select(
                "file", F.col("position").alias("node"), hashed.alias("hash"), "start", (F.col("start") + F.col("length")).alias("end"), F.lit(1).cast("long").alias("records"), "digest", name
            )
        )
        levels = [now]
        most = now.agg(F.max("node")).first()[0] or 0
        while most > 0:
            child = F.struct("node", "hash")
            grouped = now.groupBy("file", F.floor(F.col("node") / fanout).cast("long").alias("node")).agg(
                F.sort_array(F.collect_list(child)).alias("children"), F.min("start").alias("start"), F.max("end").alias("end"), F.sum("records").alias("records")
            )
            hashed = F.sha2(F.concat_ws("|", F.lit("node"), "start", "end", "records", F.array_join("children.hash", ",")), 256)
            now = common.materialise(grouped.select("file", "node", hashed.alias("hash"), "start", "end", "records"))
            levels.append(now)
            most //= fanout
        return cls(levels)

    def roots(self) -> DataFrame:
        return self.levels[-1]


def audit(primary: Tree, replica: Tree, fanout: int = FANOUT) -> DataFrame:
    """file, position, kind (changed, moved, missing, extra); start, end, digest and name on either side.

    A tree of fewer levels has smaller files only; its roots stand for the levels it lacks.
    """
    height = max(len(primary.levels), len(replica.levels))
    sides = [t.levels + [t.levels[-1]] * (height - len(t.levels)) for t in (primary, replica)]
    frontier = None
    for level in reversed(range(height)):
        a, b = (s[level] for s in sides)
        if frontier is not None:
            up = F.floor(F.col("node") / fanout)
            a, b = (s.join(frontier, (F.col("file").eqNullSafe(F.col("f"))) & (up == F.col("parent")), "left_semi") for s in (a, b))
        a, b = a.alias("a"), b.alias("b")
        same = F.col("a.file").eqNullSafe(F.col("b.file")) & (F.col("a.node") == F.col("b.node"))
        differ = a.join(b, same, "full_outer").filter(~F.col("a.hash").eqNullSafe(F.col("b.hash")))
        if level:
            frontier = common.materialise(differ.select(F.coalesce("a.file", "b.file").alias("f"), F.coalesce("a.node", "b.node").alias("parent")))
    kind = (
        F.when(F.col("b.digest").isNull(), "missing").when(F.col("a.digest").isNull(), "extra").when(F.col("a.digest") == F.col("b.digest"), "moved").otherwise("changed")
    )
    return differ.select(
        F.coalesce("a.file", "b.file").alias("file"), F.coalesce("a.node", "b.node").alias("position"), kind.alias("kind"),
        *(F.col(f"{n}.{c}").alias(f"{side}_{c}") for n, side in (("a", "primary"), ("b", "replica")) for c in ("start", "end", "digest", "name")),
    )


# --- the query --------------------------------------------------------------------------------

#: The second store is made for the query. By the first letters of a record's digest: a page whose last
#: character is another one there, and, in every fourth archive, one that lost it, which moves all behind it.
#: By the archive's number modulo 4: the last record is lost, or is there twice.
ROTTEN, SHORTER = "0", "1"
CUT, TWICE, SHIFTED = 1, 2, 3


def stores(pages: DataFrame) -> DataFrame:
    """store, file, position, text: the pages as archives in two stores, all rows of a file in one partition.

    An archive has the pages of ``FILE_RECORDS`` ids. Where ids repeat so often that it would be crowded,
    it is split by the records' digests.
    """
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", "html", F.floor(F.col("page_id").cast("long") / FILE_RECORDS).cast("long").alias("block"))
    crowded = rows.groupBy("block").count().filter(F.col("count") > CROWDED * FILE_RECORDS)
    crowded = common.materialise(crowded.select(F.col("block").alias("of"), F.ceil(F.col("count") / FILE_RECORDS).cast("long").alias("parts")))
    digest = F.sha2(F.concat(record(F.col("url"), F.col("html"), F.col("page_id")), F.lit(_END)).cast("binary"), 256)
    rows = rows.withColumn("digest", digest).join(crowded, F.col("block").eqNullSafe(F.col("of")), "left")
    part = F.when(F.col("parts").isNotNull(), F.concat(F.lit("."), F.pmod(F.conv(F.substring("digest", 1, 8), 16, 10).cast("long"), F.col("parts")).cast("string"))).otherwise("")
    rows = rows.withColumn("file", F.concat(F.lit("pages-"), F.coalesce(F.col("block").cast("string"), F.lit("none")), part))
    order = Window.partitionBy("file").orderBy("page_id", "digest")
    rows = rows.withColumns({"position": F.row_number().over(order).cast("long") - 1, "last": F.lead("digest").over(order).isNull()})

    kind = F.coalesce(F.pmod("block", F.lit(4)), F.lit(0))
    body = F.coalesce("html", F.lit(""))
    cut = F.expr("left(coalesce(html, ''), greatest(char_length(coalesce(html, '')) - 1, 0))")
    stored = (
        F.when(F.startswith("digest", F.lit(ROTTEN)), F.concat(cut, F.lit("?"))).when(F.startswith("digest", F.lit(SHORTER)) & (kind == SHIFTED), cut).otherwise(body)
    )
    entry = lambda store, position, html: F.struct(F.lit(store).alias("store"), position.alias("position"), html.alias("html"))
    at = F.col("position")
    entries = F.array(
        entry("primary", at, body),
        F.when(~(F.col("last") & (kind == CUT)), entry("replica", at, stored)),
        F.when(F.col("last") & (kind == TWICE), entry("replica", at + 1, stored)),
    )
    each = rows.withColumn("e", F.explode(F.array_compact(entries)))
    return each.select("e.store", "file", "e.position", record(F.col("url"), F.col("e.html"), F.col("page_id")).alias("text"))


def op9_fixity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Writes the pages as archives in two stores, reads both back and audits them."""
    path = common.new_folder(spark)
    write(stores(common.table(spark, sf_dir, "pages")), path)
    if not common.exists(spark, path, "store=primary"):
        kinds = "file string, position long, page_id long, kind string, primary_start long, primary_end long, primary_digest string, replica_start long, replica_end long, replica_digest string"
        return spark.createDataFrame([], kinds)
    primary, replica = (Tree.of(read(spark, f"{path}/store={s}")) for s in ("primary", "replica"))
    found = audit(primary, replica)
    page = F.regexp_extract(F.coalesce("primary_name", "replica_name"), "urn:page:(-?[0-9]+)>", 1)
    return found.withColumn("page_id", F.when(page != "", page.cast("long"))).select(
        "file", "position", "page_id", "kind", "primary_start", "primary_end", "primary_digest", "replica_start", "replica_end", "replica_digest"
    )


def _sql_record(body: str) -> str:
    crlf = "chr(13) || chr(10)"
    return (
        f"'WARC/1.1' || {crlf} || 'WARC-Type: resource' || {crlf} || 'WARC-Record-ID: <urn:page:' || coalesce(page_id::varchar, '') || '>' || {crlf}"
        f" || 'WARC-Target-URI: ' || coalesce(url, '') || {crlf} || 'Content-Type: text/html' || {crlf} || 'Content-Length: ' || octet_length(encode({body}))::varchar"
        f" || {crlf} || {crlf} || {body} || {crlf} || {crlf}"
    )


ORACLE = f"""
WITH b AS (SELECT page_id, url, coalesce(html, '') AS html, floor(page_id / {FILE_RECORDS})::bigint AS block FROM pages),
s AS (SELECT *, {_sql_record("html")} AS sound FROM b),
d AS (SELECT *, sha256(sound) AS digest, count(*) OVER (PARTITION BY block) AS n, coalesce(((block % 4) + 4) % 4, 0) AS kind FROM s),
f AS (SELECT *, 'pages-' || coalesce(block::varchar, 'none') || CASE WHEN n > {CROWDED * FILE_RECORDS}
        THEN '.' || (('0x' || substr(digest, 1, 8))::bigint % ceil(n / {FILE_RECORDS})::bigint)::varchar ELSE '' END AS file FROM d),
p AS (SELECT *, row_number() OVER w - 1 AS position, lead(digest) OVER w IS NULL AS last FROM f WINDOW w AS (PARTITION BY file ORDER BY page_id, digest)),
c AS (SELECT *, CASE WHEN digest LIKE '{ROTTEN}%' THEN left(html, greatest(length(html) - 1, 0)) || '?'
        WHEN digest LIKE '{SHORTER}%' AND kind = {SHIFTED} THEN left(html, greatest(length(html) - 1, 0)) ELSE html END AS other FROM p),
r AS (SELECT page_id, file, position, last, kind, digest, octet_length(encode(sound)) AS len, {_sql_record("other")} AS stored FROM c),
y AS (SELECT page_id, file, position, stored FROM r WHERE NOT (last AND kind = {CUT})
      UNION ALL SELECT page_id, file, position + 1, stored FROM r WHERE last AND kind = {TWICE}),
pr AS (SELECT page_id, file, position, digest, (sum(len) OVER (PARTITION BY file ORDER BY position))::bigint AS stop, len FROM r),
re AS (SELECT page_id, file, position, sha256(stored) AS digest, (sum(octet_length(encode(stored))) OVER (PARTITION BY file ORDER BY position))::bigint AS stop,
         octet_length(encode(stored)) AS len FROM y)
SELECT coalesce(pr.file, re.file) AS file, coalesce(pr.position, re.position)::bigint AS position, coalesce(pr.page_id, re.page_id) AS page_id,
  CASE WHEN re.digest IS NULL THEN 'missing' WHEN pr.digest IS NULL THEN 'extra' WHEN pr.digest = re.digest THEN 'moved' ELSE 'changed' END AS kind,
  (pr.stop - pr.len)::bigint AS primary_start, pr.stop AS primary_end, pr.digest AS primary_digest,
  (re.stop - re.len)::bigint AS replica_start, re.stop AS replica_end, re.digest AS replica_digest
FROM pr FULL JOIN re ON pr.file = re.file AND pr.position = re.position
WHERE pr.digest IS NULL OR re.digest IS NULL OR pr.digest <> re.digest OR pr.stop <> re.stop OR pr.len <> re.len
"""
