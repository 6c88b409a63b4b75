import hashlib
import random

import duckdb
from pyspark.sql import functions as F

from cyclefold.llm import warc


def sha(text):
    return hashlib.sha256(text.encode()).hexdigest()


def archive(n, seed):
    draw = random.Random(seed)
    out = []
    for i in range(n):
        body = draw.randbytes(draw.randrange(0, 300))
        out.append(b"WARC/1.0\r\nWARC-Type: resource\r\nContent-Length: %d\r\n\r\n%b\r\n\r\n" % (len(body), body))
    return out


def test_files_on_two_replicas(spark, tmp_path):
    stores = {"a": tmp_path / "a", "b": tmp_path / "b"}
    for s in stores.values():
        s.mkdir()
    want = set()
    for k, n in enumerate((1, 5, 40, 300)):
        records = archive(n, k)
        (stores["a"] / f"{k}.warc").write_bytes(b"".join(records))
        other = list(records)
        if k == 2:
            other[17] = other[17].replace(b"resource", b"resourcE")
            want.add(("2.warc", 17, "changed"))
        if k == 3:
            other[250] = other[250][:-1] + b"!"
            del other[298:]
            want |= {("3.warc", 250, "changed"), ("3.warc", 298, "missing"), ("3.warc", 299, "missing")}
        if k:
            (stores["b"] / f"{k}.warc").write_bytes(b"".join(other))
    want.add(("0.warc", 0, "missing"))
    a, b = (warc.read(spark, str(p)) for p in stores.values())
    for fanout in (2, 16):
        ta, tb = warc.Tree.of(a, fanout), warc.Tree.of(b, fanout)
        got = {(r.file, r.position, r.kind) for r in warc.audit(ta, tb, fanout).collect()}
        assert got == want
        assert {(f, p, {"missing": "extra"}.get(k, k)) for f, p, k in got} == {(r.file, r.position, r.kind) for r in warc.audit(tb, ta, fanout).collect()}
        assert warc.audit(ta, ta, fanout).count() == 0
    leaf = [sha(f"leaf|{r.start}|{r.length}|{r.digest}") for r in a.filter("file = '1.warc'").orderBy("position").collect()]
    root = warc.Tree.of(a.filter("file = '1.warc'"), 16).roots().first()
    assert root.hash == sha(f"node|0|{root.end}|5|{','.join(leaf)}") and root.records == 5
    row = warc.audit(ta, tb, 16).filter("file = '3.warc' and position = 250").first()
    assert (stores["a"] / "3.warc").read_bytes()[row.primary_start : row.primary_end] == archive(300, 3)[250]


def test_split_records_of_broken_files():
    assert list(warc.split_records(b"")) == []
    assert list(warc.split_records(b"junk")) == [(0, b"junk")]
    one = archive(1, 9)[0]
    assert [r for _, r in warc.split_records(one + one[:-3])] == [one, one[:-3]]


def test_offsets_and_lengths_are_hashed(spark):
    """Equal digests at other offsets or of other lengths differ, and so do trees of other shapes."""
    schema = "file string, position long, start long, length long, digest string"
    rows = [("f", i, 10 * i, 10, sha(str(i))) for i in range(40)]
    plain = warc.Tree.of(spark.createDataFrame(rows, schema), 4)
    for k, (start, length, kinds) in enumerate([(171, 9, {17}), (170, 11, {17}), (170, 10, set())]):
        other = [(f, i, start, length, d) if i == 17 else (f, i, s, n, d) for f, i, s, n, d in rows]
        got = warc.audit(plain, warc.Tree.of(spark.createDataFrame(other, schema), 4), 4).collect()
        assert {r.position for r in got} == kinds and {r.kind for r in got} <= {"moved"}, k
    shifted = [(f, i, s + (i > 20), n, d) for f, i, s, n, d in rows]
    got = warc.audit(plain, warc.Tree.of(spark.createDataFrame(shifted, schema), 4), 4).collect()
    assert sorted(r.position for r in got) == list(range(21, 40)) and {r.kind for r in got} == {"moved"}


def test_query_against_sql(spark, tmp_path):
    rows = [(i, f"http://h/{i}", f"<p>é {i}</p>", 1) for i in range(3000)] + [(5, None, None, 1), (None, "u", "x", 1), (7, "http://h/7", "<p>é 7</p>", 1), (7, "http://h/7", "<p>é 7</p>", 1)]
    rows += [(640, "http://h/again", f"WARC/1.1\r\n\r\n {i}", 1) for i in range(300)]  # one id with many pages
    spark.createDataFrame(rows, "page_id long, url string, html string, file int").repartition(4).write.parquet(str(tmp_path / "pages.parquet"))
    got = warc.op9_fixity(spark, str(tmp_path)).cache()
    con = duckdb.connect()
    con.execute(f"create view pages as select * from '{tmp_path}/pages.parquet/*.parquet'")
    want = con.execute(warc.ORACLE).fetchall()
    assert [c[0] for c in con.description] == got.columns
    assert want and sorted(map(str, map(tuple, got.collect()))) == sorted(map(str, want))
    kinds = {r.kind: r["count"] for r in got.groupBy("kind").count().collect()}
    assert set(kinds) == {"changed", "moved", "missing", "extra"} and min(kinds.values()) >= 10, kinds
    assert got.filter(F.startswith("file", F.lit("pages-10."))).count()
    empty = tmp_path / "empty"
    spark.createDataFrame(rows[:1], "page_id long, url string, html string, digest int").limit(0).write.parquet(str(empty / "pages.parquet"))
    assert warc.op9_fixity(spark, str(empty)).count() == 0 and warc.op9_fixity(spark, str(empty)).columns == got.columns


def test_stored_archives_hold_the_pages(spark, tmp_path):
    pages = spark.read.parquet("/root/testdata/sf0.001/pages.parquet")
    warc.write(warc.stores(pages), str(tmp_path / "s"))
    import gzip

    found = {}
    for file in sorted(tmp_path.glob("s/store=primary/file=*/*.gz")):
        for _, raw in warc.split_records(gzip.decompress(file.read_bytes())):
            head, _, body = raw.partition(b"\r\n\r\n")
            found[int(warc.record_name(raw).removeprefix("<urn:page:").removesuffix(">"))] = body[:-4].decode()
            assert f"Content-Length: {len(body) - 4}".encode() in head
    assert found == {r.page_id: r.html for r in pages.collect()}


def test_archives_are_packed_fast(spark, tmp_path):
    import gzip
    import random

    draw = random.Random(1)
    text = " ".join(f"w{draw.randrange(3000)}" for _ in range(60_000))
    warc.write(spark.createDataFrame([("primary", "f", 0, text)], "store string, file string, position long, text string"), str(tmp_path / "out"))
    (file,) = (tmp_path / "out").rglob("*.gz")
    raw = file.read_bytes()
    assert gzip.decompress(raw) == text.encode() + b"\r\n\r\n"
    assert len(raw) > 1.02 * len(gzip.compress(text.encode(), 6))
