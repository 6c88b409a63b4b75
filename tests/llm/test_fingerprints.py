import hashlib
import random

from pyspark.sql import functions as F

from cyclefold.llm import fingerprints as fp


def shingles(text):
    words = (text or "").lower().translate({ord(c): " " for c in "\t\n\x0b\x0c\r"}).split(" ")
    words = [w for w in words if w]
    return {tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))} if words else set()


def prose(draw, n):
    return " ".join(draw.choice("abcdefghij") + draw.choice(["x", "É", "zz"]) for _ in range(n))


def test_edited_texts_and_next_documents(spark):
    draw = random.Random(1)
    rows = [(i * 3, prose(draw, draw.randrange(0, 60)), "x") for i in range(60)]
    rows += [(500, "", "x"), (501, None, "x"), (600, "a\tb\nc", "x"), (7, rows[9][1], "x")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, sketch string").repartition(5)
    ordered = sorted(rows)
    got = {r.doc_id: r for r in fp.edited(docs).collect()}
    assert len(got) == len(rows)
    for (i, text, _), (_, nxt, _) in zip(ordered, ordered[1:] + ordered[:1], strict=True):
        text, nxt = text or "", nxt or ""
        q = len(text) // 4
        edited = text[: len(text) - q] + nxt[:q]
        r = got[i]
        assert (r.n_chars, r.edited_sha256) == (len(text), hashlib.sha256(edited.encode()).hexdigest())
        assert len(r.sketch) == min(fp.K, len(shingles(text))) and sorted(r.sketch) == r.sketch
        assert len(r.edited_sketch) == min(fp.K, len(shingles(edited)))
    assert got[7].sketch == got[27].sketch


def test_estimates_and_merging(spark):
    draw = random.Random(2)
    rows = []
    for i in range(30):
        a = prose(draw, 900)
        b = a[: 120 * i] + prose(draw, 700) if i else a
        rows.append((i, a, b))
    rows += [(98, "", ""), (99, "", "one two")]
    df = fp.with_sketches(spark.createDataFrame(rows, "i long, a string, b string"), {"x": "a", "y": "b"})
    got = df.select("i", fp.resemblance(F.col("x"), F.col("y")).alias("r"), fp.containment(F.col("x"), F.col("y")).alias("c"), fp.distinct_shingles(F.col("x")).alias("n")).collect()
    for r, (_, a, b) in zip(sorted(got), rows, strict=True):
        sa, sb = shingles(a), shingles(b)
        if sa and sb:
            assert abs(r.r - len(sa & sb) / len(sa | sb)) < 0.16
            assert abs(r.c - len(sa & sb) / len(sa)) < 0.22
            assert abs(r.n - len(sa)) < 0.35 * len(sa)
    assert [r.r for r in sorted(got)[-2:]] == [1.0, 0.0]
    parts = spark.createDataFrame([(1, "a b c d e f g"), (1, "h i j k l m"), (2, ""), (2, "a b c d e"), (None, ""), (3, " ".join(map(str, range(900))))], "g long, t string")
    merged = {r.g: r.s for r in fp.merge(fp.with_sketches(parts, {"s": "t"}), ["g"], "s").collect()}
    assert [len(merged[g]) for g in (1, 2, None, 3)] == [5, 1, 0, fp.K]


def test_repeated_rows_null_ids_and_no_rows(spark):
    rows = [(1, "a b c d"), (1, "a b c d"), (1, "other text"), (None, "null id"), (2, "z" * 9)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert sorted(r.n_chars for r in fp.edited(docs).collect()) == [7, 7, 7, 9, 10]
    one = fp.edited(docs.filter("doc_id = 2")).collect()
    assert one[0].edited_sha256 == hashlib.sha256(b"z" * 9).hexdigest()
    assert fp.edited(docs.limit(0)).count() == 0
