import random

import numpy as np

import corpus_pipeline
from cyclefold.llm import near_copies


def brute(texts):
    """The least index of each text's group, by all pairs."""
    def cut(text):
        w = (text or "").encode().lower().split()
        return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))}

    sets, root = [cut(t) for t in texts], list(range(len(texts)))
    for i, a in enumerate(sets):
        for j, b in enumerate(sets[:i]):
            if root[i] != root[j] and 5 * len(a & b) >= 4 * len(a | b):
                low, high = sorted((root[i], root[j]))
                root = [low if r == high else r for r in root]
    return root


def varied(draw, words, edits):
    out = list(words)
    for _ in range(edits):
        out[draw.randrange(len(out))] = f"new{draw.randrange(10**9)}"
    return " ".join(out)


def test_groups_against_all_pairs(spark):
    draw = random.Random(3)
    line = " ".join(f"common{k}" for k in range(12))
    texts = [None, "", " \n", "one two", "One  TWO", "three four"]
    for _ in range(40):  # families around the limit, chains, and a line that unrelated texts share
        words = [f"w{draw.randrange(10**6)}" for _ in range(draw.randrange(20, 200))]
        texts += [varied(draw, words, draw.randrange(0, 1 + len(words) // 25)) for _ in range(draw.randrange(1, 6))] + [f"{line} {' '.join(words[:9])}"]
    words = [f"d{k}" for k in range(100)]
    for _ in range(80):  # a dense group and a chain away from it
        texts.append(varied(draw, words, 1))
    for k in range(0, 60, 2):
        words[k] = f"e{k}"
        texts.append(" ".join(words))
    draw.shuffle(texts)
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    assert [r.component_id for r in near_copies.groups(docs).orderBy("doc_id").collect()] == brute(texts)


def test_stage_joins_what_three_bits_leave(spark):
    """Real tables: every pair of five-word similarity 0.8 or more, of which 12 differ in 5 to 10 bits."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    rows = sorted((r.doc_id, r.text) for r in docs.collect())
    want = {rows[r][0] for r in brute([t for _, t in rows])}
    got = corpus_pipeline.near_duplicates(spark, docs, "/root/testdata/sf0.01")
    assert got.columns == docs.columns
    assert sorted(r.doc_id for r in got.collect()) == sorted(want)


def test_ids(spark):
    rows = [(3, "a b c d e f"), (1, "A b  c d e f"), (9, "lonely"), (9, "lonely"), (None, "a b c d e f"), (None, "x")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert sorted(str(r.doc_id) for r in near_copies.deduplicate(docs).collect()) == ["1", "9", "None", "None"]
    assert near_copies.deduplicate(docs.limit(0)).count() == 0


def test_one_shingle_of_many_texts_is_cut_into_blocks(spark, monkeypatch):
    monkeypatch.setattr(near_copies, "BLOCK", 16)
    draw = random.Random(9)
    line = " ".join(f"common{k}" for k in range(30))
    texts = [f"{line} {' '.join(f'x{draw.randrange(40)}' for _ in range(draw.randrange(4, 9)))}" for _ in range(150)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    assert [r.component_id for r in near_copies.groups(docs).orderBy("doc_id").collect()] == brute(texts)


def test_repeated_ids_leave_one_row(spark):
    rows = [(7, f"{k} b c d e f g h", k) for k in range(20)] + [(8, "x", 0), (5, None, 0), (6, "", 0)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, component_id int")
    for some in (docs, docs.repartition(7)):
        got = near_copies.deduplicate(some)
        assert got.columns == docs.columns
        assert sorted(r.doc_id for r in got.collect()) == [5, 7, 8]
        first = got.filter("doc_id = 7").first().component_id if some is docs else first
    assert near_copies.deduplicate(docs.repartition(7)).filter("doc_id = 7").first().component_id == first


def test_a_shared_passage_is_one_meeting(spark):
    """Its shingles all have the same texts, which are paired there once and not once a shingle."""
    passage = " ".join(f"p{k}" for k in range(60))
    texts = [f"{passage} {' '.join(f'x{i}y{k}' for k in range(40))}" for i in range(12)]
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "key long, text string")
    met = near_copies.meetings(near_copies.summaries(docs, 12))
    least = {r.key: r.least for r in met.groupBy("key").agg({"at": "min"}).withColumnRenamed("min(at)", "least").collect()}
    assert met.groupBy("key").count().filter("count > 1").count() < 12 and met.count() < 30
    first = {r.key: r.prefix for r in near_copies.summaries(docs, 12).collect()}
    assert all(least[k] == min(a for a, x in enumerate(p) if sum(x in q for q in first.values()) > 1) for k, p in first.items() if k in least)


def test_counts_keep_every_similar_pair():
    draw = random.Random(5)
    ruled_out = 0
    for _ in range(300):
        a = {draw.getrandbits(63) for _ in range(draw.randrange(1, 3000))}
        b = set(draw.sample(sorted(a), draw.randrange(len(a) + 1))) | {draw.getrandbits(63) for _ in range(draw.randrange(1 + len(a) // 4))}
        x, y = (np.array(sorted(s), np.int64) for s in (a, b))
        allowed = near_copies.counts_allow(len(a), near_copies.bin_counts(x), len(b), near_copies.bin_counts(y))
        assert allowed or 5 * len(a & b) < 4 * len(a | b)
        ruled_out += not allowed
    assert ruled_out > 100


def test_a_dense_group_gives_one_pair_a_text_in_a_round(spark):
    """Texts that meet at one shingle, each a component of its own: with the nearest, not with all others."""
    texts = [f"{' '.join(f'd{k}' for k in range(60))} tail{i}" for i in range(90)]
    docs = spark.createDataFrame(list(enumerate(texts)), "key long, text string")
    known = near_copies.summaries(docs, 90)
    met = known.selectExpr("7L AS token", "key", "n", "0L AS at", "key AS root", *near_copies.PROFILE)
    assert near_copies.all_pairs(met).count() == 90 * 89 // 2
    nearest = near_copies.all_pairs(met, nearest=True).collect()
    assert len(nearest) <= 89 and {k for r in nearest for k in r} == set(range(90))
