import random

import pytest

from cyclefold.llm import token_counts as tc


@pytest.fixture(scope="module")
def encoder():
    return tc.ChunkedEncoder(tc.default_model(), chunk=64, overlap=4)


def test_spliced_ids_are_the_library_ids(encoder):
    draw = random.Random(3)
    alphabets = ["abc ", "a", "étä ñ\n", "the of and ing tion ", "日本語😀x ", " ", "\x00a\t ", "▁ a", "<s></s> ", "12 34"]
    for k in range(400):
        chars = draw.choice(alphabets) if k % 2 else "".join(draw.sample(alphabets, 3))
        text = "".join(draw.choice(chars) for _ in range(draw.randrange(0, 900)))
        assert encoder.ids(text) == encoder.encoder.encode(text), repr(text)
        assert encoder.count(text) == len(encoder.encoder.encode(text))
    bytes_only = "\U00013000" * 300  # no token that could be a boundary
    assert encoder.ids(bytes_only) == encoder.encoder.encode(bytes_only)
    assert encoder.widened and encoder.whole


def test_production_chunks():
    whole = tc.ChunkedEncoder(tc.default_model())
    draw = random.Random(4)
    text = " ".join("".join(draw.choice(["th", "er", "on", "ß", "ing", "q"]) for _ in range(draw.randrange(1, 6))) for _ in range(40000))
    assert whole.ids(text) == whole.encoder.encode(text)
    assert not whole.whole


def test_edge_cases(spark):
    rows = [(1, None, 5), (2, "", 5), (3, "a b", 5), (3, "a b", 5), (None, "x" * 40000, 5)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, n_tokens int")
    got = {(r.doc_id, r.n_bytes, r.n_tokens, r.over_limit) for r in tc.token_counts(docs).collect()}
    n = len(tc.ChunkedEncoder(tc.default_model()).encoder.encode("x" * 40000))
    assert got == {(1, 0, 0, False), (2, 0, 0, False), (3, 3, 2, False), (None, 40000, n, n > 4096)}
    assert tc.token_counts(docs).count() == 5
    assert tc.token_counts(docs.limit(0)).count() == 0
