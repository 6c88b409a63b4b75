import random
import zlib

import numpy as np
import pytest

from cyclefold.llm import toxicity as tox


def corpus(n, seed):
    """Invented prose in two languages; toxic texts hold an inflected stem or a two-word phrase."""
    draw = random.Random(seed)
    parts = {"en": ["the", "and", "of", "thon", "erin", "ouhe", "ing"], "de": ["der", "und", "nicht", "schb", "erung", "keit"]}
    texts, labels = [], []
    for _ in range(n):
        lang = draw.choice(list(parts))
        words = ["".join(draw.choice(parts[lang]) for _ in range(draw.choice([1, 1, 2, 3]))) for _ in range(draw.randrange(5, 120))]
        bad = draw.random() < 0.5
        if bad:
            for _ in range(draw.randrange(1, 4)):
                at = draw.randrange(len(words))
                words[at:at] = [draw.choice(["zgwor", "vyxla"]) + draw.choice("aeiou") + draw.choice(["", "st", "ch"])]
        texts.append(" ".join(words) + ".")
        labels.append(int(bad))
    return texts, labels


@pytest.fixture(scope="module")
def model():
    texts, labels = corpus(800, 1)
    return tox.train([tox.words_of(t) for t in texts], labels)


def test_held_out_accuracy(model):
    texts, labels = corpus(600, 2)
    got = tox.Scorer(model)(texts) >= tox.THRESHOLD
    assert (got == np.array(labels)).mean() > 0.97


def test_scores_do_not_depend_on_batches_or_blocks(model, monkeypatch):
    texts, _ = corpus(40, 3)
    texts += [None, "", " ".join(texts)]
    whole = tox.Scorer(model)(texts)
    single = tox.Scorer(model)
    assert np.allclose(whole, [single([t])[0] for t in texts], atol=1e-5)
    monkeypatch.setattr(tox, "BLOCK_WORDS", 16)
    assert np.allclose(whole, tox.Scorer(model)(texts), atol=1e-5)
    assert whole[-3] == whole[-2]


def test_hashes_against_plain_loops():
    words = ["a", "héllo", "ab", "x" * 40]
    row, count = tox.hashes([w.encode() for w in words])
    at = 0
    for w, n in zip(words, count, strict=True):
        alone, one = tox.hashes([w.encode()])
        assert one[0] == n and (row[at : at + n] == alone).all()
        at += n
    assert count[0] == 1 + 1 and at == len(row)


def plain_logit(net, text):
    """The network word by word."""
    words = [*text, None, None] if text else [None, None, None]
    vector = []
    for w in words:
        rows = [] if w is None else tox.hashes([w])[0] % len(net.p["embedding"])
        vector.append([sum(float(net.p["embedding"][r, d]) for r in rows) / max(1, len(rows)) for d in range(tox.DIM)])
    z, k = float(net.p["intercept"][0]), 0
    for w, width in enumerate(tox.WIDTHS):
        for f in range(tox.FILTERS):
            best = max(
                sum(vector[i + j][d] * net.p["filters"][w, j, d, f] for j in range(width) for d in range(tox.DIM)) + net.p["bias"][w, f]
                for i in range(len(words) - 2)
            )
            z += max(best, 0.0) * net.p["weight"][k]
            k += 1
    return z


def test_convolution_and_gradients_against_plain_loops():
    draw = np.random.default_rng(3)
    texts = [[b"one", b"word", b"more", b"one"], [], [b"short"], [b"h\xc3\xa9llo", b"one", b"x", b"yy", b"zzz", b"word"]]
    net = tox.Net(texts, draw, buckets=64)
    for k, v in net.p.items():
        net.p[k] = draw.normal(0, 0.5, v.shape) * (v != 0 if k == "filters" else 1)
    some, y = np.arange(4), np.array([1.0, 0.0, 1.0, 0.0])
    assert np.allclose(net.forward(some)[0], [plain_logit(net, t) for t in texts], atol=1e-9)

    def loss():
        z = np.array([plain_logit(net, t) for t in texts])
        return float(np.mean(np.logaddexp(0, z) - y * z))

    grad, used = net.gradients(some, y)
    full = grad | {"embedding": np.zeros(net.p["embedding"].shape)}
    full["embedding"][used] = grad["embedding"]
    for k, g in full.items():
        places = [tuple(draw.integers(0, n) for n in g.shape) for _ in range(25)] + [tuple(np.unravel_index(np.abs(g).argmax(), g.shape))]
        for at in places:
            if k == "filters" and at[1] >= tox.WIDTHS[at[0]]:
                continue
            was, step = net.p[k][at], 1e-6
            net.p[k][at] = was + step
            up = loss()
            net.p[k][at] = was - step
            down = loss()
            net.p[k][at] = was
            assert abs((up - down) / (2 * step) - g[at]) < 1e-6, (k, at)


def test_query_edge_cases(spark):
    texts, labels = corpus(300, 4)
    rows = [(i, t, 1.0) for i, t in enumerate(texts)] + [(5000, None, 1.0), (5001, "", 1.0), (None, texts[0], 1.0), (0, texts[0], 1.0)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, score double")
    marks = [(i, y) for i, y in enumerate(labels)]
    flipped = [(i, 1 - y) if zlib.crc32(str(i).encode()) % 3 == 1 else (i, y) for i, y in marks]
    schema = "doc_id long, toxic int"
    marks = spark.createDataFrame([*marks, (None, 1), (1, None), *marks[:5]], schema)
    flipped = spark.createDataFrame([*flipped, (None, 0), (1, None)], schema)
    a, b = tox.fit(docs, marks, sample=60), tox.fit(docs, flipped, sample=60)
    assert (a.embedding == b.embedding).all() and a.intercept == b.intercept  # held-out labels are not learned from
    got = tox.scored(docs, a, ["doc_id"]).collect()
    assert len(got) == len(rows) and all(0 <= r.score <= 1 for r in got)
    kept = tox.clean(docs, marks)
    assert kept.columns == docs.columns
    none = tox.fit(docs, marks.limit(0))
    assert {r.score for r in tox.scored(docs, none, ["doc_id"]).collect()} == {0.0}
    assert tox.scored(docs.limit(0), a, ["doc_id"]).count() == 0
