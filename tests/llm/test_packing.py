import random
import zlib
from collections import defaultdict

import numpy as np

from cyclefold.llm import packing


def test_ids_are_the_library_ids():
    encoder = packing.WordEncoder(packing.default_vocabulary())
    draw = random.Random(2)
    texts = ["", " ", "It's we'll''s 'S x'Re", "<|endoftext|> a", "ǅ ﬁ Σας ΟΔΟΣ", "é a b\x1cc\x85d", "1234 ½²x µªº ×÷ ß ÿ Þ", "日本 語😀", "a­b ¿que?"]
    for _ in range(300):
        texts.append("".join(draw.choice("abcDEÉßé '.!s12\n\t-") for _ in range(draw.randrange(200))))
    for _ in range(2):
        got = encoder.batch(texts)
        for text, raw in zip(texts, got, strict=True):
            want = encoder.tokenizer.encode(text, add_special_tokens=False).ids
            assert np.frombuffer(raw, "<u4").tolist() == want, repr(text)


def best_fit_decreasing(sizes, capacity):
    gaps = []
    for s in sorted(sizes, reverse=True):
        fit = [g for g in gaps if g >= s]
        if fit:
            gaps.remove(min(fit))
            gaps.append(min(fit) - s)
        else:
            gaps.append(capacity - s)
    return len(gaps)


def test_plans():
    draw = random.Random(8)
    for k in range(300):
        capacity = draw.choice([10, 64, 100])
        low, high = draw.choice([(1, capacity), (1, capacity // 3), (capacity // 3, capacity), (capacity // 2, capacity)])
        histogram = {draw.randint(low, high): draw.randint(1, 30) for _ in range(draw.randint(1, 12))}
        sizes = [s for s, n in histogram.items() for _ in range(n)]
        plan = packing.Plan(histogram, capacity)
        bins, ranks = defaultdict(list), defaultdict(list)
        for length, rank, sequences, q, first, offset in plan.rows:
            for i in range(sequences * q):
                bins[first + i // q].append((offset + i % q * length, length))
                ranks[length].append(rank + i)
        assert {s: sorted(r) for s, r in ranks.items()} == {s: list(range(n)) for s, n in histogram.items()}
        for inside in bins.values():
            at = 0
            for offset, length in sorted(inside):
                assert offset == at
                at += length
            assert at <= capacity and sum(3 * length > capacity for _, length in inside) <= 2
        assert len(bins) == plan.sequences >= -(-sum(sizes) // capacity)
        assert len(bins) <= best_fit_decreasing(sizes, capacity) + 1
    assert packing.Plan({}, 8).arrays()["rank"].size == 0


def test_pack_edge_cases(spark):
    rows = [(1, None, 0), (2, "", 0), (3, "a b c " * 3000, 0), (None, "x", 0), (4, "one two", 0), (4, "one two", 0)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, length int").repartition(3)
    got = packing.pack(docs).collect()
    assert sorted((r.length for r in got if r.doc_id == 3), reverse=True) == [4096, 4096, 809]
    assert [r.length for r in got if r.doc_id in (1, 2)] == [1, 1] and len(got) == 8
    assert {r.ids_crc32 for r in got if r.doc_id in (1, 2)} == {zlib.crc32(b"\1\0\0\0")}
    by = defaultdict(list)
    for r in got:
        by[r.sequence_id].append((r.offset, r.length))
    assert len(by) == 3
    for inside in by.values():
        ends = 0
        for offset, length in sorted(inside):
            assert offset == ends
            ends += length
        assert ends <= 4096
    assert packing.pack(docs.limit(0)).count() == 0
