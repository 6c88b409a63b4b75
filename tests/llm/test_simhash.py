import random
import re

import xxhash

from cyclefold.llm import simhash


def brute_fingerprint(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))]
    hashed = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashed) > len(hashed))


def brute_components(prints, radius=3):
    root = list(range(len(prints)))
    for i in range(len(prints)):
        for j in range(i):
            if (prints[i] ^ prints[j]).bit_count() <= radius:
                a, b = root[i], root[j]
                root = [min(a, b) if r in (a, b) else r for r in root]
    return root


def test_fingerprint():
    for text in (None, "", " \n", "One", "one TWO", "a b c", "a  b\tc d É Ü é", "x y z w q r", "w " * 5000):
        assert simhash.fingerprint(text) == brute_fingerprint(text), text


def test_components_against_all_pairs(spark):
    draw = random.Random(5)
    prints = [draw.getrandbits(64) for _ in range(60)]
    for p in prints[:12]:  # chains and dense balls around some
        for _ in range(draw.randrange(1, 25)):
            p ^= sum(1 << draw.randrange(64) for _ in range(draw.randrange(1, 4))) & (2**64 - 1)
            prints.append(p & (2**64 - 1))
    base = draw.getrandbits(64)
    prints += [base ^ (1 << i) ^ (1 << j) for i in range(12) for j in range(i)]
    prints = sorted(set(prints))
    signed = [p - 2**64 if p >> 63 else p for p in prints]
    df = spark.createDataFrame([(s,) for s in signed], "fp long")
    for n in (1, 1 << 17, 1 << 26):  # four, five and six blocks
        found = {r.node: r.root for r in simhash.components.of_edges(simhash.links(df, n)).collect()}
        got = [found.get(s, s) for s in signed]
        want = brute_components(prints)
        pairs = set(zip(got, want, strict=True))
        assert len(pairs) == len({a for a, _ in pairs}) == len({b for _, b in pairs})


def test_groups_edge_cases(spark):
    long = "the quick brown fox jumps over the lazy dog again and again " * 40
    rows = [(3, long, 1), (1, long, 1), (2, long.upper(), 1), (7, None, 1), (6, "", 1), (9, "lonely text here", 1), (9, "lonely text here", 1), (None, "other words for none", 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, fp int")
    got = sorted((r.doc_id is None, r.doc_id, r.component_id) for r in simhash.groups(docs).collect())
    assert [(d, c) for _, d, c in got[:-1]] == [(1, 1), (2, 1), (3, 1), (6, 6), (7, 6), (9, 9), (9, 9)]
    assert got[-1][1:] == (None, None)
    kept = simhash.deduplicate(docs)
    assert kept.columns == docs.columns
    assert sorted(str(r.doc_id) for r in kept.collect()) == ["1", "6", "9", "None"]
    assert simhash.groups(docs.limit(0)).count() == 0
