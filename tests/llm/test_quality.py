import random
import re
from collections import Counter

import duckdb

from cyclefold.llm import quality


def brute(text):
    text = text or ""
    words = re.findall(r"[^\x20\x09-\x0D]+", text)
    windows = [tuple(words[i : i + 8]) for i in range(len(words) - 7)]
    count = Counter(windows)
    inside = {i + k for i, w in enumerate(windows) if count[w] > 1 for k in range(8)}
    lines = [x for x in text.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    return (len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text)), len(lines) - len(set(lines)), len(inside), len(lines))


def test_measures_against_brute_force():
    draw = random.Random(1)
    for k in range(300):
        words = [draw.choice(["a", "bé", "#c", "d|", "\x85", "\x1c"]) + str(draw.randrange(1 + k % 7)) for _ in range(draw.randrange(0, 80))]
        text = "".join(w + draw.choice([" ", "\n", "\t", " \n", "  "]) for w in words)
        assert quality.measure(text) == brute(text), repr(text)
    assert quality.measure(None) == (0, 0, 0, 0, 0, 0)
    assert quality.measure("w " * 30000)[4] == 30000


def doc(n, extra=""):
    return " ".join(f"word{n}x{i}" for i in range(40)) + extra


def brute_kept(rows):
    """(id, text, host) to the ids kept, rule by rule in plain Python."""
    seen = {}
    for doc_id, text, host in rows:
        n, _, symbols, dup, repeat, lines = brute(text)
        doubt = (100 * symbols / (10 * n) if n else 0, 100 * dup / (30 * lines) if lines else 0)
        seen.setdefault(host, []).append((doc_id, n < 20, 100 * repeat > 30 * n, doubt))
    fails = {h: [sum(d[1] for d in ds), sum(d[2] for d in ds), *(sum(d[3][k] > 1 for d in ds) for k in (0, 1))] for h, ds in seen.items()}
    n = {h: len(ds) for h, ds in seen.items()}
    total = sum(n.values())
    priors = []
    for r in range(4):
        mean = min(max(sum(f[r] for f in fails.values()) / total, 1e-6), 1 - 1e-6)
        spread = sum(n[h] * (fails[h][r] / n[h] - mean) ** 2 for h in n)
        scale = total - sum(x * x for x in n.values()) / total
        between = (spread - (len(n) - 1) * mean * (1 - mean)) / scale if scale > 0 else 0
        heaviest = max(1, total / len(n))
        weight = min(max(mean * (1 - mean) / between - 1 if between > 1e-9 else heaviest, 1), heaviest)
        priors.append((mean * weight, weight))
    kept = []
    for h, ds in seen.items():
        rate = [(fails[h][r] + a) / (n[h] + w) for r, (a, w) in enumerate(priors)]
        allowed = [1 + 3 * (1 - x / 0.5) if x < 0.5 else 1 - 0.75 * (x - 0.5) / 0.5 for x in rate[2:]]
        for doc_id, few, repeats, doubt in ds:
            if not (few or repeats or max(rate) >= 0.8) and all(x <= y for x, y in zip(doubt, allowed, strict=True)):
                kept.append(doc_id)
    return kept


def test_hosts_and_edge_cases(spark):
    some, gross = " ## $$$ ** ##", " " + " ".join("#" * k for k in range(1, 12))  # doubts of about 2 and 13
    rows = [(i, doc(i), "good", 0) for i in range(30)] + [(100, doc(100, some), "good", 0), (101, doc(101, gross), "good", 0)]
    rows += [(200 + i, doc(200 + i, some), "bad", 0) for i in range(40)] + [(300, doc(300), "bad", 0)]
    rows += [(600 + i, doc(600 + i, some if i % 3 else ""), "doubtful", 0) for i in range(30)] + [(650, doc(650, " # $"), "doubtful", 0)]
    rows += [(400, doc(400, some), "tiny", 0), (500, None, None, 0), (501, doc(501), None, 0), (501, doc(501), None, 0)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, n_words int")
    got = {r.row.doc_id: r for r in quality.verdicts(docs, ["doc_id"]).collect()}
    assert all(got[i].kept for i in range(30)) and got[100].kept and got[501].kept and not got[101].kept
    assert not any(got[200 + i].kept for i in range(40)) and not got[300].kept  # a condemned host loses also what breaks no rule
    assert not any(got[600 + i].kept for i in range(30) if i % 3) and got[600].kept and got[650].kept
    assert not got[500].kept and got[500].base_failed
    assert sorted(r[0] for r in rows if got[r[0]].kept) == sorted(brute_kept([r[:3] for r in rows]))
    kept = quality.keep_good(docs)
    assert kept.columns == docs.columns
    assert Counter(r.doc_id for r in kept.collect()) == Counter(r[0] for r in rows if got[r[0]].kept)
    assert quality.verdicts(docs.limit(0), ["doc_id"]).count() == 0
    rates = {r.host: r.rate_symbols for r in quality.host_verdicts(quality.measured(docs, ["doc_id"])).collect()}
    assert 0 < rates["tiny"] < 1 and rates["good"] < 0.2 < 0.8 < rates["bad"]


def test_kept_over_whole_tables(spark):
    """The given table, and the same with hosts made of its bad documents, against plain Python and SQL."""
    table = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text", "source")
    bad = sorted((r.doc_id, r.text, f"farm{r.doc_id % 3}") for r in table.collect() if not quality.verdict_alone(r.text))
    for docs in (table, table.unionByName(spark.createDataFrame(bad * 3, table.schema))):
        rows = [tuple(r) for r in docs.collect()]
        got = quality.verdicts(docs, ["doc_id"]).collect()
        assert Counter(r.row.doc_id for r in got if r.kept) == Counter(brute_kept(rows))
        con = duckdb.connect()
        con.register("documents", docs.toPandas())
        assert Counter(r[0] for r in con.execute(f"SELECT doc_id FROM ({quality.ORACLE}) WHERE kept").fetchall()) == Counter(r.row.doc_id for r in got if r.kept)


def test_priors():
    assert quality.prior(0, 0, 0, 0, 0) == (1.0, 1.0)
    a, b = quality.prior(10, 100, 1000, 50, 25.0)  # no spread between hosts: the weight of a host of mean size
    assert abs(a - 5) < 1e-9 and abs(b - 5) < 1e-9
    a, b = quality.prior(2, 100, 5000, 50, 50.0)  # all or none: as little weight as can be
    assert abs(a + b - 1) < 1e-9
