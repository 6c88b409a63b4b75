import zlib

import numpy as np
from pyspark.sql import SparkSession

import corpus_pipeline
from cyclefold.llm import packing, pii, quality, toxicity


def plain(rows, model, allowed):
    """The stages on a list, row by row."""
    rows = [r for r in rows if _good(r, allowed)]
    scorer = toxicity.Scorer(model)
    rows = [r for r in rows if scorer([r[1]])[0] < toxicity.THRESHOLD]
    sets = [_shingles(r[1]) for r in rows]
    root = list(range(len(rows)))
    for i in range(len(rows)):
        for j in range(i):
            if 5 * len(sets[i] & sets[j]) >= 4 * len(sets[i] | sets[j]):
                a, b = root[i], root[j]
                root = [min(a, b) if x in (a, b) else x for x in root]
    least = {}
    for r, k in zip(rows, root, strict=True):
        least[k] = min(least.get(k, r[0]), r[0])
    rows = [r for r, k in zip(rows, root, strict=True) if r[0] == least[k]]
    encoder = packing.WordEncoder(packing.default_vocabulary())
    out = set()
    for doc_id, text, *_ in rows:
        ids = encoder.tokenizer.encode(pii.redacted(text), add_special_tokens=False).ids + [1]
        for k in range(0, len(ids), 4096):
            piece = np.array(ids[k : k + 4096], "<u4")
            out.add((doc_id, k // 4096, k, len(piece), zlib.crc32(piece.tobytes())))
    return out


def _shingles(text):
    """Near-duplicates share 0.8 of their five-word shingles."""
    words = (text or "").encode().lower().split()
    return {tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))}


def _good(row, hosts):
    words, _, symbols, dup, repeat, lines = quality.measure(row[1])
    if words < 20 or 100 * repeat > 30 * words or hosts[row[3]].condemned:
        return False
    return 100 * symbols / (10.0 * words) <= hosts[row[3]].allowed_symbols and 100 * dup / (30.0 * lines) <= hosts[row[3]].allowed_dup_lines


def test_stages_against_a_plain_version(spark: SparkSession, tmp_path):
    source = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    labels = spark.read.parquet("/root/testdata/sf0.001/labels.parquet")
    source.write.parquet(str(tmp_path / "documents.parquet"))
    labels.write.parquet(str(tmp_path / "labels.parquet"))
    rows = sorted(tuple(r) for r in source.collect())
    allowed = {r.host: r for r in quality.host_verdicts(quality.measured(source, ["doc_id"])).collect()}
    kept = source.filter(source.doc_id.isin([r[0] for r in rows if _good(r, allowed)]))
    want = plain(rows, toxicity.fit(kept, labels), allowed)
    got = corpus_pipeline.run(spark, str(tmp_path)).collect()
    assert {(r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in got} == want and len(got) == len(want)


def test_stages_keep_the_columns(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    odd = docs.limit(3).unionByName(spark.createDataFrame([(None, None, None, None, None), (1, "", "en", "s", 0)], docs.schema))
    for some in (odd, docs.limit(0)):
        for _, stage in corpus_pipeline.STAGES[:-1]:
            out = stage(spark, some, "/root/testdata/sf0.001")
            assert out.schema.simpleString() == docs.schema.simpleString()
            out.count()
