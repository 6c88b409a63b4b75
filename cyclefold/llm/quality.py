"""Quality rules per document, and verdicts per host by shrunken failure rates.

Method. Each document is measured whole (`measure`) and held against the rules: too few words, too
many repeated ones, too many symbols, too many repeated lines. The first two are *hard*, they reject a
document by themselves; the others are *soft*, a document may exceed what they allow so many times as
its host's verdict says. For every host and rule the share of documents that fail is shrunk towards the
corpus: with a beta prior whose mean and weight are fitted to all hosts by moments, the posterior rate of
a host with f failures in n documents is (f + a) / (n + a + b), so a host with few documents cannot be
condemned by one of them. The verdict that is joined back to the documents:

* a host of which a rule's rate reaches ``CONDEMNED`` loses all its documents;
* else its rate of each soft rule moves that rule's limit: ``TOLERANCE`` times as much is allowed on a host
  without failures, the rule itself at a rate of ``HOST_LIMIT``, a ``TOLERANCE``-th at a rate of one, in
  between in proportion. A host that mostly fails a rule is thus held to a stricter one.

The prior weighs at most as much as a host of mean size, so a host of more documents speaks for itself.

Words are maximal runs without the six ASCII white-space characters. Defined results: null
text = empty text (no words, hence rejected); a null host is a host of its own; repeated
rows count once each; an empty table gives an empty result.
"""

from __future__ import annotations

from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

WINDOW = 8
SYMBOLS = "#*$%&|<>"
SPACES = " \t\n\r\x0b\x0c"
MIN_WORDS = 20
MAX_REPEAT_PERCENT = 30
#: Soft rules: symbols per word and duplicated lines per line, in percent.
MAX_SYMBOL_PERCENT = 10
MAX_DUP_LINE_PERCENT = 30
#: The rate of a soft rule at which a host's documents are held to the rule itself, how far the limit moves
#: on either side, and the rate of any rule from which a host loses all its documents.
HOST_LIMIT = 0.5
TOLERANCE = 4.0
CONDEMNED = 0.8
HARD, SOFT = ("few_words", "repeats"), ("symbols", "dup_lines")

_MIX = np.array([pow(0x9E3779B97F4A7C15, k + 1, 1 << 64) | 1 for k in range(WINDOW)], dtype=np.uint64)


def repeated_words(words: list[bytes]) -> int:
    """Words inside 8-word windows that occur at least twice, every occurrence counted."""
    n = len(words) - WINDOW + 1
    if n < 2:
        return 0
    ids = np.fromiter(map(hash, words), np.int64, len(words)).view(np.uint64)
    mixed = np.zeros(n, np.uint64)
    for k in range(WINDOW):
        mixed += (ids[k : k + n] ^ (ids[k : k + n] >> np.uint64(29))) * _MIX[k]
    ordered = np.sort(mixed)
    if not (ordered[1:] == ordered[:-1]).any():
        return 0  # equal windows have equal hashes
    _, inverse, count = np.unique(mixed, return_inverse=True, return_counts=True)
    maybe = np.flatnonzero(count[inverse] > 1)
    exact = Counter(tuple(words[i : i + WINDOW]) for i in maybe)
    covered = np.zeros(len(words) + 1, np.int64)
    for i in maybe:
        if exact[tuple(words[i : i + WINDOW])] > 1:
            covered[i] += 1
            covered[i + WINDOW] -= 1
    return int((np.cumsum(covered) > 0).sum())


def measure(text: str | None) -> tuple[int, int, int, int, int, int]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_lines (lines with a word)."""
    text = text or ""
    words = text.encode("utf-8", "surrogatepass").split()
    seen: set[str] = set()
    lines = duplicates = 0
    for line in text.split("\n"):
        if line.strip(SPACES):
            lines += 1
            duplicates += line in seen
            seen.add(line)
    return (
        len(words),
        len(text) - sum(map(text.count, SPACES)),
        sum(map(text.count, SYMBOLS)),
        duplicates,
        repeated_words(words),
        lines,
    )


def verdict_alone(text: str | None) -> bool:
    """Whether a text breaks no rule, whatever its host."""
    words, _, symbols, dup, repeat, lines = measure(text)
    hard = words < MIN_WORDS or 100 * repeat > MAX_REPEAT_PERCENT * words
    return not hard and 100 * symbols <= MAX_SYMBOL_PERCENT * words and 100 * dup <= MAX_DUP_LINE_PERCENT * lines


_COUNTS = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines"]


def doubts() -> dict[str, F.Column]:
    """By soft rule, how many times a document exceeds it; 1 is just allowed."""
    share = lambda c, of, most: F.coalesce(F.try_divide(100 * F.col(c), F.lit(float(most)) * F.col(of)), F.lit(0.0))
    return {"symbols": share("n_symbols", "n_words", MAX_SYMBOL_PERCENT), "dup_lines": share("n_dup_lines", "n_lines", MAX_DUP_LINE_PERCENT)}


def failures() -> dict[str, F.Column]:
    """By rule, whether a document fails it."""
    hard = {"few_words": F.col("n_words") < MIN_WORDS, "repeats": 100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * F.col("n_words")}
    return hard | {r: d > 1 for r, d in doubts().items()}


def measured(docs: DataFrame, keep: list[str], host: str = "source") -> DataFrame:
    """The columns ``keep`` and ``host`` of ``docs`` inside struct ``row``, and the counts of its text."""
    fields = list(dict.fromkeys([*keep, host]))
    row = F.struct(*[F.col(c) for c in fields])
    schema = pa.schema([(c, pa.int64()) for c in _COUNTS])

    def run(batches):
        for batch in batches:
            for part in common.slices(batch):
                rows = [measure(t) for t in part.column(1).to_pylist()]
                counts = np.array(rows, np.int64).reshape(-1, len(_COUNTS))
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), *(pa.array(counts[:, i]) for i in range(len(_COUNTS)))],
                    names=["row", *schema.names],
                )

    given = docs.select(row.alias("row"), F.col("text").alias("text"))
    out = f"row {given.schema['row'].dataType.simpleString()}, " + ", ".join(f"{c} long" for c in _COUNTS)
    return (
        given.mapInArrow(run, out)
        .withColumn("host", F.col("row").getField(host))
        .withColumn("base_failed", failures()["few_words"] | failures()["repeats"])
    )


def host_verdicts(per_document: DataFrame) -> DataFrame:
    """host, n_docs; for each rule f_ (failures) and rate_ (posterior mean); for soft rules allowed_; condemned.

    Prior by moments over all hosts: the variance of the rates between hosts beyond what n draws
    explain gives the prior's weight. Only one row of sums comes to the driver.
    """
    counts = [F.count_if(failed).alias(f"f_{r}") for r, failed in failures().items()]
    hosts = common.materialise(per_document.groupBy("host").agg(F.count("*").alias("n_docs"), *counts))
    prior = _priors(hosts)
    rates = {r: (F.col(f"f_{r}") + F.lit(a)) / (F.col("n_docs") + F.lit(a + b)) for r, (a, b) in prior.items()}
    judged = hosts.withColumns({f"rate_{r}": rate for r, rate in rates.items()})
    judged = judged.withColumns({f"allowed_{r}": _allowed(F.col(f"rate_{r}")) for r in SOFT})
    return judged.withColumn("condemned", F.greatest(*(F.col(f"rate_{r}") for r in prior)) >= CONDEMNED)


def _allowed(rate: F.Column) -> F.Column:
    lenient = 1 + (TOLERANCE - 1) * (1 - rate / HOST_LIMIT)
    strict = 1 - (1 - 1 / TOLERANCE) * (rate - HOST_LIMIT) / (1 - HOST_LIMIT)
    return F.when(rate < HOST_LIMIT, lenient).otherwise(strict)


def _priors(hosts: DataFrame) -> dict[str, tuple[float, float]]:
    rules = [*HARD, *SOFT]
    n = F.col("n_docs").cast("double")
    f = {r: F.col(f"f_{r}").cast("double") for r in rules}
    row = hosts.agg(F.count("*"), F.sum(n), F.sum(n * n), *(x for r in rules for x in (F.sum(f[r]), F.sum(f[r] * f[r] / n)))).first()
    k, docs, squares = row[:3]
    return {r: prior(k, docs, squares, *row[3 + 2 * i : 5 + 2 * i]) for i, r in enumerate(rules)}


def prior(hosts: int, docs: float, squares: float, failed: float, within: float) -> tuple[float, float]:
    """The beta prior of one rule. squares: sum of n * n over hosts; within: sum of f * f / n."""
    if not hosts or not docs:
        return 1.0, 1.0
    mean = min(max(failed / docs, 1e-6), 1 - 1e-6)
    spread = within - docs * mean * mean  # sum of n (rate - mean)^2
    excess = spread - (hosts - 1) * mean * (1 - mean)
    scale = docs - squares / docs
    between = excess / scale if scale > 0 else 0.0
    heaviest = max(1.0, docs / hosts)
    weight = mean * (1 - mean) / between - 1 if between > 1e-9 else heaviest
    weight = min(max(weight, 1.0), heaviest)
    return mean * weight, (1 - mean) * weight


def judged(rows: DataFrame, hosts: DataFrame) -> DataFrame:
    """Adds ``kept``. ``hosts`` is a written table, so that its size is known when it is joined:
    Spark broadcasts it only below its threshold and else splits a hot host in a sorted join."""
    allowed = [f"allowed_{r}" for r in SOFT]
    out = rows.join(hosts.select(F.col("host").alias("of_host"), "condemned", *allowed), F.col("host").eqNullSafe(F.col("of_host")), "left")
    fine = ~F.col("base_failed") & ~F.col("condemned")
    for r, d in doubts().items():
        fine &= d <= F.col(f"allowed_{r}")
    return out.withColumn("kept", fine)


def verdicts(docs: DataFrame, keep: list[str], host: str = "source") -> DataFrame:
    """``row`` (the columns kept), the counts, base_failed and kept, one row per document."""
    rows = common.materialise(measured(docs, keep, host))
    return judged(rows, common.materialise(host_verdicts(rows)))


def keep_good(docs: DataFrame, host: str = "source") -> DataFrame:
    """The documents that stay, columns as given.

    Texts are measured twice, once for the host rates and once for the verdicts, so that no
    text is shuffled unless the hosts are too many to broadcast.
    """
    hosts = common.materialise(host_verdicts(measured(docs, [host], host)))
    return judged(measured(docs, docs.columns, host), hosts).filter("kept").select("row.*")


def op6_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return verdicts(common.table(spark, sf_dir, "documents"), ["doc_id"]).select(
        F.col("row.doc_id").cast("long").alias("doc_id"),
        "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept",
    )


_SPACE = r"[ \t\n\r\x0b\x0c]"
_WORD = r"[^ \t\n\r\x0b\x0c]+"


def _sql_prior(r: str) -> str:
    return f"""
  SELECT '{r}' AS rule, mean * weight AS a, (1 - mean) * weight AS b FROM (
    SELECT mean, least(greatest(CASE WHEN between_ > 1e-9 THEN mean * (1 - mean) / between_ - 1 ELSE heaviest END, 1.0), heaviest) AS weight FROM (
      SELECT mean, heaviest, CASE WHEN docs - squares / docs > 0 THEN (within - docs * mean * mean - (k - 1) * mean * (1 - mean)) / (docs - squares / docs) ELSE 0.0 END AS between_ FROM (
        SELECT count(*) AS k, sum(n_docs)::double AS docs, sum(n_docs * n_docs)::double AS squares, sum(f_{r} * f_{r} / n_docs::double) AS within,
          least(greatest(sum(f_{r})::double / sum(n_docs), 1e-6), 1 - 1e-6) AS mean, greatest(1.0, sum(n_docs)::double / count(*)) AS heaviest FROM h)))"""


def _sql_rate(r: str) -> str:
    return f"(f_{r} + (SELECT a FROM pr WHERE rule = '{r}')) / (n_docs + (SELECT a + b FROM pr WHERE rule = '{r}'))"


def _sql_allowed(r: str) -> str:
    rate = f"rate_{r}"
    return (
        f"CASE WHEN {rate} < {HOST_LIMIT} THEN 1 + {TOLERANCE - 1} * (1 - {rate} / {HOST_LIMIT})"
        f" ELSE 1 - {1 - 1 / TOLERANCE} * ({rate} - {HOST_LIMIT}) / {1 - HOST_LIMIT} END"
    )


_RULES = (*HARD, *SOFT)
ORACLE = f"""
WITH t AS (SELECT row_number() OVER () AS rid, doc_id, source AS host, coalesce(text, '') AS text FROM documents),
s AS (SELECT *, regexp_extract_all(text, '{_WORD}') AS words, list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '{_WORD}')) AS lines FROM t),
u AS (SELECT rid, unnest(words) AS w, generate_subscripts(words, 1) AS i FROM s),
g AS (SELECT rid, i, w || ' ' || {" || ' ' || ".join(f"lead(w, {k}) OVER o" for k in range(1, WINDOW))} AS win FROM u WINDOW o AS (PARTITION BY rid ORDER BY i)),
m AS (SELECT rid, i FROM (SELECT rid, i, count(*) OVER (PARTITION BY rid, win) AS n FROM g WHERE win IS NOT NULL) WHERE n > 1),
c AS (SELECT rid, count(DISTINCT i + k) AS n_repeat_words FROM m, range({WINDOW}) AS r(k) GROUP BY rid),
d AS (SELECT doc_id, host, len(words) AS n_words, length(regexp_replace(text, '{_SPACE}', '', 'g')) AS word_chars,
        length(text) - length(regexp_replace(text, '[{SYMBOLS}]', '', 'g')) AS n_symbols, len(lines) - len(list_distinct(lines)) AS n_dup_lines,
        coalesce(n_repeat_words, 0) AS n_repeat_words, len(lines) AS n_lines FROM s LEFT JOIN c USING (rid)),
e AS (SELECT *, n_words < {MIN_WORDS} AS few_words, 100 * n_repeat_words > {MAX_REPEAT_PERCENT} * n_words AS repeats,
        CASE WHEN n_words > 0 THEN 100 * n_symbols / ({float(MAX_SYMBOL_PERCENT)} * n_words) ELSE 0.0 END AS d_symbols,
        CASE WHEN n_lines > 0 THEN 100 * n_dup_lines / ({float(MAX_DUP_LINE_PERCENT)} * n_lines) ELSE 0.0 END AS d_dup_lines FROM d),
h AS (SELECT host, count(*) AS n_docs, count(*) FILTER (few_words) AS f_few_words, count(*) FILTER (repeats) AS f_repeats,
        count(*) FILTER (d_symbols > 1) AS f_symbols, count(*) FILTER (d_dup_lines > 1) AS f_dup_lines FROM e GROUP BY host),
pr AS ({" UNION ALL ".join(map(_sql_prior, _RULES))}),
v AS (SELECT *, {", ".join(f"{_sql_rate(r)} AS rate_{r}" for r in _RULES)} FROM h),
x AS (SELECT host, greatest({", ".join(f"rate_{r}" for r in _RULES)}) >= {CONDEMNED} AS condemned, {", ".join(f"{_sql_allowed(r)} AS allowed_{r}" for r in SOFT)} FROM v)
SELECT doc_id, n_words::bigint AS n_words, word_chars::bigint AS word_chars, n_symbols::bigint AS n_symbols, n_dup_lines::bigint AS n_dup_lines, n_repeat_words::bigint AS n_repeat_words,
  few_words OR repeats AS base_failed, NOT (few_words OR repeats) AND NOT condemned AND d_symbols <= allowed_symbols AND d_dup_lines <= allowed_dup_lines AS kept
FROM e JOIN x ON e.host IS NOT DISTINCT FROM x.host
"""
