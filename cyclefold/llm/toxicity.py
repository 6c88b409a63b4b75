"""Toxicity by a convolutional text classifier, trained and run in numpy.

Method. A word's embedding is the mean of the embeddings of its hashes: the word itself and
its character n-grams, so that inflected forms of a known stem are known too. Filters of
several widths run over the sequence of embeddings, each is max-pooled over the whole text,
and a linear layer on the pooled values gives a logit. It is trained by minibatch Adam on a
bounded sample of labelled rows (at most ``SAMPLE`` per class, chosen by a hash of the id, each with
its whole text); the bound is a parameter.

Thresholds are calibrated by language on a part of the sample that is not trained on. The
language is guessed from the text's own function words; the table's lang, source, labels and
doc_id are never inputs of a score. Each language's logits are shifted so that its best
threshold becomes the common score ``THRESHOLD``.

Only rows whose crc32(doc_id as text) mod 3 is not 1 are learned from.

Defined results: null text = empty text, scored like any text; a null doc_id is not held
out and never has a label; labels that repeat a doc_id count once, the larger wins; without
labels of both classes every score is the share of toxic labels (0 without labels); an empty
table gives an empty result.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

THRESHOLD = 0.7
SAMPLE = 2500
BUCKETS = 1 << 18
DIM, FILTERS, WIDTHS = 8, 8, (1, 2, 3)
GRAMS = (3, 4, 5)
#: Words of one matrix product, and words whose embeddings a task keeps before it starts anew.
BLOCK_WORDS, KEPT_WORDS = 1 << 15, 300_000

#: Function words by which a text's language is guessed.
FUNCTION_WORDS = {
    1: "the and of to in is that it for was on are with as be by this from".split(),
    2: "der die und das den von zu mit sich des ist nicht dem ein eine für auf".split(),
    3: "le la les et des du en un une est que dans qui par pour sur au".split(),
    4: "el los las y del se por con para una su al lo como más que de".split(),
}
_LANGUAGE = {}
for _k, _words in FUNCTION_WORDS.items():
    for _w in _words:
        _LANGUAGE[_w.encode()] = 0 if _w.encode() in _LANGUAGE else _k  # shared words don't tell

_TO_SPACE = bytes(c if c >= 128 or chr(c).isalpha() else 32 for c in range(256))


def words_of(text: str | None) -> list[bytes]:
    return (text or "").lower().encode("utf-8", "surrogatepass").translate(_TO_SPACE).split()


def hashes(words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Embedding rows of the words' hashes, word after word, and how many each word has."""
    marked = [b"<%b>" % w for w in words]
    lengths = np.fromiter(map(len, marked), np.int64, len(marked))
    data = np.frombuffer(b"".join(marked), np.uint8).astype(np.uint64)
    ends = np.repeat(np.cumsum(lengths), lengths)
    at, owner = np.arange(len(data)), np.repeat(np.arange(len(words)), lengths)
    rows, owners = [np.fromiter(map(zlib.crc32, marked), np.uint64, len(marked)) * np.uint64(0x9E3779B97F4A7C15)], [np.arange(len(words))]
    for n in GRAMS:
        ok = at + n <= ends
        h = np.full(int(ok.sum()), n, np.uint64)
        for k in range(n):
            h = (h ^ data[np.flatnonzero(ok) + k]) * np.uint64(0x100000001B3)
        rows.append(h * np.uint64(0x9E3779B97F4A7C15))
        owners.append(owner[ok])
    row, who = np.concatenate(rows), np.concatenate(owners)
    by = np.argsort(who, kind="stable")
    return ((row[by] >> np.uint64(40)) % np.uint64(BUCKETS)).astype(np.int32), np.bincount(who, minlength=len(words))


@dataclass
class Model:
    """``embedding`` is None where the labels could not be learned from; ``prior`` is then the score."""

    embedding: np.ndarray | None
    filters: np.ndarray | None  # (width, position, DIM, FILTERS), zero beyond a filter's width
    bias: np.ndarray | None
    weight: np.ndarray | None
    intercept: float
    shift: np.ndarray  # by guessed language, 0 = none
    prior: float
    #: Rows that calibrated the thresholds, and how many of them the thresholds get wrong.
    calibrated: tuple[int, int] = (0, 0)

    def pooled(self, x: np.ndarray, starts: np.ndarray, ends: np.ndarray, where: bool = False):
        """Max-pooled filters over x[starts:ends] of each text; two more rows stand behind each end."""
        out, arg = [], []
        for w, width in enumerate(WIDTHS):
            y = sum(x[j : len(x) - 2 + j] @ self.filters[w, j] for j in range(width)) + self.bias[w]
            if where:
                best = np.stack([s + np.argmax(y[s:e], axis=0) for s, e in zip(starts, ends, strict=True)])
                arg.append(best)
                out.append(np.take_along_axis(y, best, axis=0))
            else:
                cuts = np.stack([starts, ends], axis=1).ravel()[:-1]
                out.append(np.maximum.reduceat(y[: ends[-1]], cuts, axis=0)[::2])
        return np.concatenate(out, axis=1), arg

    def logits(self, pooled: np.ndarray) -> np.ndarray:
        return np.maximum(pooled, 0) @ self.weight + self.intercept

    def scores(self, logits: np.ndarray, language: np.ndarray) -> np.ndarray:
        z = logits - self.shift[language] + np.log(THRESHOLD / (1 - THRESHOLD))
        return 1 / (1 + np.exp(-np.clip(z, -40, 40)))


def _padded(ids: np.ndarray) -> np.ndarray:
    """Word indexes and two zeros (the zero vector), which the last windows look at; one word at least."""
    return np.concatenate([ids, np.zeros(2 + (not len(ids)), np.int64)])


def _laid_out(runs: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Runs one after another; windows start in [start, end) of each and look at the two behind it."""
    over = np.cumsum([len(r) for r in runs])
    return np.concatenate(runs), over - [len(r) for r in runs], over - 2


class Scorer:
    """Scores whole texts; keeps the embeddings of the words it has met."""

    def __init__(self, model: Model):
        self.model = model
        self._restart()

    def _restart(self) -> None:
        self.index: dict[bytes, int] = {}
        self.x = np.zeros((1, DIM), np.float32)
        self.language = np.zeros(1, np.int8)

    def _learn(self, new: list[bytes]) -> None:
        row, count = hashes(new)
        sums = np.add.reduceat(self.model.embedding[row], np.cumsum(count) - count, axis=0)
        self.index |= {w: len(self.x) + i for i, w in enumerate(new)}
        self.x = np.concatenate([self.x, (sums / count[:, None]).astype(np.float32)])
        self.language = np.concatenate([self.language, np.array([_LANGUAGE.get(w, 0) for w in new], np.int8)])

    def __call__(self, texts: list[str | None]) -> np.ndarray:
        if self.model.embedding is None:
            return np.full(len(texts), self.model.prior)
        if len(self.index) > KEPT_WORDS:
            self._restart()
        words = [words_of(t) for t in texts]
        if new := list({w for ws in words for w in ws}.difference(self.index)):
            self._learn(new)
        runs, of = [], []
        get = self.index.__getitem__
        for i, ws in enumerate(words):
            ids = np.fromiter(map(get, ws), np.int64, len(ws))
            padded = _padded(ids)
            for at in range(0, len(padded) - 2, BLOCK_WORDS):  # runs of a long text look at two words of the next
                runs.append(padded[at : at + BLOCK_WORDS + 2])
                of.append(i)
        pooled = np.full((len(texts), FILTERS * len(WIDTHS)), -np.inf, np.float32)
        votes = np.zeros((len(texts), 1 + max(FUNCTION_WORDS)), np.int64)
        at = 0
        while at < len(runs):
            end, total = at, 0
            while end < len(runs) and (end == at or total + len(runs[end]) <= BLOCK_WORDS):
                total += len(runs[end])
                end += 1
            laid, starts, ends = _laid_out(runs[at:end])
            got, _ = self.model.pooled(self.x[laid], starts, ends)
            np.maximum.at(pooled, of[at:end], got)
            for k in FUNCTION_WORDS:
                cuts = np.stack([starts, ends], axis=1).ravel()[:-1]
                np.add.at(votes[:, k], of[at:end], np.add.reduceat((self.language[laid[: ends[-1]]] == k).astype(np.int64), cuts)[::2])
            at = end
        votes[:, 0] = 0
        return self.model.scores(self.model.logits(pooled), np.where(votes.max(axis=1) > 0, votes.argmax(axis=1), 0))


class Net:
    """The parameters while they are fitted to some texts (rows of words), and their gradients."""

    def __init__(self, texts: Iterable[list[bytes]], draw: np.random.Generator, buckets: int = BUCKETS):
        """Words become numbers as they come, so that only distinct ones are held."""
        index: dict[bytes, int] = {}
        self.docs, self.spoken = [], []
        for words in texts:
            self.docs.append(_padded(np.array([index.setdefault(w, len(index) + 1) for w in words], np.int64)).astype(np.int32))
            self.spoken.append(np.bincount([_LANGUAGE.get(w, 0) for w in words], minlength=1 + max(FUNCTION_WORDS)))
        names = list(index)
        parts = [hashes(names[at : at + BLOCK_WORDS]) for at in range(0, len(names), BLOCK_WORDS)] or [hashes([b"?"])]
        self.row, count = (np.concatenate([p[k] for p in parts]) for k in (0, 1))
        self.row %= buckets
        self.first, self.count = np.r_[0, np.cumsum(count) - count], np.r_[0, count]
        filters = draw.normal(0, 0.5, (len(WIDTHS), max(WIDTHS), DIM, FILTERS))
        for w, width in enumerate(WIDTHS):
            filters[w, width:] = 0
        self.p = {
            "embedding": draw.normal(0, 0.02, (buckets, DIM)).astype(np.float32),
            "filters": filters,
            "bias": np.zeros((len(WIDTHS), FILTERS)),
            "weight": draw.normal(0, 0.3, FILTERS * len(WIDTHS)),
            "intercept": np.zeros(1),
        }

    def model(self, shift: np.ndarray, prior: float) -> Model:
        p = self.p
        return Model(p["embedding"], p["filters"], p["bias"], p["weight"], float(p["intercept"][0]), shift, prior)

    def vectors(self, words: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Embeddings of distinct words (0 = none), and their hashes' rows with owners."""
        n = self.count[words]
        owner = np.repeat(np.arange(len(words)), n)
        rows = self.row[np.repeat(self.first[words] - (np.cumsum(n) - n), n) + np.arange(n.sum())]
        x = np.zeros((len(words), DIM))
        for d in range(DIM):
            x[:, d] = np.bincount(owner, self.p["embedding"][rows, d], len(words))
        return x / np.maximum(n, 1)[:, None], rows, owner

    def forward(self, some: np.ndarray):
        laid, starts, ends = _laid_out([self.docs[i] for i in some])
        distinct, back = np.unique(laid, return_inverse=True)
        x, rows, owner = self.vectors(distinct)
        model = self.model(np.zeros(1), 0.0)
        pooled, arg = model.pooled(x[back], starts, ends, where=True)
        return model.logits(pooled), pooled, arg, back, x, rows, owner, distinct

    def gradients(self, some: np.ndarray, y: np.ndarray) -> tuple[dict[str, np.ndarray], np.ndarray]:
        """Of the mean logistic loss of the texts ``some`` with classes ``y``: by parameter, the
        embedding's only for the rows that are returned with them."""
        z, pooled, arg, back, x, rows, owner, distinct = self.forward(some)
        p = self.p
        dz = (1 / (1 + np.exp(-np.clip(z, -40, 40))) - y) / len(some)
        grad = {"weight": np.maximum(pooled, 0).T @ dz, "intercept": np.array([dz.sum()]), "filters": np.zeros_like(p["filters"]), "bias": np.zeros_like(p["bias"])}
        dpool = np.outer(dz, p["weight"]) * (pooled > 0)
        dx = np.zeros_like(x)
        for w, width in enumerate(WIDTHS):
            d = dpool[:, w * FILTERS : (w + 1) * FILTERS]
            grad["bias"][w] = d.sum(axis=0)
            for j in range(width):
                word = back[arg[w] + j]
                grad["filters"][w, j] = np.einsum("bfd,bf->df", x[word], d)
                np.add.at(dx, word.ravel(), (d[:, :, None] * p["filters"][w, j].T[None]).reshape(-1, DIM))
        dx[distinct == 0] = 0
        touched = np.flatnonzero(np.abs(dx).sum(axis=1))
        mine = np.isin(owner, touched)
        used, where = np.unique(rows[mine], return_inverse=True)
        de = np.zeros((len(used), DIM))
        np.add.at(de, where, (dx / np.maximum(self.count[distinct], 1)[:, None])[owner[mine]])
        return grad | {"embedding": de}, used


def train(texts: Iterable[list[bytes]], toxic: Iterable[int], epochs: int = 5, batch: int = 32, seed: int = 7) -> Model:
    """Fits the classifier to tokenised texts; every fourth text of each class calibrates."""
    y = np.array(list(toxic), np.float64)
    shift = np.zeros(1 + max(FUNCTION_WORDS))
    if not 0 < y.sum() < len(y):
        return Model(None, None, None, None, 0.0, shift, float(y.mean()) if len(y) else 0.0)
    draw = np.random.default_rng(seed)
    held = np.zeros(len(y), bool)
    for c in (0, 1):
        of = draw.permutation(np.flatnonzero(y == c))
        held[of[: len(of) // 4]] = True
    net = Net(texts, draw)
    first_moment = {k: np.zeros_like(v) for k, v in net.p.items()}
    second_moment = {k: np.zeros_like(v) for k, v in net.p.items()}
    step = 0
    learn = np.flatnonzero(~held)
    for _ in range(epochs):
        order = draw.permutation(learn)
        for at in range(0, len(order), batch):
            some = order[at : at + batch]
            grad, used = net.gradients(some, y[some])
            step += 1
            for k, g in grad.items():
                at_rows = used if k == "embedding" else slice(None)
                m = first_moment[k][at_rows] = 0.9 * first_moment[k][at_rows] + 0.1 * g
                v = second_moment[k][at_rows] = 0.99 * second_moment[k][at_rows] + 0.01 * g * g
                net.p[k][at_rows] -= 0.02 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
    quiet = second_moment["embedding"].sum(axis=1) == 0
    net.p["embedding"][quiet] = 0  # never learned: no vote
    logits, languages = np.zeros(len(y)), np.zeros(len(y), int)
    calibrating = np.flatnonzero(held)
    for at in range(0, len(calibrating), batch):
        some = calibrating[at : at + batch]
        logits[some] = net.forward(some)[0]
    for i in calibrating:
        votes = net.spoken[i]
        votes[0] = 0
        languages[i] = votes.argmax() if votes.max() else 0
    common_shift = best_threshold(logits[held], y[held], 0.0)
    shift[:] = common_shift
    for k in FUNCTION_WORDS:
        own = held & (languages == k)
        if min(y[own].sum(), (1 - y[own]).sum()) >= 10:
            shift[k] = best_threshold(logits[own], y[own], common_shift)
    wrong = int(((logits >= shift[languages]) != (y == 1))[held].sum())
    fitted = net.model(shift, float(y.mean()))
    return Model(
        *(a.astype(np.float32) for a in (fitted.embedding, fitted.filters, fitted.bias, fitted.weight)), fitted.intercept, shift, fitted.prior, (int(held.sum()), wrong)
    )


def best_threshold(logits: np.ndarray, y: np.ndarray, default: float) -> float:
    """The middle of the widest gap among the cuts of fewest errors."""
    if not 0 < y.sum() < len(y):
        return default
    by = np.argsort(logits)
    z, t = logits[by], y[by]
    errors = np.r_[0, np.cumsum(t)] + np.r_[np.cumsum((1 - t)[::-1])[::-1], 0]
    gaps = np.r_[0, np.diff(z), 0]
    cut = max(np.flatnonzero(errors == errors[1:-1].min())[:], key=lambda i: gaps[i])
    return float((z[cut - 1] + z[cut]) / 2) if 0 < cut < len(z) else default


def fit(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> Model:
    """Learns from at most ``sample`` labelled rows of each class that are not held out.

    The sampled ids are bounded, so they are broadcast; no text is shuffled. Only the sampled
    words come to the driver.
    """
    known = (
        labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("toxic"))
        .dropna()
        .filter(held_out_expr() == F.lit(False))
        .groupBy("doc_id")
        .agg(F.max("toxic").alias("toxic"))
    )
    order = [F.xxhash64("doc_id"), F.col("doc_id")]
    ids = common.materialise(
        known.filter("toxic = 1").orderBy(*order).limit(sample).unionByName(known.filter("toxic = 0").orderBy(*order).limit(sample))
    )

    def tokens(batches):
        for batch in batches:
            for part in common.slices(batch):
                words = [b" ".join(words_of(t)) for t in part.column(2).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(words, pa.binary())], names=["doc_id", "toxic", "words"])

    rows = (
        docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
        .join(F.broadcast(ids), "doc_id")
        .select("doc_id", "toxic", "text")
        .mapInArrow(tokens, "doc_id long, toxic int, words binary")
        .collect()
    )
    rows.sort(key=lambda r: (r.doc_id, bytes(r.words)))
    rows = [r for k, r in enumerate(rows) if not k or rows[k - 1].doc_id != r.doc_id]  # repeated rows count once
    return train((bytes(r.words).split() for r in rows), (r.toxic for r in rows))


def held_out_expr():
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 == 1, F.lit(False))


def scored(docs: DataFrame, model: Model, keep: list[str]) -> DataFrame:
    """``row`` (the columns kept) and score for every row of ``docs``."""
    given = docs.select(F.struct(*keep).alias("row"), F.col("text").alias("text"))

    def run(batches):
        scorer = Scorer(model)
        for batch in batches:
            for part in common.slices(batch):
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(scorer(part.column(1).to_pylist()), pa.float64())], names=["row", "score"])

    return given.mapInArrow(run, f"row {given.schema['row'].dataType.simpleString()}, score double")


def clean(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """The documents that score below the threshold, columns as given."""
    return scored(docs, fit(docs, labels), docs.columns).filter(F.col("score") < threshold).select("row.*")


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    model = fit(docs, common.table(spark, sf_dir, "labels"))
    return scored(docs, model, ["doc_id"]).select(F.col("row.doc_id").cast("long").alias("doc_id"), "score").select(
        "doc_id", held_out_expr().alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted")
    )
