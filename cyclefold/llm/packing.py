"""Best-fit packing of token runs into sequences, with large-item matching.

Method. A document is its token ids and one end id; what is longer than a sequence is cut
into whole pieces and one shorter last piece. Only the lengths decide how pieces share
sequences, and a length is one of ``capacity`` values. So the plan is made from the
histogram of lengths, which is bounded whatever the corpus:

* pieces above a third of the capacity are *large*, at most two fit a sequence. From the
  longest on, each takes the longest partner that fits (the sets of possible partners are
  nested, so this greedy matching finds as many pairs as there can be); large pieces of at
  most half the capacity that stay single pair among themselves;
* the others fill the remaining gaps from the longest on, each in the tightest gap.

Equal lengths are placed in bulk: a step of the plan says that the pieces of one length
with ranks r .. r+m*q-1 go to m neighbouring sequences, q to each. Every piece then finds its
place by its rank among the pieces of its length. Ranks need no gathering: a piece counts
within its input partition, and the partitions' counts are summed up in order.

Token ids are the library's. Most words recur, so the ids of a word are kept (merges never
cross a word of the tokenizer's own split) and only new words go to the library's merges;
texts with characters beyond Latin-1, control characters or special tokens go to the library
whole.

Defined results: null text = empty text = the end id alone; repeated rows are packed as
separate documents; an empty table gives an empty result.
"""

from __future__ import annotations

import json
import re
import struct
import zlib
from bisect import bisect_left, insort
from collections.abc import Iterable

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common

CAPACITY = 4096
END_ID = 1
VOCABULARY = "word_bpe_49k.json"
#: Words whose ids a task keeps before it starts anew.
KEPT_WORDS = 1_200_000


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path(VOCABULARY)


def _byte_letters() -> dict[int, int]:
    """The alphabet of byte-level vocabularies: printable bytes stand for themselves, the others follow 255."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    others = (b for b in range(256) if b not in plain)
    return {b: 256 + i for i, b in enumerate(others)}


_BYTE_LETTERS = _byte_letters()


class WordEncoder:
    """The library's ids of whole texts, as little-endian unsigned 32-bit numbers."""

    _plain = re.compile(r"[\t\n\r -~¡-ÿ]*")
    #: Fixed: the tokenizer's own split, for lower-case Latin-1.
    _words = re.compile(
        r"'s|'t|'re|'ve|'m|'ll|'d|[a-zªµºß-öø-ÿ]+|[0-9²³¹¼-¾]"
        r"|[^\sa-zªµºß-öø-ÿ0-9²³¹¼-¾]+"
    )

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            about = json.load(f)
        self.special = [t["content"] for t in about["added_tokens"]]
        self.merge = self.tokenizer.model.tokenize
        self.kept: dict[str, bytes] = {}

    def _library(self, text: str) -> np.ndarray:
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, "<u4")

    def _merged(self, word: str) -> bytes:
        """A new word goes to the library's merges alone, in its alphabet of bytes."""
        letters = word if word.isascii() else word.encode().decode("latin-1").translate(_BYTE_LETTERS)
        ids = [t.id for t in self.merge(letters)]
        return struct.pack(f"<{len(ids)}I", *ids)

    def _learn(self, run: str) -> None:
        """The ids of a run without white space, from those of its words."""
        kept, words = self.kept, self._words.findall(run)
        for word in words:
            if word not in kept:
                kept[word] = self._merged(word)
        if run not in kept:
            kept[run] = b"".join([kept[w] for w in words])

    def batch(self, texts: Iterable[str]) -> list[bytes]:
        """The ids of each text; new runs of the batch are learned first."""
        if len(self.kept) > KEPT_WORDS:
            self.kept.clear()
        split: list[bytes | list[str]] = []
        runs: set[str] = set()
        for text in texts:
            if self._plain.fullmatch(text) and not any(s in text for s in self.special):
                split.append(text.lower().split())
                runs.update(split[-1])
            else:
                split.append(self._library(text).tobytes())
        for run in runs.difference(self.kept):
            self._learn(run)
        kept = self.kept.__getitem__
        return [x if isinstance(x, bytes) else b"".join(map(kept, x)) for x in split]


_PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long, part int, nth long"


def pieces(docs: DataFrame, capacity: int = CAPACITY, vocabulary: str | None = None, end_id: int = END_ID) -> DataFrame:
    """The pieces of every row of ``docs`` (columns doc_id, text), with the input partition and the
    number of earlier pieces of the same length in it."""
    vocabulary = vocabulary or default_vocabulary()
    end = np.array([end_id], "<u4").tobytes()
    schema = pa.schema([("doc_id", pa.int64()), ("piece", pa.int32()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64()), ("part", pa.int32()), ("nth", pa.int64())])

    def run(batches):
        encoder, part = WordEncoder(vocabulary), TaskContext.get().partitionId()
        seen = [0] * (capacity + 1)
        for batch in batches:
            for some in common.slices(batch):
                rows = []
                texts = [t or "" for t in some.column(1).to_pylist()]
                for doc_id, raw in zip(some.column(0).to_pylist(), encoder.batch(texts), strict=True):
                    raw += end
                    for k, at in enumerate(range(0, len(raw), 4 * capacity)):
                        ids = raw[at : at + 4 * capacity]
                        n = len(ids) // 4
                        rows.append((doc_id, k, at // 4, n, zlib.crc32(ids), part, seen[n]))
                        seen[n] += 1
                yield pa.RecordBatch.from_arrays(
                    [pa.array(c, type=f.type) for c, f in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema
                )

    return docs.selectExpr("cast(doc_id as long) doc_id", "text").mapInArrow(run, _PIECES)


class Plan:
    """Where the pieces of each length go: rows (length, first rank, sequences, q, first sequence, offset)."""

    def __init__(self, histogram: dict[int, int], capacity: int = CAPACITY):
        self.capacity, self.sequences = capacity, 0
        self.rows: list[tuple[int, int, int, int, int, int]] = []
        self._rank: dict[int, int] = dict.fromkeys(histogram, 0)
        self._gaps: list[int] = []  # sorted
        self._open: dict[int, list[tuple[int, int]]] = {}  # gap -> runs (first sequence, sequences)
        large = {s: n for s, n in histogram.items() if 3 * s > capacity and n}
        self._match(large)
        for s in sorted((s for s in histogram if s not in large), reverse=True):
            self._fill(s, histogram[s])

    def _put(self, length: int, first: int, sequences: int, q: int, gap: int) -> None:
        """q pieces of a length into each of some sequences of one gap."""
        self.rows.append((length, self._rank[length], sequences, q, first, self.capacity - gap))
        self._rank[length] += sequences * q
        self._leave(gap - q * length, first, sequences)

    def _leave(self, gap: int, first: int, sequences: int) -> None:
        if gap and sequences:
            if gap not in self._open:
                insort(self._gaps, gap)
                self._open[gap] = []
            self._open[gap].append((first, sequences))

    def _new(self, sequences: int) -> int:
        self.sequences += sequences
        return self.sequences - sequences

    def _match(self, count: dict[int, int]) -> None:
        count, half = dict(count), self.capacity // 2
        single = sorted(s for s in count if s <= half)  # possible partners, ascending
        for s in sorted((s for s in count if s > half), reverse=True):
            while count[s]:
                at = bisect_left(single, self.capacity - s + 1) - 1
                if at < 0:
                    self._put(s, self._new(count[s]), count[s], 1, self.capacity)
                    break
                self._pair(s, single, at, count)
        while single:
            s = single[-1]
            if count[s] > 1:
                n = count[s] // 2
                self._put(s, self._new(n), n, 2, self.capacity)
                count[s] %= 2
                if not count[s]:
                    single.pop()
            elif len(single) > 1:
                single.pop()
                self._pair(s, single, len(single) - 1, count)
            else:
                self._put(single.pop(), self._new(1), 1, 1, self.capacity)

    def _pair(self, s: int, single: list[int], at: int, count: dict[int, int]) -> None:
        partner = single[at]
        n = min(count[s], count[partner])
        first = self._new(n)
        self.rows.append((s, self._rank[s], n, 1, first, 0))
        self._rank[s] += n
        self._put(partner, first, n, 1, self.capacity - s)
        count[s] -= n
        count[partner] -= n
        if not count[partner]:
            single.pop(at)

    def _fill(self, s: int, count: int) -> None:
        while count:
            at = bisect_left(self._gaps, s)
            if at == len(self._gaps):
                n = -(-count // (self.capacity // s))
                self._leave(self.capacity, self._new(n), n)
                continue
            gap = self._gaps[at]
            first, n = self._open[gap].pop()
            if not self._open[gap]:
                del self._open[gap]
                self._gaps.pop(at)
            q = gap // s
            full = min(n, count // q)
            if full:
                self._put(s, first, full, q, gap)
                count -= full * q
            if full < n and 0 < count < q:
                self._put(s, first + full, 1, count, gap)
                count, full = 0, full + 1
            self._leave(gap, first + full, n - full)

    def arrays(self) -> dict[str, np.ndarray]:
        names = ("length", "rank", "sequences", "q", "first", "offset")
        table = np.array(sorted(self.rows), np.int64).reshape(-1, len(names))
        return dict(zip(names, table.T.copy(), strict=True))


def placed(parts: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """Adds sequence_id and offset to written ``pieces``."""
    counts = common.materialise(parts.groupBy("part", "length").agg(F.count("*").alias("n")))
    histogram = {r.length: r.n for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # <= capacity rows
    plan = Plan(histogram, capacity).arrays()
    before = Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    base = common.materialise(counts.select("part", "length", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base")))
    given = ["doc_id", "piece", "start", "length", "ids_crc32"]
    schema = pa.schema([("doc_id", pa.int64()), ("piece", pa.int32()), *((c, pa.int64()) for c in (*given[2:], "sequence_id", "offset"))])

    def place(batches):
        key = plan["length"] << 44 | plan["rank"]
        for batch in batches:
            length, rank = (batch.column(batch.schema.get_field_index(c)).to_numpy(zero_copy_only=False) for c in ("length", "rank"))
            row = np.searchsorted(key, length << 44 | rank, side="right") - 1
            within = rank - plan["rank"][row]
            sequence = plan["first"][row] + within // plan["q"][row]
            offset = plan["offset"][row] + within % plan["q"][row] * length
            yield pa.RecordBatch.from_arrays(
                [*(batch.column(batch.schema.get_field_index(c)) for c in given), pa.array(sequence), pa.array(offset)], schema=schema
            )

    return (
        parts.join(base, ["part", "length"])
        .select(*given, (F.col("base") + F.col("nth")).alias("rank"))
        .mapInArrow(place, "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
    )


def pack(docs: DataFrame, capacity: int = CAPACITY, vocabulary: str | None = None, end_id: int = END_ID) -> DataFrame:
    return placed(common.materialise(pieces(docs, capacity, vocabulary, end_id)), capacity)


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(common.table(spark, sf_dir, "documents"))
