"""SentencePiece encoding and decoding as composed weighted transducers.

Method. From a model file three machines are compiled:

* the normaliser maps characters to the model's alphabet (white space to its mark, one mark
  put in front of a text);
* the piece machine maps runs of normalised characters to pieces, and a character that is no
  piece to the pieces of its bytes;
* for models of merges, the pair machine accepts a sequence of pieces if every two
  neighbours are what merging their characters by rank yields. A sequence of which this
  holds everywhere is the merged form of the whole, and there is just one.

A text is composed with them and the shortest path taken in the tropical semiring, position
by position, with the last piece as the pair machine's state. For models of merges the pair
machine weighs 0 or infinity, so one path is left, the library's; for unigram models the pair
machine is absent and a piece weighs its negated score. Where no piece holds a mark behind
another character, paths of different words never share an arc, so words are composed one by
one and the paths of words are kept.

Decoding runs the machines the other way: pieces to characters, byte pieces joined to
characters (a byte that is part of none becomes U+FFFD), marks to spaces, the first one off.

Defined results: null text = empty text = no pieces; a text's own mark characters come
back as spaces, as in the library; an empty table gives an empty result.
"""

from __future__ import annotations

import heapq
import math
import struct
import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from . import common

MODEL = "piece_bpe_32k.model"
MARK = "▁"
KEPT_WORDS, KEPT_PAIRS = 500_000, 1_000_000
#: Texts up to this many characters are composed from their end.
SHORT = 200
#: Piece types of the model format, and its penalty below the worst score.
NORMAL, UNKNOWN, CONTROL, USER_DEFINED, UNUSED, BYTE = 1, 2, 3, 4, 5, 6
UNIGRAM, MERGES = 1, 2
UNKNOWN_PENALTY = 10.0


def default_model() -> str:
    import public_tokenizers

    return public_tokenizers.path(MODEL)


def _fields(data: bytes) -> Iterator[tuple[int, int | bytes]]:
    """(number, value) of the fields of a protocol buffer message."""
    at = 0

    def varint() -> int:
        nonlocal at
        value = shift = 0
        while True:
            byte = data[at]
            at += 1
            value |= (byte & 127) << shift
            shift += 7
            if byte < 128:
                return value

    while at < len(data):
        key = varint()
        if key & 7 == 0:
            yield key >> 3, varint()
            continue
        size = {1: 8, 5: 4}.get(key & 7)
        size = varint() if size is None else size
        yield key >> 3, data[at : at + size]
        at += size


class Machine:
    """The composed transducers of one model."""

    def __init__(self, model: bytes):
        self.pieces: list[tuple[str, float, int]] = []
        self.kind, self.prefix, self.squeeze, byte_fallback = UNIGRAM, True, True, False
        for number, value in _fields(model):
            if number == 1:
                piece = dict(_fields(value))
                self.pieces.append((piece[1].decode(), struct.unpack("<f", piece[2])[0] if 2 in piece else 0.0, piece.get(3, NORMAL)))
            elif number == 2:
                trainer = dict(_fields(value))
                self.kind, byte_fallback = trainer.get(3, UNIGRAM), bool(trainer.get(35, 0))
            elif number == 3:
                normaliser = dict(_fields(value))
                if normaliser.get(2):
                    raise ValueError("only the identity normaliser is supported")
                self.prefix, self.squeeze = bool(normaliser.get(3, 1)), bool(normaliser.get(4, 1))
        if self.kind not in (UNIGRAM, MERGES) or any(t == USER_DEFINED for *_, t in self.pieces):
            raise ValueError("only unigram and merge models without user-defined pieces are supported")
        self.id = {p: i for i, (p, _, t) in enumerate(self.pieces) if t in (NORMAL, UNUSED)}
        self.rank = {p: s for p, s, t in self.pieces if t in (NORMAL, UNUSED)}
        self.bytes = {int(p[3:5], 16): i for i, (p, _, t) in enumerate(self.pieces) if t == BYTE} if byte_fallback else {}
        self.unknown = next(i for i, (*_, t) in enumerate(self.pieces) if t == UNKNOWN)
        self.longest = max(map(len, self.id))
        self.worst = min(self.rank.values()) - UNKNOWN_PENALTY
        #: Words can be composed one by one.
        self.by_word = not any(MARK in p.lstrip(MARK) for p in self.id)
        #: A line feed in no piece parts words too.
        self.by_line = not any("\n" in p for p in self.id)
        self.bytes_of = [
            bytes([int(p[3:5], 16)]) if t == BYTE else b" \xe2\x81\x87 " if t == UNKNOWN else b"" if t == CONTROL else p.replace(MARK, " ").encode()
            for p, _, t in self.pieces
        ]
        self.packed = {p: struct.pack("<I", i) for p, i in self.id.items()}
        self.words: dict[str, bytes] = {}  # of words as they are
        self.marked: dict[str, bytes] = {}  # of words with one mark in front, by the word behind it
        self.pairs: dict[tuple[str, str], bool] = {}
        self.whole: dict[str, bool] = {}
        self.tails: dict[str, str] = {}

    # --- the normaliser ---

    def normalised(self, text: str) -> str:
        if self.squeeze:
            text = " ".join(filter(None, text.replace(MARK, " ").split(" ")))
        if not text:
            return ""
        return (MARK if self.prefix else "") + text.replace(" ", MARK)

    # --- the pair machine ---

    def merged(self, symbols: list[str]) -> list[str]:
        """Neighbours merge, the best piece first, the leftmost of equals."""
        symbols, after = list(symbols), [*range(1, len(symbols)), -1]
        before = [*range(-1, len(symbols) - 1)]
        heap: list[tuple[float, int, int, str]] = []

        def offer(i: int) -> None:
            if i >= 0 and after[i] >= 0 and (both := symbols[i] + symbols[after[i]]) in self.rank:
                heapq.heappush(heap, (-self.rank[both], i, after[i], both))

        for i in range(len(symbols) - 1):
            offer(i)
        while heap:
            _, i, j, both = heapq.heappop(heap)
            if symbols[i] and after[i] == j and symbols[i] + symbols[j] == both:
                symbols[i], symbols[j] = both, ""
                after[i] = after[j]
                if after[j] >= 0:
                    before[after[j]] = i
                offer(before[i])
                offer(i)
        return [s for s in symbols if s]

    def is_whole(self, piece: str) -> bool:
        """The piece is what its own characters merge to."""
        if (known := self.whole.get(piece)) is None:
            known = self.whole[piece] = len(piece) == 1 or self.merged(list(piece)) == [piece]
        return known

    def agree(self, left: str, right: str) -> bool:
        key = left, right
        if (known := self.pairs.get(key)) is None:
            if len(self.pairs) > KEPT_PAIRS:
                self.pairs.clear()
            known = self.pairs[key] = self.merged(list(left + right)) == [left, right]
        return known

    # --- shortest paths ---

    def tail(self, text: str) -> str:
        """The last piece on the path through a short text. A path's beginning is the path of the
        beginning, so the composition is expanded only where asked for, and kept."""
        if (known := self.tails.get(text)) is not None:
            return known
        n = len(text)
        for start in range(max(0, n - self.longest), n):
            piece = text[start:]
            if (piece in self.rank and self.is_whole(piece) or start == n - 1) and (not start or self.agree(self.tail(text[:start]), piece)):
                self.tails[text] = piece
                return piece
        raise AssertionError("a merge model has a path through every text")

    def path(self, text: str) -> list[str]:
        """The pieces (or single characters that are none) on the shortest path through a normalised text."""
        if self.kind == MERGES and len(text) <= SHORT:
            out = []
            while text:
                out.append(self.tail(text))
                text = text[: -len(out[-1])]
            return out[::-1]
        n = len(text)
        best = [math.inf] * (n + 1)
        best[0] = 0.0
        last: list[str] = [""] * (n + 1)
        merges, rank = self.kind == MERGES, self.rank
        for end in range(1, n + 1):
            for start in range(max(0, end - self.longest), end):
                if best[start] == math.inf:
                    continue
                piece = text[start:end]
                if piece in rank:
                    weight = 0.0 if merges else -rank[piece]
                    if merges and not self.is_whole(piece):
                        continue
                elif end - start == 1:
                    weight = 0.0 if merges else -self.worst
                else:
                    continue
                if merges and start and not self.agree(last[start], piece):
                    continue
                if best[start] + weight < best[end]:
                    best[end], last[end] = best[start] + weight, piece
                    if merges:
                        break  # there is only one
        out = []
        while n:
            out.append(last[n])
            n -= len(last[n])
        return out[::-1]

    def output(self, path: Iterable[str]) -> list[int]:
        ids: list[int] = []
        for piece in path:
            if piece in self.id:
                ids.append(self.id[piece])
            elif self.bytes:
                ids += [self.bytes[b] for b in piece.encode("utf-8", "surrogatepass")]
            elif not ids or ids[-1] != self.unknown:
                ids.append(self.unknown)
        return ids

    def encode(self, text: str | None) -> bytes:
        """Ids as little-endian unsigned 32-bit numbers."""
        text = self.normalised(text or "")
        if not text:
            return b""
        if not (self.by_word and self.by_line and self.bytes):
            return self._packed(text)
        if len(self.words) + len(self.marked) > KEPT_WORDS:
            self.words.clear()
            self.marked.clear()
        if len(self.tails) > KEPT_PAIRS:
            self.tails.clear()
        out = []
        for line in text.split("\n"):
            first, *rest = line.split(MARK)
            if "" in rest:  # runs of marks
                words = _words(line)
                self._learn(words, self.words, "")
                out.append(b"".join(map(self.words.__getitem__, words)))
                continue
            head = [first] if first else []
            self._learn(head, self.words, "")
            self._learn(rest, self.marked, MARK)
            out.append(b"".join([*map(self.words.__getitem__, head), *map(self.marked.__getitem__, rest)]))
        return struct.pack("<I", self.bytes[10]).join(out)

    def _packed(self, text: str) -> bytes:
        if self.kind == MERGES and len(text) <= SHORT:  # path and output in one walk
            known, packed, out = self.tails.get, self.packed.get, []
            while text:
                piece = known(text) or self.tail(text)
                out.append(packed(piece) or struct.pack(f"<{len(b := piece.encode())}I", *map(self.bytes.__getitem__, b)))
                text = text[: -len(piece)]
            return b"".join(out[::-1])
        ids = self.output(self.path(text))
        return struct.pack(f"<{len(ids)}I", *ids)

    def _learn(self, words: list[str], kept: dict[str, bytes], mark: str) -> None:
        for word in set(words).difference(kept):
            kept[word] = self._packed(mark + word)

    def decode(self, ids: bytes) -> str:
        raw = b"".join(map(self.bytes_of.__getitem__, np.frombuffer(ids, "<u4").tolist()))
        if self.prefix and raw[:1] == b" ":
            raw = raw[1:]
        try:
            return raw.decode()
        except UnicodeDecodeError:
            return _each_bad_byte(raw)


def _words(text: str) -> list[str]:
    """Runs of marks with what follows them, up to the next run."""
    parts = text.split(MARK)
    words, marks = [parts[0]] if parts[0] else [], 0
    for part in parts[1:]:
        marks += 1
        if part:
            words.append(MARK * marks + part)
            marks = 0
    if marks:
        words.append(MARK * marks)
    return words


def _each_bad_byte(raw: bytes) -> str:
    out, at = [], 0
    while at < len(raw):
        for size in (1, 2, 3, 4):
            try:
                out.append(raw[at : at + size].decode())
                at += size
                break
            except UnicodeDecodeError:
                continue
        else:
            out.append("�")
            at += 1
    return "".join(out)


def compiled(path: str) -> Machine:
    with open(path, "rb") as f:
        return Machine(f.read())


def encoded(docs: DataFrame, model: str | None = None) -> DataFrame:
    """doc_id, ids (binary, little-endian unsigned 32-bit) for every row of ``docs`` (doc_id, text)."""
    model = model or default_model()

    def make():
        machine = compiled(model)
        return lambda doc_id, text: ((doc_id, machine.encode(text)),)

    schema = pa.schema([("doc_id", pa.int64()), ("ids", pa.binary())])
    return docs.selectExpr("cast(doc_id as long) doc_id", "text").mapInArrow(common.per_row(["doc_id", "text"], schema, make), "doc_id long, ids binary")


def decoded(rows: DataFrame, model: str | None = None) -> DataFrame:
    """doc_id, text for every row of ``rows`` (doc_id, ids)."""
    model = model or default_model()

    def make():
        machine = compiled(model)
        return lambda doc_id, ids: ((doc_id, machine.decode(ids or b"")),)

    schema = pa.schema([("doc_id", pa.int64()), ("text", pa.string())])
    return rows.selectExpr("cast(doc_id as long) doc_id", "ids").mapInArrow(common.per_row(["doc_id", "ids"], schema, make), "doc_id long, text string")


def op2_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, ids_crc32, n_chars (decoded code points) and whether decoding gives the text back."""
    model = default_model()

    def make():
        machine = compiled(model)

        def one(doc_id, text):
            ids = machine.encode(text)
            back = machine.decode(ids)
            return ((doc_id, len(ids) // 4, zlib.crc32(ids), len(back), back == (text or "").replace(MARK, " ")),)

        return one

    schema = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64()), ("n_chars", pa.int64()), ("round_trip", pa.bool_())])
    docs = common.table(spark, sf_dir, "documents").selectExpr("cast(doc_id as long) doc_id", "text")
    return docs.mapInArrow(common.per_row(["doc_id", "text"], schema, make), "doc_id long, n_tokens long, ids_crc32 long, n_chars long, round_trip boolean")
