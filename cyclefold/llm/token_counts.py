"""Token counts of huge documents by overlapping chunks that resynchronise.

Method. A text longer than one chunk is encoded chunk by chunk, each chunk starting inside
its predecessor, with the code point span of every token. The two encodings are spliced at a
common boundary that is proven stable: a token that both have with the same span and id. If
none is found, the overlap is widened (doubled) and the chunk encoded again; if it would
reach behind what is already spliced, the text is encoded in one piece.

Why the splice is exact. Merging by rank gives a token sequence that is right for a text
exactly if every pair of neighbours is right by itself: a merge across a token border happens
in the whole text if and only if it happens in that pair alone. The left chunk's sequence up
to the common token and the right chunk's after it contain only pairs that one of the
encodings has produced, hence the spliced sequence is the encoding of the whole text. The
first token of a right chunk holds the marker that the encoder puts before a text, and byte
tokens are parts of a character; neither is used as a boundary.

Defined results: null text = empty text = 0 tokens. A task holds one slice of texts and one
chunk's tokens; of what is spliced only the count is kept.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from . import common

CHUNK = 16384
OVERLAP = 128
LIMIT = 4096
MODEL = "piece_bpe_32k.model"


def default_model() -> str:
    import public_tokenizers

    return public_tokenizers.path(MODEL)


class ChunkedEncoder:
    """Whole-text encodings from overlapping chunks, with a sentencepiece model that keeps white space."""

    def __init__(self, model: str, chunk: int = CHUNK, overlap: int = OVERLAP):
        import sentencepiece

        self.encoder = sentencepiece.SentencePieceProcessor(model_file=model)
        self.chunk, self.overlap = chunk, overlap
        self.widened = self.whole = 0
        pieces = [self.encoder.id_to_piece(i) for i in range(self.encoder.vocab_size())]
        byte = [int(m[1], 16) if (m := re.fullmatch("<0x([0-9A-F]{2})>", p)) else -1 for p in pieces]
        #: Code points that a token covers; of a character's bytes only the first counts.
        self.length = np.array([len(p) if b < 0 else int(not 0x80 <= b <= 0xBF) for p, b in zip(pieces, byte, strict=True)])
        self.boundary = np.array([b < 0 for b in byte]) & (self.length > 0)
        self.boundary[self.encoder.unk_id()] = False

    def spans(self, text: str, at: int, end: int) -> tuple[np.ndarray, np.ndarray] | None:
        """ids and start offsets in the whole text of the tokens of text[at:end]; None if they don't add up."""
        ids = np.array(self.encoder.encode(text[at:end]), np.int64)
        ends = np.cumsum(self.length[ids])
        if ends[-1] != end - at + 1:  # the encoder's marker is one more
            return None
        return ids, at - 1 + ends - self.length[ids]

    def parts(self, text: str):
        """Runs of ids that make up the encoding of the whole text; None first if it must be encoded in one piece."""
        end = min(self.chunk, len(text))
        left = self.spans(text, 0, end)
        while left and end < len(text):
            new_end, overlap = min(len(text), end + self.chunk), self.overlap
            while True:
                start = end - overlap
                if start <= left[1][0]:
                    yield None
                    return
                right = self.spans(text, start, new_end)
                if right is None:
                    yield None
                    return
                tail = int(np.searchsorted(left[1][: len(left[0])], start))
                head = int(np.searchsorted(right[1], end))
                _, i, j = np.intersect1d(
                    np.where(self.boundary[left[0][tail:]], left[1][tail : len(left[0])] << 32 | left[0][tail:], -1 - np.arange(len(left[0]) - tail)),
                    np.where(self.boundary[right[0][1:head]], right[1][1:head] << 32 | right[0][1:head], -(1 << 62) - np.arange(max(head - 1, 0))),
                    return_indices=True,
                )
                if len(i):
                    break
                self.widened += 1
                overlap *= 2
            yield left[0][: tail + int(i[0]) + 1]
            cut = int(j[0]) + 2
            # The boundary token itself is counted; its start bounds how far a later overlap may reach.
            left, end = (right[0][cut:], np.r_[right[1][cut:], new_end]), new_end
        yield left[0] if left else None

    def ids(self, text: str) -> list[int]:
        if len(text) > self.chunk:
            runs = list(self.parts(text))
            if all(r is not None for r in runs):
                return np.concatenate(runs).tolist()
            self.whole += 1
        return self.encoder.encode(text)

    def count(self, text: str) -> int:
        if len(text) > self.chunk:
            total = 0
            for run in self.parts(text):
                if run is None:
                    self.whole += 1
                    break
                total += len(run)
            else:
                return total
        return len(self.encoder.encode(text))


def token_counts(docs: DataFrame, model: str | None = None, limit: int = LIMIT) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit for every row of ``docs`` (columns doc_id, text)."""
    model = model or default_model()
    schema = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_tokens", pa.int64()), ("over_limit", pa.bool_())])

    def make():
        encoder = ChunkedEncoder(model)

        def one(doc_id, text):
            n = encoder.count(text or "")
            return ((doc_id, len((text or "").encode()), n, n > limit),)

        return one

    return docs.selectExpr("cast(doc_id as long) doc_id", "text").mapInArrow(
        common.per_row(["doc_id", "text"], schema, make), "doc_id long, n_bytes long, n_tokens long, over_limit boolean"
    )


def op10_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts(common.table(spark, sf_dir, "documents"))
