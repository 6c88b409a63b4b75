import itertools
import math
import random
import struct

import numpy as np
import pytest
import sentencepiece

from cyclefold.llm import sentencepiece_fst as fst


@pytest.fixture(scope="module")
def machine():
    return fst.compiled(fst.default_model())


@pytest.fixture(scope="module")
def library():
    return sentencepiece.SentencePieceProcessor(model_file=fst.default_model())


def samples():
    draw = random.Random(11)
    yield from ("", " ", "  ", "a", " a", "a ", "▁", "a▁b", "▁▁x", "<s> </s> <unk> <0x41>", "\x00", "\n\n\t ", "日本語 テキスト", "😀👩‍👩‍👧 𓀀", "Größe naïve", "xxxxxxxxxxxxxxxxxxxxxxxx", "ﬁ ½ é")
    alphabets = ["abcdefgh ", "the and ing er on ", "éèêçüßöäñ ", " \n\t", "aaaaab", "0123456789.", "日本語中文字", "😀𓀀x ", "ABCdef-_'\" "]
    for k in range(1500):
        chars = alphabets[k % len(alphabets)] + (draw.choice(alphabets) if k % 3 == 0 else "")
        yield "".join(draw.choice(chars) for _ in range(draw.randrange(1, 60)))


def test_same_ids_and_texts_as_the_library(machine, library):
    assert machine.by_word
    for text in samples():
        ids = machine.encode(text)
        want = library.encode(text)
        assert np.frombuffer(ids, "<u4").tolist() == want, repr(text)
        assert machine.decode(ids) == library.decode(want) == text.replace("▁", " "), repr(text)


def test_words_and_whole_texts_have_one_path(machine):
    for text in itertools.islice(samples(), 0, None, 7):
        whole = machine.normalised(text)
        assert machine.path(whole) == [p for w in fst._words(whole) for p in machine.path(w)]
        assert machine.path(whole) == machine.merged(list(whole))


def test_invalid_byte_pieces(machine, library):
    for raw in ([0xE6, 0x97], [0x41, 0xFF, 0xC3, 0xA9, 0xC3]):
        ids = [machine.bytes[b] for b in raw]
        assert machine.decode(struct.pack(f"<{len(ids)}I", *ids)) == library.decode(ids)


def field(number, value):
    def varint(n):
        out = b""
        while n > 127:
            out += bytes([n & 127 | 128])
            n >>= 7
        return out + bytes([n])

    if isinstance(value, float):
        return varint(number << 3 | 5) + struct.pack("<f", value)
    if isinstance(value, int):
        return varint(number << 3) + varint(value)
    return varint(number << 3 | 2) + varint(len(value)) + value


def test_unigram_paths_against_all_segmentations():
    pieces = [("<unk>", 0.0, 2)] + [(p, -s, 1) for p, s in (("a", 3.0), ("b", 3.5), ("ab", 4.0), ("ba", 4.5), ("▁", 2.0), ("▁a", 3.25), ("aba", 7.0), ("bb", 6.125))]
    proto = b"".join(field(1, field(1, p.encode()) + field(2, s) + field(3, t)) for p, s, t in pieces) + field(2, field(3, 1)) + field(3, field(3, 1) + field(4, 0))
    machine = fst.Machine(proto)
    score = {p: s for p, s, _ in pieces[1:]}
    draw = random.Random(3)
    for _ in range(200):
        text = machine.normalised("".join(draw.choice("ab c") for _ in range(draw.randrange(1, 9))))
        best = math.inf
        for cuts in itertools.product((0, 1), repeat=len(text) - 1):
            at = [0, *(i + 1 for i, c in enumerate(cuts) if c), len(text)]
            parts = [text[a:b] for a, b in itertools.pairwise(at)]
            if all(p in score or len(p) == 1 for p in parts):
                best = min(best, sum(-score.get(p, machine.worst) for p in parts))
        assert abs(sum(-score.get(p, machine.worst) for p in machine.path(text)) - best) < 1e-9


def test_tables(spark):
    rows = [(1, None, 9), (2, "", 9), (3, "a b", 9), (3, "a b", 9), (None, "ü " * 9000, 9)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, ids int")
    ids = fst.encoded(docs)
    back = sorted((str(r.doc_id), r.text) for r in fst.decoded(ids).collect())
    assert back == sorted((str(d), t or "") for d, t, _ in rows)
    assert fst.encoded(docs.limit(0)).count() == 0
