"""Personal data found through disguises, with spans of the original text.

Method. A cascade of transducers rewrites a text and keeps, for every output character, the
source span it came from:

1. glyphs: compatibility forms (full width, mathematical), digits of any script and Cyrillic
   and Greek look-alikes become ASCII; invisible characters vanish;
2. separators: bracketed or spelled "at" and "dot" (English, German, French, Spanish) become
   @ and ., spelled ones only between words that then read like an address: both words of one
   language, a plausible top-level part at the end, and where all that could be prose ("look at
   the dot in the middle", "order at example dot com") a sign that it is none;
3. digits: letters that look like digits inside numbers become them, and in runs of number
   words, spelled "plus" and "dot" and plain digits the words become digits, however few they are;
   what guards against false hits is what an identifier must fulfil.

Identifiers are detected in the rewritten text by the same patterns as in the plain text,
and their spans are mapped back. Spans of the plain text stay as they are; a span of a
rewritten text is added if it holds a rewritten character and no span of its kind covers it. It
may therefore lie over a plain span that saw only a fragment; but one letter or number word that
stands apart from a plain span ("+1 988 555 2485 I ...") does not lengthen it.

Kinds and patterns (leftmost, without overlap inside a kind, failing matches dropped and not
retried): email; ip with parts up to 255; card of 16 to 19 digits that pass the Luhn sum; phone
of 8 to 15 digits after a plus sign. Every search is linear in the text.

Defined results: null text = empty text, no spans, the hash of the empty string; repeated
rows are separate rows; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import re
import sys
import unicodedata
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

KINDS = ("email", "ip", "card", "phone")

_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])([0-9]++)\.([0-9]++)\.([0-9]++)\.([0-9]++)")
_CARD = re.compile(r"[0-9](?:[ -]?[0-9])++")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_DIGIT = re.compile("[0-9]")

Span = tuple[int, int]


def emails(text: str) -> list[Span]:
    found, free = [], 0
    at = text.find("@")
    while at >= 0:
        start = at
        while start > free and text[start - 1] in _LOCAL:
            start -= 1
        if start < at and (m := _DOMAIN.match(text, at + 1)):
            found.append((start, m.end()))
            free = m.end()
        at = text.find("@", max(at + 1, free))
    return found


def ips(text: str) -> list[Span]:
    def small(part: str) -> bool:
        part = part.lstrip("0")
        return len(part) < 4 and int(part or 0) <= 255

    return [m.span() for m in _IP.finditer(text) if all(map(small, m.groups()))]


def luhn(digits: str) -> bool:
    values = [int(d) for d in reversed(digits)]
    return not (sum(values[::2]) + sum(2 * d - 9 * (d > 4) for d in values[1::2])) % 10


def cards(text: str) -> list[Span]:
    found = []
    for m in _CARD.finditer(text):
        if m.end() - m.start() >= 16 and m.end() - m.start() <= 37:
            digits = m[0].replace(" ", "").replace("-", "")
            if 16 <= len(digits) <= 19 and luhn(digits):
                found.append(m.span())
    return found


def phones(text: str) -> list[Span]:
    return [m.span() for m in _PHONE.finditer(text) if 8 <= sum(map(str.isdigit, m[0])) <= 15]


def detect(text: str) -> dict[str, list[Span]]:
    """The plain spans of each kind, in order."""
    digits = _DIGIT.search(text)
    return {
        "email": emails(text),
        "ip": ips(text) if digits else [],
        "card": cards(text) if digits else [],
        "phone": phones(text) if digits and "+" in text else [],
    }


# --- transducers ------------------------------------------------------------------------------

#: Letters of other scripts that look like these ASCII letters.
_LOOKALIKE = {
    "а": "a", "в": "b", "с": "c", "ԁ": "d", "е": "e", "һ": "h", "і": "i", "ј": "j", "ӏ": "l", "м": "m", "о": "o", "р": "p",
    "ԛ": "q", "ѕ": "s", "т": "t", "ѵ": "v", "ԝ": "w", "х": "x", "у": "y", "А": "A", "В": "B", "С": "C", "Е": "E", "Н": "H",
    "І": "I", "Ј": "J", "К": "K", "М": "M", "О": "O", "Р": "P", "Ѕ": "S", "Т": "T", "Х": "X", "У": "Y",
    "α": "a", "ι": "i", "κ": "k", "ν": "v", "ο": "o", "ρ": "p", "υ": "u", "ϲ": "c", "Α": "A", "Β": "B", "Ε": "E", "Ζ": "Z",
    "Η": "H", "Ι": "I", "Κ": "K", "Μ": "M", "Ν": "N", "Ο": "O", "Ρ": "P", "Τ": "T", "Υ": "Y", "Χ": "X", "ı": "i",
    "‐": "-", "‑": "-", "‒": "-", "–": "-", "−": "-", "․": ".", "。": ".", "·": ".",
}
#: Characters without width.
_INVISIBLE = "­͏​‌‍‎‏⁠﻿"

#: The spelled separators of the four languages, which "dot" goes with which "at".
_DOTS_OF = {"at": ("dot",), "ät": ("punkt", "dot"), "klammeraffe": ("punkt", "dot"), "arobase": ("point", "dot"), "arroba": ("punto", "dot")}
_AT_WORDS = "|".join(_DOTS_OF)
_DOT_WORDS = "dot|punkt|point|punto"
#: Top-level parts beside the two-letter ones, and two-letter ones that are English words.
_TOP = frozenset("com org net edu gov mil int info biz name pro app dev online site example test invalid".split())
_TOP_WORDS = frozenset("am an as at be by do go he hi if in is it la me my no of oh on or pm so to up us we".split())
#: Words that stand before "at" or behind it in prose.
_PROSE_LOCAL = frozenset(
    "about again all also anyone arrive arrived available bought buy contact everyone find found good happy he her here him i it live look looked looking looks meet met"
    " more not now online only open or order ordered out over page people point read see seen she shop shopping site sold store them there they time us visit we website work working you".split()
)
_ARTICLES = frozenset("the a an der die das ein eine le la les un une cette el los las una esta".split())
_PROSE_DOMAIN = frozenset("a all an any each every her his its least most my no node one our red some that the their these this those what which your".split())
#: The digits of the four languages.
_DIGIT_WORDS = {
    "zero": "0", "oh": "0", "one": "1", "two": "2", "three": "3", "four": "4", "five": "5", "six": "6", "seven": "7", "eight": "8", "nine": "9",
    "null": "0", "eins": "1", "zwei": "2", "zwo": "2", "drei": "3", "vier": "4", "fünf": "5", "sechs": "6", "sieben": "7", "acht": "8", "neun": "9",
    "zéro": "0", "un": "1", "deux": "2", "trois": "3", "quatre": "4", "cinq": "5", "sept": "7", "huit": "8", "neuf": "9",
    "cero": "0", "uno": "1", "dos": "2", "tres": "3", "cuatro": "4", "cinco": "5", "seis": "6", "siete": "7", "ocho": "8", "nueve": "9",
}


#: All that the glyph transducer may rewrite.
_BEYOND = re.compile("[\xad\xb7\u0100-\U0010ffff]")


@lru_cache(maxsize=1)
def _glyphs() -> dict[int, str | None]:
    """The glyph transducer, from the Unicode tables beyond Latin-1."""
    table: dict[int, str | None] = {}
    for code in range(0x100, sys.maxunicode + 1):
        c = chr(code)
        if 0xD800 <= code <= 0xDFFF:
            continue
        plain = unicodedata.normalize("NFKC", c)
        digit = unicodedata.decimal(c, None)
        if digit is not None:
            table[code] = str(digit)
        elif len(plain) == 1 and " " < plain <= "~":
            table[code] = plain
    table |= {ord(c): plain for c, plain in _LOOKALIKE.items()}
    return table | dict.fromkeys(map(ord, _INVISIBLE))


_OPEN, _CLOSE = r"[\[({<]\s{0,3}", r"\s{0,3}[\])}>]"
_BRACKETED = re.compile(rf"\s{{0,3}}{_OPEN}(?:(?P<at>{_AT_WORDS}|@)|(?:{_DOT_WORDS}|\.)){_CLOSE}\s{{0,3}}", re.I)
_PART = r"[A-Za-z0-9._%+-]{1,64}"
_DOT_SEP = rf"[ _]{{1,3}}(?:{_DOT_WORDS}|\.)[ _]{{1,3}}"
_ADDRESS = re.compile(
    rf"(?<![\w.%+-])(?P<local>{_PART}(?:[ _]{{1,3}}(?:{_DOT_WORDS})[ _]{{1,3}}{_PART}){{0,3}})(?P<at>[ _]{{1,3}}(?:(?P<word>{_AT_WORDS})|@)[ _]{{1,3}}|@)"
    rf"[A-Za-z0-9-]{{1,63}}(?P<rest>(?:(?:{_DOT_SEP}|\.)[A-Za-z0-9-]{{1,63}})+)",
    re.I,
)
_SHOUTED = re.compile(r"(?<![\w.%+-])[a-z0-9._%+-]{1,64}(?P<at>AT|@)[a-z0-9-]{1,63}(?P<rest>(?:(?:DOT|\.)[a-z0-9-]{1,63})+)(?![A-Za-z0-9])")
_DOT_IN = re.compile(_DOT_SEP, re.I)
_WORD = "|".join(sorted(map(re.escape, _DIGIT_WORDS), key=len, reverse=True))
_SEP = r"(?:[ ,-]{1,3})"
_RUN = re.compile(rf"\b(?:plus{_SEP})?(?:(?:{_WORD}|[0-9]++)\b)(?:{_SEP}(?:(?:{_WORD}|{_DOT_WORDS}|[0-9]+)\b))*", re.I)
_TOKEN = re.compile(rf"(?P<plus>plus)|(?P<word>{_WORD})|(?P<dot>{_DOT_WORDS})|(?P<digits>[0-9]+)", re.I)
#: Between a plain number and one look-alike letter or number word that is rather the prose around it.
_APART = re.compile(rf"(?:[ ,.()-]+(?:[OolI]|{_WORD}))?|(?:[OolI]|{_WORD})[ ,.()-]+", re.I)
_RUN_WORDS = frozenset(["plus", *_DIGIT_WORDS, *_DOT_WORDS.split("|")])


_SPOKEN = str.maketrans(",-+()[]:;\"!?", " " * 12)
#: Spelled "at" between any of the separators that _ADDRESS accepts.
_SPELLED_AT = tuple(f"{a}{w}{b}" for w in _AT_WORDS.split("|") for a in " _" for b in " _")


def _spelled_hint(low: str) -> bool:
    """Two neighbours that can stand inside a run, one of them a word; every run that is rewritten has them."""
    words = (low.translate(_SPOKEN) + " ").replace(". ", " ").split()
    seen = bytes([2 if w in _RUN_WORDS else "0" <= w[0] <= "9" for w in words])
    return b"\2\1" in seen or b"\1\2" in seen or b"\2\2" in seen


class Rewritten:
    """A text with the source span of every character and whether it was rewritten."""

    def __init__(self, text: str):
        self.text = text
        self.start = np.arange(len(text))
        self.end = self.start + 1
        self.changed = np.zeros(len(text), bool)

    def splice(self, edits: list[tuple[int, int, str]]) -> None:
        """Replace [a, b) by a text for each edit; edits are in order and apart."""
        if not edits:
            return
        text, start, end, changed, at = [], [], [], [], 0
        for a, b, put in edits:
            if a > at:
                text.append(self.text[at:a])
                start.append(self.start[at:a])
                end.append(self.end[at:a])
                changed.append(self.changed[at:a])
            text.append(put)
            start.append(np.full(len(put), self.start[a]))
            end.append(np.full(len(put), self.end[b - 1]))
            changed.append(np.ones(len(put), bool))
            at = b
        text.append(self.text[at:])
        start.append(self.start[at:])
        end.append(self.end[at:])
        changed.append(self.changed[at:])
        self.text = "".join(text)
        self.start, self.end, self.changed = (np.concatenate(x) for x in (start, end, changed))


def _glyph_edits(text: str) -> list[tuple[int, int, str]]:
    if text.isascii():
        return []
    if not _BEYOND.search(text):
        return []
    table = _glyphs()
    return [(m.start(), m.end(), table[ord(m[0])] or "") for m in _BEYOND.finditer(text) if ord(m[0]) in table]


def _top(label: str, sure: bool) -> bool:
    """Whether a label can end an address; ``sure`` if nothing else speaks for prose."""
    label = label.lower()
    return label in _TOP or len(label) == 2 and label.isalpha() and (sure or label not in _TOP_WORDS)


#: Just before an address: what announces one.
_CUE = re.compile(r"(?:e-?mail|mailto|correo|courriel|adresse|address|kontakt|contacto|mail|:|<)[ _]{0,3}\Z", re.I)


def _kept_dots(text: str, m: re.Match) -> list[tuple[int, int]] | None:
    """The separators behind "at" of the longest part that reads like an address; None if there is none."""
    word, local = (m["word"] or "").lower(), m["local"]
    dots = [d.span() for d in _DOT_IN.finditer(text, m.start("rest"), m.end("rest"))]
    dots += [(i, i + 1) for i in range(m.start("rest"), m.end("rest")) if text[i] == "." and not any(a <= i < b for a, b in dots)]
    dots.sort()
    spelled = [text[a:b].strip(" _") for a, b in dots]
    first = text[m.end("at") : dots[0][0]]
    sure = bool(
        not word  # an @ is no prose
        or re.search("[0-9._%+-]|[a-z][A-Z]", local) or _DOT_IN.search(local) or re.search("[0-9-]", first) or _CUE.search(text, max(0, m.start() - 12), m.start())
        or word not in ("at",) or "_" in m["at"] or m["word"].isupper() and not local.isupper()
    )
    if word and local.lower() in _ARTICLES or not sure and (local.lower() in _PROSE_LOCAL or first.lower() in _PROSE_DOMAIN):
        return None
    ends = [*(a for a, _ in dots[1:]), m.end("rest")]
    whole = False  # a plain address is complete so far
    kept = 0
    for k, ((_, b), by) in enumerate(zip(dots, spelled, strict=True)):
        apart = by != "." or dots[k][1] - dots[k][0] > 1
        if word and by != "." and by.lower() not in _DOTS_OF[word]:
            break
        if not word and m["at"] == "@" and by == "." and apart:  # a full stop apart ends the sentence
            break
        label = text[b : ends[k]]
        if whole and apart and (by.lower() != "dot" or not _top(label, False)):
            break
        if _top(label, sure):
            kept = k + 1
        whole = not word and m["at"] == "@" and all(x == "." and d[1] - d[0] == 1 for x, d in zip(spelled[: k + 1], dots, strict=False)) and _top(label, True) or whole
    if not kept or word and all(x == "." for x in spelled[:kept]):
        return None
    return dots[:kept]


def _address_edits(text: str) -> list[tuple[int, int, str]]:
    """A spelled "at" counts only with a spelled "dot" behind it: "see us at example.com" is no address."""
    edits, at = [], 0
    while m := _ADDRESS.search(text, at):
        dots = _kept_dots(text, m)
        if dots is None:
            at = m.end("local")
            continue
        edits += [(m.start("local") + d.start(), m.start("local") + d.end(), ".") for d in _DOT_IN.finditer(m["local"])]
        edits += [(m.start("at"), m.end("at"), "@")] if m["at"] != "@" else []
        edits += [(a, b, ".") for a, b in dots if b - a > 1]
        at = dots[-1][1]
    return edits


def _shouted_edits(text: str) -> list[tuple[int, int, str]]:
    edits = []
    for m in _SHOUTED.finditer(text):
        dots = [(m.start("rest") + d.start(), m.start("rest") + d.end(), ".") for d in re.finditer("DOT", m["rest"])]
        if dots and _top(re.split(r"DOT|\.", m["rest"])[-1], m["at"] == "@"):
            edits += ([(m.start("at"), m.end("at"), "@")] if m["at"] != "@" else []) + dots
    return edits


#: Letters that stand for digits inside numbers.
_LETTER_DIGITS = {"O": "0", "o": "0", "l": "1", "I": "1"}
_NUMBER_LIKE = re.compile(r"(?<![A-Za-z0-9])[0-9OolI](?:[ .()-]{0,2}[0-9OolI])++(?![A-Za-z0-9])")
_LETTER_BY_DIGIT = re.compile(r"[0-9][ .()-]{0,2}[OolI]|[OolI][ .()-]{0,2}[0-9]")


def _letter_edits(text: str) -> list[tuple[int, int, str]]:
    """O, l and I inside numbers of mostly true digits."""
    edits = []
    for m in _NUMBER_LIKE.finditer(text):
        letters = [i for i in range(m.start(), m.end()) if text[i] in _LETTER_DIGITS]
        if letters and 2 * len(letters) <= sum(c in "0123456789" for c in m[0]):
            edits += [(i, i + 1, _LETTER_DIGITS[text[i]]) for i in letters]
    return edits


#: Digits in groups of thousands: "plus 10 000 000" is a sum.
_THOUSANDS = re.compile(r"[0-9]{1,3}(?:[ ,][0-9]{3})+")


def _runs(text: str) -> Iterator[list[re.Match]]:
    """Runs of number words and plain numbers; a comma ends one unless most of its gaps have one."""
    for m in _RUN.finditer(text):
        tokens = list(_TOKEN.finditer(text, m.start(), m.end()))
        commas = [i for i in range(1, len(tokens)) if "," in text[tokens[i - 1].end() : tokens[i].start()]]
        if len(commas) > 2 and 2 * len(commas) >= len(tokens):
            commas = []
        for first, last in zip([0, *commas], [*commas, len(tokens)], strict=True):
            yield tokens[first:last]


def _digit_edits(text: str) -> list[tuple[int, int, str]]:
    """Words become digits; the space between two plain numbers of a run stays."""
    edits = []
    for tokens in _runs(text):
        while tokens and tokens[-1]["dot"]:
            tokens.pop()
        if len(tokens) < 2 or all(t["digits"] for t in tokens):
            continue
        if tokens[0]["plus"] and _THOUSANDS.fullmatch(text, tokens[1].start(), tokens[-1].end()):
            continue
        put = ["+" if t["plus"] else "." if t["dot"] else t["digits"] or _DIGIT_WORDS[t["word"].lower()] for t in tokens]
        for i, t in enumerate(tokens):  # the separator in front of a token belongs to it
            if t["digits"] and (not i or tokens[i - 1]["digits"]):
                continue
            edits.append((tokens[i - 1].end() if i else t.start(), t.end(), put[i]))
    return edits


def disguised(text: str) -> Rewritten | None:
    """The text as the transducers leave it; None if they change nothing."""
    seen = Rewritten(text)
    seen.splice(_glyph_edits(text))
    if any(c in seen.text for c in "[({<"):
        seen.splice([(m.start(), m.end(), "@" if m["at"] else ".") for m in _BRACKETED.finditer(seen.text)])
    low = seen.text.lower()
    if "@" in low or any(w in low for w in _SPELLED_AT):
        seen.splice(_address_edits(seen.text))
        low = seen.text.lower()
    if "DOT" in seen.text:
        seen.splice(_shouted_edits(seen.text))
        low = seen.text.lower()
    if _LETTER_BY_DIGIT.search(seen.text):
        seen.splice(_letter_edits(seen.text))
        low = seen.text.lower()
    if _spelled_hint(low):
        seen.splice(_digit_edits(seen.text))
    return seen if len(seen.text) != len(text) or seen.changed.any() else None


def _lengthens(text: str, kind: str, span: Span, held: Span) -> bool:
    """Whether a rewritten span that meets a held one of its kind has more of the identifier."""
    parts = text[span[0] : max(span[0], held[0])], text[min(span[1], held[1]) : span[1]]
    return any(parts) and (kind == "email" or not all(_APART.fullmatch(p) for p in parts))


def spans(text: str | None) -> tuple[dict[str, list[Span]], dict[str, list[Span]]]:
    """The plain spans of each kind, and all spans with those that the transducers add."""
    text = text or ""
    base = detect(text)
    seen = disguised(text)
    if seen is None:
        return base, base
    every = {}
    removed = np.r_[False, seen.start[1:] > seen.end[:-1]] if len(seen.text) else np.zeros(0, bool)
    for kind, found in detect(seen.text).items():
        own = list(base[kind])
        for a, b in found:
            if seen.changed[a:b].any() or removed[a + 1 : b].any():
                span = int(seen.start[a]), int(seen.end[b - 1])
                if all(span[1] <= s or e <= span[0] or _lengthens(text, kind, span, (s, e)) for s, e in own):
                    own.append(span)
        every[kind] = sorted(own)
    return base, every


def joined(found: dict[str, list[Span]]) -> str:
    return ",".join(f"{kind}:{a}:{b}" for kind in KINDS for a, b in found[kind])


def redacted(text: str | None) -> str | None:
    """The text with every span replaced by its kind in capitals and brackets; spans that meet become one."""
    if not text:
        return text
    out, at = [], 0
    runs: list[list] = []
    for a, b, kind in sorted((a, b, kind) for kind, own in spans(text)[1].items() for a, b in own):
        if runs and a < runs[-1][1]:
            runs[-1][1] = max(b, runs[-1][1])
        else:
            runs.append([a, b, kind])
    for a, b, kind in runs:
        out += [text[at:a], f"[{kind.upper()}]"]
        at = b
    return "".join([*out, text[at:]])


_SCHEMA = "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string"


def found(docs: DataFrame) -> DataFrame:
    """Counts of the plain spans, their hash, and all spans, for every row (columns doc_id, text)."""
    schema = pa.schema([("doc_id", pa.int64()), *((f"n_{k}", pa.int64()) for k in KINDS), ("base_sha256", pa.string()), ("spans", pa.string())])

    def make():
        def one(doc_id, text):
            base, every = spans(text)
            return ((doc_id, *(len(base[k]) for k in KINDS), hashlib.sha256(joined(base).encode()).hexdigest(), joined(every)),)

        return one

    return docs.selectExpr("cast(doc_id as long) doc_id", "text").mapInArrow(common.per_row(["doc_id", "text"], schema, make), _SCHEMA)


def redact(docs: DataFrame) -> DataFrame:
    """The documents with their personal data replaced and n_chars, if it is there, as the new length."""
    given = docs.select(F.struct(*docs.columns).alias("row"), F.col("text").alias("text"))

    def run(batches):
        for batch in batches:
            for part in common.slices(batch):
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([redacted(t) for t in part.column(1).to_pylist()], pa.string())], names=["row", "text"])

    done = given.mapInArrow(run, f"row {given.schema['row'].dataType.simpleString()}, text string")
    length = lambda c: F.coalesce(F.char_length("text"), F.col("row").getField(c)).cast(docs.schema[c].dataType)
    return done.select(*(F.col("text") if c == "text" else length(c).alias(c) if c == "n_chars" else F.col("row").getField(c).alias(c) for c in docs.columns))


def op3_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return found(common.table(spark, sf_dir, "documents"))
