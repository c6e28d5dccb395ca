"""Personal data in plain and in disguised writing, with offsets into the source text.

Plain identifiers are matched on the text as it is. For disguises a chain of transducers rewrites the text (homoglyphs to
ASCII, spelled digits to digits, bracketed or spaced "at" and "dot" to their signs), each step keeping for every character
of its output the source characters that it stands for. The same matchers run on the rewritten text; a match maps back to
the source span from its first to past its last character, and counts where it overlaps no plain span of its kind.
"""

from __future__ import annotations

import hashlib
import re
import unicodedata

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from . import common

# The four kinds and the patterns that define them.
KINDS = ("email", "ip", "card", "phone")
PATTERNS = {
    "email": re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"),
    "ip": re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"),
    "card": re.compile(r"[0-9]([\x20-]?[0-9])+"),
    "phone": re.compile(r"\+[0-9][\x20().0-9-]+[0-9]"),
}
# Letters of other scripts that look like ASCII ones, side by side.
LOOKALIKES = dict(zip("аеорсухіјѕԁһԛԝАВЕКМНОРСТХІЈЅαοριντυκΑΒΕΖΗΙΚΜΝΟΡΤΥΧ", "aeopcyxijsdhqwABEKMHOPCTXIJSaopivtukABEZHIKMNOPTYX", strict=True))
# The names of the digits in the four languages of the corpus.
DIGIT_NAMES = {
    name: str(i)
    for names in (
        "zero one two three four five six seven eight nine",
        "null eins zwei drei vier fünf sechs sieben acht neun",
        "zéro un deux trois quatre cinq six sept huit neuf",
        "cero uno dos tres cuatro cinco seis siete ocho nueve",
    )
    for i, name in enumerate(names.split())
} | {"oh": "0"}
_NAME = "|".join(sorted(DIGIT_NAMES, key=len, reverse=True))
# Names of the highest level that a spelled-out address may end in; those that are words as well are left out.
_TOP = "com|org|net|edu|gov|mil|int|info|biz|name|io|co|uk|de|fr|es|eu|nl|ch|se|dk|pl|pt|br|mx|ca|au|jp|cn|ru|example|test|invalid|localhost"
#: Signs in brackets count anywhere; capitals between spaces only where a name and a host could stand beside them.
_AT = r"(?i:\s*[\[({<]\s*(?:at|@|arroba|chez)\s*[\])}>]\s*)|(?<=[A-Za-z0-9._%+-])\s+AT\s+(?=[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]|\s+(?:DOT|dot)\s+[A-Za-z]|\s*[\[({<]))"
_DOT_IN_BRACKETS = r"(?i:\s*[\[({<]\s*(?:dot|\.|punkt|point|punto)\s*[\])}>]\s*)"
_DOT = _DOT_IN_BRACKETS + r"|(?<=[A-Za-z0-9-])\s+DOT\s+(?=[A-Za-z0-9])"
#: What may stand between spelled digits; a spelled or bracketed dot as well.
_JOIN = rf"(?:{_DOT_IN_BRACKETS}|\s+(?:dot|punkt|point|punto)\s+|[ \-.,]{{1,3}})"
#: Three or more digits in a row, at least two of them spelled, are a spelled number; a "plus" before it is its sign.
SPELLED = re.compile(rf"(?<!\w)(plus[ \-]{{1,3}}|más[ \-]{{1,3}})?(?:(?:{_NAME}|[0-9]){_JOIN}){{2,}}(?:{_NAME}|[0-9])(?!\w)", re.I)
DIGIT = re.compile(rf"({_NAME}|[0-9])({_JOIN}?)", re.I)
#: Bare "at" and "dot" only in "name at host dot top".
BARE = re.compile(rf"([A-Za-z0-9._%+-]+)(\s+at\s+|\s*@\s*)(?!(?:the|a|an|this|that|my|our|your)\s)((?:[A-Za-z0-9-]+\s+dot\s+)+)((?:{_TOP})(?![A-Za-z0-9]))", re.I)
SIGNS = re.compile(f"(?P<at>{_AT})|(?P<dot>{_DOT})")


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        n = ord(c) - 48
        total += n if i % 2 == 0 else n * 2 - 9 * (n > 4)
    return total % 10 == 0


def holds(kind: str, match: str) -> bool:
    """What a match must satisfy beyond its pattern."""
    if kind == "email":
        return True
    if kind == "ip":
        return all(len(p.lstrip("0")) <= 3 and int(p) <= 255 for p in match.split("."))
    digits = "".join(c for c in match if "0" <= c <= "9")
    return 9 <= len(digits) <= 15 if kind == "phone" else 13 <= len(digits) <= 19 and luhn(digits)


def plain_spans(text: str) -> dict[str, list[tuple[int, int]]]:
    """Leftmost non-overlapping matches of each kind; one that fails its test is dropped and not tried again."""
    need = {"email": "@", "ip": ".", "card": "", "phone": "+"}
    return {k: [m.span() for m in PATTERNS[k].finditer(text) if holds(k, m[0])] if need[k] in text else [] for k in KINDS}


class Tape:
    """A text and, for each of its characters, the half-open source range that it stands for."""

    def __init__(self, text: str, spans: list[tuple[int, int]] | None = None):
        self.text = text
        self.spans = spans or [(i, i + 1) for i in range(len(text))]

    def rewritten(self, pieces: list[tuple[int, int, str]]) -> Tape:
        """Each (start, end, new) replaces that range; every new character stands for the whole range."""
        text, spans, at = [], [], 0
        for start, end, new in pieces:
            source = (self.spans[start][0], self.spans[end - 1][1])
            text += (self.text[at:start], new)
            spans += [*self.spans[at:start], *[source] * len(new)]
            at = end
        return Tape("".join([*text, self.text[at:]]), spans + self.spans[at:])


def ascii_twin(c: str) -> str:
    """What an odd character is a disguise of: a lookalike's letter, a digit of another script, a wide form; or nothing."""
    if c in LOOKALIKES:
        return LOOKALIKES[c]
    if (d := unicodedata.digit(c, None)) is not None and unicodedata.category(c) == "Nd":
        return str(d)
    folded = unicodedata.normalize("NFKC", c)
    return folded if folded != c and folded.isascii() and folded.strip() else ""


ODD = re.compile(r"[^\x00-ɏ‐-‧€]")
INVISIBLE = re.compile("[­​-‏⁠﻿]+")


def unhomoglyph(tape: Tape) -> Tape:
    """Lookalike letters to ASCII, in words that also have ASCII letters, digits or signs of an address; invisible characters go."""
    pieces = [(m.start(), m.end(), "") for m in INVISIBLE.finditer(tape.text)]
    for m in re.finditer(r"\S+", tape.text):
        if ODD.search(m[0]) and (re.search(r"[@0-9]|[A-Za-z]\.|\.[A-Za-z]|[A-Za-z]", m[0]) or any(unicodedata.category(c) == "Nd" or "＀" <= c <= "￯" for c in m[0])):
            pieces += [(i, i + 1, twin) for i, c in enumerate(m[0], m.start()) if c > "ɏ" and not INVISIBLE.match(c) and (twin := ascii_twin(c))]
    return tape.rewritten(sorted(pieces)) if pieces else tape


def undigit(tape: Tape) -> Tape:
    """Runs of spelled digits to digits; what joins them goes, but for dots, which numbers of four parts keep."""
    pieces = []
    for m in SPELLED.finditer(tape.text):
        if sum(not x[0].isdigit() for x in DIGIT.findall(m[0])) < 2:
            continue
        if m[1]:
            pieces.append((*m.span(1), "+"))
        for d in DIGIT.finditer(m[0]):
            start, end = m.start() + d.start(), m.start() + d.start() + len(d[1])
            pieces.append((start, end, d[1] if d[1].isdigit() else DIGIT_NAMES[d[1].lower()]))
            if d[2] and m.start() + d.end() < m.end():
                pieces.append((end, m.start() + d.end(), "." if d[2] == "." or any(c.isalpha() or c in "[({<" for c in d[2]) else ""))
    return tape.rewritten(pieces) if pieces else tape


def unsign(tape: Tape) -> Tape:
    """Disguised signs of an address to the signs."""
    pieces = [(m.start(), m.end(), "@" if m["at"] else ".") for m in SIGNS.finditer(tape.text)]
    taken = [(a, b) for a, b, _ in pieces]
    for m in BARE.finditer(tape.text):
        new = [(m.start(2), m.end(2), "@")] + [(m.start(3) + d.start(), m.start(3) + d.end(), ".") for d in re.finditer(r"\s+dot\s+", m[3], re.I)]
        pieces += [p for p in new if not any(p[0] < b and a < p[1] for a, b in taken)]
    return tape.rewritten(sorted(pieces)) if pieces else tape


_DIGIT_WORDS = {*DIGIT_NAMES, *"0123456789"}
_DOT_WORDS = {"dot", "punkt", "point", "punto"}
_WORDS = re.compile(r"\w+")


def disguised(text: str) -> bool:
    """Whether any transducer could change the text: the patterns of the transducers, behind cheap tests that pass all they match."""
    if not text.isascii() and (ODD.search(text) or INVISIBLE.search(text)):
        return True
    low = text.casefold()
    if ("at" in low or "@" in low or "dot" in low or any(c in low for c in "[({<")) and (SIGNS.search(text) or ("dot" in low and BARE.search(text))):
        return True
    # each digit of a spelled number is a word of its own, with nothing but signs and dots between
    found = [w for w in _WORDS.findall(low) if w not in _DOT_WORDS]
    return b"\1\1\1" in bytes(map(_DIGIT_WORDS.__contains__, found)) and SPELLED.search(text) is not None


def all_spans(text: str) -> tuple[dict[str, list[tuple[int, int]]], dict[str, list[tuple[int, int]]]]:
    """Plain spans, and plain with added ones, each sorted by start."""
    base = plain_spans(text)
    if not disguised(text):
        return base, base
    tape = unsign(undigit(unhomoglyph(Tape(text))))
    if tape.text == text:
        return base, base
    found = {k: list(v) for k, v in base.items()}
    for kind, spans in plain_spans(tape.text).items():
        for a, b in spans:
            start, end = tape.spans[a][0], tape.spans[b - 1][1]
            if all(end <= x or y <= start for x, y in found[kind]):
                found[kind].append((start, end))
        found[kind].sort()
    return base, found


def digest(spans: dict[str, list[tuple[int, int]]]) -> str:
    return ",".join(f"{kind}:{a}:{b}" for kind in KINDS for a, b in spans[kind])


RESULT = "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_added long, n_spans long"
NAMES = [c.split()[0] for c in RESULT.split(", ")]


def personal_data(docs: DataFrame) -> DataFrame:
    """One row a document: counts and digest of the plain spans, and all spans (code points, end exclusive).

    n_email, n_ip, n_card and n_phone count plain spans; n_added counts those that only the rewritten text shows, n_spans
    all. Null and
    empty texts have no spans; repeated rows are kept; an empty table gives no rows.
    """

    def run(batches):
        for batch in batches:
            columns: list[list] = [[] for _ in NAMES[1:]]
            for text in batch.column(1).to_pylist():
                base, found = all_spans(text)
                plain = digest(base)
                row = (*(len(base[k]) for k in KINDS), hashlib.sha256(plain.encode()).hexdigest(), plain if found is base else digest(found), sum(map(len, found.values())) - sum(map(len, base.values())), sum(map(len, found.values())))
                for column, value in zip(columns, row, strict=True):
                    column.append(value)
            kinds = [pa.int64()] * 4 + [pa.string()] * 2 + [pa.int64()] * 2
            yield pa.RecordBatch.from_arrays([batch.column(0), *map(pa.array, columns, kinds)], NAMES)

    return common.mapped(common.texts(docs), run, RESULT)


def masked(docs: DataFrame) -> DataFrame:
    """doc_id and text with every found span replaced by its kind in brackets."""

    def run(batches):
        for batch in batches:
            out = []
            for text in batch.column(1).to_pylist():
                _, found = all_spans(text)
                at, parts = 0, []
                for a, b, kind in sorted((a, b, kind) for kind in KINDS for a, b in found[kind]):
                    if a >= at:
                        parts += (text[at:a], f"[{kind}]")
                        at = b
                out.append("".join([*parts, text[at:]]))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.string())], ["doc_id", "text"])

    return common.mapped(common.texts(docs), run, "doc_id long, text string")


def op4_pii_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return personal_data(common.read(spark, sf_dir, "documents"))
