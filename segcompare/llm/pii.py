"""Personal data in texts, plain and disguised, with spans in the source's characters.

Plain identifiers are found in the source text itself. For disguised ones a chain of transducers rewrites
the text (look-alike characters, digits spelled as words, written-out or bracketed "at" and "dot") and keeps,
for each piece of its output, the source characters it came from. The same detectors then run over the
rewritten text, and what they find is carried back to source spans; only finds that touch a rewritten piece
and overlap no plain find of their kind are added.

Defined results: a null or empty text has no spans; rows are independent, so ties, repeated rows, null ids
and other columns change nothing; an empty table gives no rows; equal finds of two kinds are both given. Names, hosts
and blanks of any length are read.
"""

from __future__ import annotations

import bisect
import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

from .words import chunks

KINDS = ("email", "ip", "card", "phone")
COLUMNS = "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_added long"
Span = tuple[str, int, int]

_LOCAL = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-"
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])[0-9]+\.[0-9]+\.[0-9]+\.[0-9]+")
_CARD = re.compile(r"[0-9](?:[ -]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_DIGITS = re.compile("[0-9]")


def _emails(text: str) -> list[Span]:
    out, end, at = [], 0, text.find("@")
    while at >= 0:
        begin = at
        while begin > end and text[begin - 1] in _LOCAL:
            begin -= 1
        found = _DOMAIN.match(text, at + 1) if begin < at else None
        if found:
            out.append(("email", begin, found.end()))
            end = found.end()
        at = text.find("@", max(at + 1, end))
    return out


def passes_luhn(digits: str) -> bool:
    values = [int(c) for c in reversed(digits)]
    return (sum(values[::2]) + sum(sum(divmod(2 * v, 10)) for v in values[1::2])) % 10 == 0


def detect(text: str) -> list[Span]:
    """Plain identifiers: leftmost, not overlapping within a kind, in the order of KINDS, then of start."""
    out = _emails(text)
    if not _DIGITS.search(text):
        return out
    for m in _IP.finditer(text):
        if all(len(p.lstrip("0")) <= 3 and int(p) <= 255 for p in m[0].split(".")):
            out.append(("ip", m.start(), m.end()))
    for m in _CARD.finditer(text):
        if m.end() - m.start() >= 16:
            digits = m[0].replace(" ", "").replace("-", "")
            if 16 <= len(digits) <= 19 and passes_luhn(digits):
                out.append(("card", m.start(), m.end()))
    if "+" in text:
        for m in _PHONE.finditer(text):
            if 8 <= sum(c.isdigit() for c in m[0]) <= 15:
                out.append(("phone", m.start(), m.end()))
    return out


# Look-alikes of ASCII characters; whole ranges follow by rule below.
LOOK_ALIKES = {
    "а": "a", "е": "e", "о": "o", "р": "p", "с": "c", "у": "y", "х": "x", "і": "i", "ѕ": "s", "ј": "j", "һ": "h", "ԁ": "d", "ԛ": "q", "ԝ": "w",
    "А": "A", "В": "B", "Е": "E", "К": "K", "М": "M", "Н": "H", "О": "O", "Р": "P", "С": "C", "Т": "T", "Х": "X", "У": "Y", "І": "I", "Ѕ": "S", "Ј": "J",
    "ο": "o", "α": "a", "ι": "i", "ν": "v", "ρ": "p", "υ": "u", "κ": "k", "Ο": "O", "Α": "A", "Β": "B", "Ε": "E", "Ι": "I", "Κ": "K", "Μ": "M", "Ν": "N", "Τ": "T", "Χ": "X",
    "ı": "i", "ɡ": "g", "ⅼ": "l", "․": ".", "。": ".", "｡": ".", "﹒": ".", "·": ".", "﹫": "@", "−": "-", "﹣": "-", "﹢": "+",
}
#: Characters that show nothing and are dropped.
_INVISIBLE = "­​‌‍⁠﻿"
_DIGIT_ROWS = (0x0660, 0x06F0, 0x0966, 0x2080, *range(0x1D7CE, 0x1D800, 10))
_MAP = {ord(k): v for k, v in LOOK_ALIKES.items()}
_MAP |= {0xFF01 + k: chr(0x21 + k) for k in range(94)}
_MAP |= {row + k: str(k) for row in _DIGIT_ROWS for k in range(10)}
_MAP |= {c: " " for c in (0xA0, *range(0x2000, 0x200B), 0x202F, 0x3000)} | {c: "-" for c in range(0x2010, 0x2016)}
_MAPPED = re.compile("[" + "".join(map(re.escape, map(chr, _MAP))) + _INVISIBLE + "]")
_INVISIBLES = re.compile(f"[{_INVISIBLE}]+")

# Names of the digits 0 to 9.
_NAMES = {
    "en": "zero one two three four five six seven eight nine",
    "de": "null eins zwei drei vier fünf sechs sieben acht neun",
    "fr": "zéro un deux trois quatre cinq six sept huit neuf",
    "es": "cero uno dos tres cuatro cinco seis siete ocho nueve",
}
_VALUE = {name: str(k) for names in _NAMES.values() for k, name in enumerate(names.split())} | {"oh": "0"}
_NAME = "(?:" + "|".join(sorted(_VALUE, key=len, reverse=True)) + ")"
_POINT = {"dot", "point", "punkt", "punto"}
_SPELLED = re.compile(rf"(?<!\w)(?:(?:plus|{_NAME}|[0-9]+)(?!\w)[\s,-]{{1,3}}){{2,}}(?:(?:{'|'.join(_POINT)}|{_NAME}|[0-9]+)(?!\w)[\s,-]{{1,3}})*(?:{_NAME}|[0-9]+)(?!\w)", re.I)
_TWO_NAMES = re.compile(rf"(?<!\w){_NAME}[\s,-]{{1,3}}{_NAME}(?!\w)", re.I)
_ITEM = re.compile(r"\w+")

# blanks are taken whole and from their first one on, so that no long run of them is read more than once
_OPEN, _SHUT = r"[(\[{<][ \t]*+", r"[ \t]*+[)\]}>][ \t]*+"
_AT = rf"(?:(?<![ \t])[ \t]*+(?:{_OPEN}(?:at|@|arroba){_SHUT}|(?<=[ \t])at[ \t]++|@[ \t]*+))"
_DOT = rf"(?:(?<![ \t])[ \t]*+(?:{_OPEN}(?:dot|punkt|point|punto|\.){_SHUT}|(?<=[ \t])(?:dot|punkt|punto)[ \t]++|(?<![ \t])\.))"
_HINT = re.compile(r"[(\[{<][ \t]*+(?:at|@|arroba|dot|punkt|point|punto|\.)[ \t]*+[)\]}>]|[ \t](?:dot|punkt|punto)[ \t]|[ \t]@|@[ \t]", re.I)
_AT_MARK = re.compile(_AT, re.I)
_NAME_CHAIN = re.compile(rf"(?<![A-Za-z0-9_%+-])[A-Za-z0-9_%+-]++(?:{_DOT}[A-Za-z0-9_%+-]++)*+", re.I)
_HOST_CHAIN = re.compile(rf"[A-Za-z0-9-]++(?:{_DOT}[A-Za-z0-9-]++)++", re.I)
_QUAD = re.compile(rf"(?<![0-9])[0-9]{{1,3}}(?:{_DOT}[0-9]{{1,3}}){{3}}(?![0-9])", re.I)
# Last labels that let a bare "at ... dot ..." count as an address.
_ENDINGS = set("com org net edu gov mil int info biz io co ai dev app me tv eu de fr es uk us ca it nl be ch at pl se no dk fi pt br mx ar in jp cn ru au nz example test invalid local".split())
_DOT_MARK = re.compile(_DOT, re.I)
_MARK = re.compile(rf"(?P<at>{_AT})|(?P<dot>{_DOT})", re.I)


class Rewriting:
    """A text and, piece by piece, the source span each part of it came from."""

    def __init__(self, text: str):
        self.text = text
        self.pieces = [(0, 0, len(text), True)]  # start here, source start, source end, characters kept one for one
        self.starts = [0]

    def source(self, start: int, end: int) -> tuple[int, int, bool]:
        """Source span of a part, and whether a rewritten piece lies in it."""
        a, b = bisect.bisect_right(self.starts, start) - 1, bisect.bisect_right(self.starts, end - 1) - 1
        at, lo, hi, plain = self.pieces[a]
        begin = lo + (start - at) if plain else lo
        at, lo, hi, plain_b = self.pieces[b]
        stop = lo + (end - at) if plain_b else hi
        return begin, stop, not all(p[3] for p in self.pieces[a : b + 1])

    def replace(self, edits: list[tuple[int, int, str]]) -> None:
        """edits: (start, end, new text), in order, not overlapping."""
        if not edits:
            return
        out, pieces, at, size = [], [], 0, 0

        def keep(lo: int, hi: int) -> None:
            nonlocal size
            while lo < hi:
                k = bisect.bisect_right(self.starts, lo) - 1
                here, s, e, plain = self.pieces[k]
                stop = min(hi, self.starts[k + 1] if k + 1 < len(self.starts) else len(self.text))
                pieces.append((size, s + lo - here, s + stop - here, True) if plain else (size, s, e, False))
                out.append(self.text[lo:stop])
                size += stop - lo
                lo = stop

        for start, end, new in edits:
            keep(at, start)
            if new:
                begin, stop, _ = self.source(start, end)
                pieces.append((size, begin, stop, False))
                out.append(new)
                size += len(new)
            at = end
        keep(at, len(self.text))
        self.text, self.pieces, self.starts = "".join(out), pieces, [p[0] for p in pieces]


def _spelled(text: str) -> list[tuple[int, int, str]]:
    edits = []
    for m in _SPELLED.finditer(text):
        items = [x[0].lower() for x in _ITEM.finditer(m[0])]
        if sum(x in _VALUE for x in items) >= 3:
            edits.append((m.start(), m.end(), "".join(_VALUE.get(x, "+" if x == "plus" else "." if x in _POINT else x) for x in items)))
    return edits


def _addresses(text: str) -> list[tuple[int, int]]:
    """Spans of addresses with a written-out mark: a chain of names that ends at an "at", and a chain of host labels after it."""
    spans, done = [], 0
    for m in _AT_MARK.finditer(text):
        if m.start() < done:
            continue
        begin, done = done, m.end()
        names = None
        for names in _NAME_CHAIN.finditer(text, begin, m.start()):
            pass
        host = _HOST_CHAIN.match(text, m.end()) if names and names.end() == m.start() else None
        if not host:
            continue
        mark = m[0].strip().lower()
        dots = [x[0] for x in _DOT_MARK.finditer(host[0]) if x[0] != "."]
        ending = re.split(_DOT, host[0], flags=re.I)[-1].lower()
        if mark == "at" and (not dots or ending not in _ENDINGS):
            continue  # "look at one dot on the map"
        if dots or m[0] != "@" or any(x[0] != "." for x in _DOT_MARK.finditer(names[0])):
            spans.append((names.start(), host.end()))
            done = host.end()
    return spans


def _marks(text: str) -> list[tuple[int, int, str]]:
    spans = _addresses(text)
    spans += [(m.start(), m.end()) for m in _QUAD.finditer(text) if m[0].count(".") < 3 or not re.fullmatch(r"[0-9.]+", m[0])]
    edits, last = [], 0
    for lo, hi in sorted(spans):
        for m in _MARK.finditer(text, max(lo, last), hi):
            if m[0] not in "@.":
                edits.append((m.start(), m.end(), "@" if m["at"] else "."))
                last = m.end()
    return edits


def normalise(text: str) -> Rewriting | None:
    """The rewritten text, or None where no transducer has anything to do."""
    now = Rewriting(text)
    if not text.isascii() and _MAPPED.search(text):
        changed = text.translate(_MAP)
        now.text = changed  # one character for one; these places count as rewritten
        places = [m.start() for m in _MAPPED.finditer(text)]
        pieces, at = [], 0
        for p in places:
            if p > at:
                pieces.append((at, at, p, True))
            pieces.append((p, p, p + 1, False))
            at = p + 1
        if at < len(text):
            pieces.append((at, at, len(text), True))
        now.pieces, now.starts = pieces, [p[0] for p in pieces]
        now.replace([(m.start(), m.end(), "") for m in _INVISIBLES.finditer(changed)])
    if _TWO_NAMES.search(now.text):
        now.replace(_spelled(now.text))
    if _HINT.search(now.text):
        now.replace(_marks(now.text))
    return None if len(now.pieces) == 1 and now.pieces[0][3] else now


def find_identifiers(text: str | None) -> tuple[list[Span], list[Span]]:
    """(plain spans, spans added by deobfuscation), both in source characters."""
    base = detect(text or "")
    now = normalise(text) if text else None
    if now is None:
        return base, []
    taken = {kind: [s[1:] for s in base if s[0] == kind] for kind in KINDS}  # in order, not overlapping
    added = []
    for kind, lo, hi in detect(now.text):
        begin, end, rewritten = now.source(lo, hi)
        k = bisect.bisect_left(taken[kind], (begin, end))
        free = (k == 0 or taken[kind][k - 1][1] <= begin) and (k == len(taken[kind]) or taken[kind][k][0] >= end)
        if rewritten and free:
            taken[kind].insert(k, (begin, end))
            added.append((kind, begin, end))
    return base, added


def written(spans: list[Span]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in sorted(spans, key=lambda s: (KINDS.index(s[0]), s[1])))


def mask(text: str, spans: list[Span]) -> str:
    """text with each span replaced by its kind in capitals; overlapping spans become one."""
    out, at = [], 0
    for kind, a, b in sorted(spans, key=lambda s: (s[1], -s[2])):
        if a >= at:
            out += [text[at:a], f"<{kind.upper()}>"]
        at = max(at, b)
    return "".join([*out, text[at:]])


def personal_data(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of docs: counts and digest of the plain spans, all spans, number of added ones."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in chunks(batches):
            rows = []
            for text in batch.column(1).to_pylist():
                base, added = find_identifiers(text)
                counts = [sum(s[0] == k for s in base) for k in KINDS]
                rows.append((*counts, hashlib.sha256(written(base).encode()).hexdigest(), written(base + added), len(added)))
            kinds = [*[pa.int64()] * 4, pa.string(), pa.string(), pa.int64()]
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True))], names=[c.split()[0] for c in COLUMNS.split(", ")])

    return docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text")).mapInArrow(run, COLUMNS)


def mask_documents(docs: DataFrame, text_col: str = "text", chars_col: str = "n_chars") -> DataFrame:
    """docs with every found span masked in the text (and the character count renewed); all columns and rows stay."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in chunks(batches, text_col):
            names, columns = batch.schema.names, list(batch.columns)
            k = names.index(text_col)
            texts = columns[k].to_pylist()
            new = [t if not t else mask(t, [s for part in find_identifiers(t) for s in part]) for t in texts]
            columns[k] = pa.array(new, batch.schema.field(k).type)
            if chars_col in names and pa.types.is_integer(batch.schema.field(chars_col).type):
                c = names.index(chars_col)
                columns[c] = pa.array([old if a == b else len(b) for a, b, old in zip(texts, new, columns[c].to_pylist(), strict=True)], batch.schema.field(c).type)
            yield pa.RecordBatch.from_arrays(columns, schema=batch.schema)

    return docs.mapInArrow(run, docs.schema)
