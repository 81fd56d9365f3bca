"""Personal data with offset-preserving deobfuscation.

Base detectors work on the text as it is. Beside them a transducer rewrites
the disguised stretches of a text (homoglyphs, spelled digits, ``at``/``dot``
words and brackets) and keeps for each character of its output the stretch of
the source it came from. The detectors run again on that output, and the spans
found are mapped back to source characters. A mapped span counts if it touches
no base span of its kind, so base spans are never changed.

Offsets are code points, ends exclusive. Null texts are empty and have no
span; whole texts of any length are read; each row is judged for itself.
"""

from __future__ import annotations

import hashlib
import re
from bisect import bisect_right
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

KINDS = ("email", "ip", "card", "phone")

# Detectors, digit words, look-alike letters.
EMAIL = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
IP = re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
DIGITS = {"zero": "0", "one": "1", "two": "2", "three": "3", "four": "4", "five": "5", "six": "6", "seven": "7", "eight": "8", "nine": "9",
          "null": "0", "eins": "1", "zwei": "2", "drei": "3", "vier": "4", "fünf": "5", "sechs": "6", "sieben": "7", "acht": "8", "neun": "9",
          "zéro": "0", "un": "1", "deux": "2", "trois": "3", "quatre": "4", "cinq": "5", "sept": "7", "huit": "8", "neuf": "9",
          "cero": "0", "uno": "1", "dos": "2", "tres": "3", "cuatro": "4", "cinco": "5", "seis": "6", "siete": "7", "ocho": "8", "nueve": "9"}
LOOK_ALIKE = dict(zip("АВЕЅІЈКМНОРСТУХЗаеорсухіјѕԁһԛԝ" "ΑΒΕΖΗΙΚΜΝΟΡΤΥΧοαν" "․。．﹒＠﹫‐‑–−＋﹢＿", "ABESIJKMHOPCTYX3aeopcyxijsdhqw" "ABEZHIKMNOPTYXoav" "....@@----++_"))
LOOK_ALIKE |= {chr(0xFF10 + i): str(i) for i in range(10)} | {chr(0x660 + i): str(i) for i in range(10)}
LOOK_ALIKE |= {chr(0xFF21 + i): chr(65 + i) for i in range(26)} | {chr(0xFF41 + i): chr(97 + i) for i in range(26)}

_WORD = "|".join(sorted(DIGITS, key=len, reverse=True))
_SPELLED = rf"(?<![^\W_])(?:{_WORD})(?:[ ,.-]{{1,2}}(?:{_WORD}|[0-9]+))+(?![^\W_])"
_AT = r"\s*[\[({<]\s*(?:at|ät|arroba|arobase|klammeraffe)\s*[\])}>]\s*"
_DOT = r"\s*[\[({<]\s*(?:dot|punkt|point|punto|\.)\s*[\])}>]\s*"
_SAID = r"(?<=[A-Za-z0-9_%+-]) +(?:at|AT|arroba|arobase) +(?=[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)* +(?:dot|DOT|punkt|point|punto) +[A-Za-z])"
_SAID_DOT = r"(?<=[A-Za-z0-9]) +(?:dot|DOT|punkt|point|punto) +(?=[A-Za-z0-9])"
_ALIKE = "[" + re.escape("".join(LOOK_ALIKE)) + "]"
STRETCH = re.compile(rf"(?P<spelled>{_SPELLED})|(?P<at>{_AT}|{_SAID})|(?P<dot>{_DOT}|{_SAID_DOT})|(?P<alike>{_ALIKE})", re.IGNORECASE)
_RUN = re.compile(r"[A-Za-z0-9._%+@-]*")
_RUN_CHARS = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+@-")
_HAS_DIGIT = re.compile("[0-9]")
_PIECE = re.compile(rf"{_WORD}|[0-9]+", re.IGNORECASE)


def luhn(digits: str) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = int(c) * (1 + k % 2)
        total += d - 9 * (d > 9)
    return total % 10 == 0


def _small(part: str) -> bool:
    part = part.lstrip("0")
    return len(part) <= 3 and int(part or 0) <= 255


def detect(text: str) -> dict[str, list[tuple[int, int]]]:
    """Spans of each kind, from left to right; matches that fail a test are dropped."""
    out: dict[str, list[tuple[int, int]]] = {k: [] for k in KINDS}
    at, done = text.find("@"), 0
    while at >= 0:  # an e-mail address lies in one run of its characters
        start = at
        while start > done and text[start - 1] in _RUN_CHARS:
            start -= 1
        done = _RUN.match(text, start).end()
        out["email"] += [m.span() for m in EMAIL.finditer(text, start, done)]
        at = text.find("@", max(done, at + 1))
    if _HAS_DIGIT.search(text):
        out["ip"] = [m.span() for m in IP.finditer(text) if all(map(_small, m[0].split(".")))]
        for m in CARD.finditer(text):
            digits = m[0].replace(" ", "").replace("-", "")
            if 13 <= len(digits) <= 19 and luhn(digits):
                out["card"].append(m.span())
        if "+" in text:
            out["phone"] = [m.span() for m in PHONE.finditer(text) if 9 <= sum("0" <= c <= "9" for c in m[0]) <= 15]
    return out


def transduce(text: str) -> tuple[str, list[tuple[int, int, int, int]]]:
    """The rewritten text and the rewritten stretches: (start, end) there and (start, end) in the source."""
    out, moved, at, size = [], [], 0, 0
    for m in STRETCH.finditer(text):
        a, b = m.span()
        if m.lastgroup == "at":
            new = "@"
        elif m.lastgroup == "dot":
            new = "."
        elif m.lastgroup == "alike":
            new = LOOK_ALIKE.get(m[0], m[0])
        else:
            pieces = [x for x in _PIECE.finditer(text, a, b)]
            for x in pieces:  # each word for itself, so that spans may end inside of the stretch
                out.append(text[at:x.start()].replace(",", " ") if at >= a else text[at:x.start()])
                size += len(out[-1])
                new = DIGITS.get(x[0].lower(), x[0])
                moved.append((size, size + len(new), x.start(), x.end()))
                out.append(new)
                size += len(new)
                at = x.end()
            continue
        out.append(text[at:a])
        size += a - at
        moved.append((size, size + len(new), a, b))
        out.append(new)
        size += len(new)
        at = b
    out.append(text[at:])
    return "".join(out), moved


def disguised(text: str, base: dict[str, list[tuple[int, int]]]) -> dict[str, list[tuple[int, int]]]:
    """Spans that only the rewritten text shows, as source offsets."""
    extra: dict[str, list[tuple[int, int]]] = {k: [] for k in KINDS}
    if not STRETCH.search(text):
        return extra
    new, moved = transduce(text)
    if not moved:
        return extra
    starts = [x[0] for x in moved]
    def source(at: int, end: bool) -> int:
        k = bisect_right(starts, at - end) - 1
        if k < 0:
            return at
        a, b, c, d = moved[k]
        if at - end < b:
            return d if end else c
        return d + at - b

    for kind, spans in detect(new).items():
        for a, b in spans:
            x, y = source(a, False), source(b, True)
            k = bisect_right(starts, b - 1) - 1
            changed = k >= 0 and moved[k][1] > a
            if changed and not any(p < y and x < q for p, q in base[kind]):
                extra[kind].append((x, y))
    return extra


def listed(spans: dict[str, list[tuple[int, int]]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k in KINDS for a, b in sorted(spans[k]))


def personal_data(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (id, counts of base spans by kind, hash of the base spans, all spans, number of added spans)."""
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for t in b.column(1):
                text = t.as_py() or ""
                base = detect(text)
                extra = disguised(text, base)
                both = {k: base[k] + extra[k] for k in KINDS}
                rows.append((*(len(base[k]) for k in KINDS), hashlib.sha256(listed(base).encode()).hexdigest(), listed(both), sum(map(len, extra.values()))))
            cols = list(zip(*rows)) if rows else [[]] * 7
            types = [pa.int64()] * 4 + [pa.string(), pa.string(), pa.int64()]
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(c, t) for c, t in zip(cols, types))], names=["id", *NAMES])

    return docs.select(id_col, text_col).mapInArrow(run, f"id {kind}, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_added long")


NAMES = ["n_email", "n_ip", "n_card", "n_phone", "base_sha256", "spans", "n_added"]


def mask(text: str, label: str = "[{}]") -> str:
    """``text`` with every span, base or disguised, replaced by its kind."""
    base = detect(text)
    extra = disguised(text, base)
    spans = sorted((a, b, k) for k in KINDS for a, b in base[k] + extra[k])
    out, at = [], 0
    for a, b, k in spans:
        if a >= at:
            out += [text[at:a], label.format(k)]
            at = b
        at = max(at, b)
    return "".join([*out, text[at:]])
