"""Personal data, found also behind disguises, with offsets of the source.

A transducer rewrites homoglyphs, foreign digits, invisible characters, spelled digits and at/dot disguises, and keeps for
every character it writes the span of the source that it stands for. The detectors run on the source (base spans) and on
what the transducer wrote; spans found there are mapped back and added unless they lie within a base span of their kind.

Nulls are empty texts without spans. The detectors and the transducer are linear in the text, also on long runs. Repeated
rows are treated alike, extra columns are ignored, an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import re
import unicodedata

from pyspark.sql import DataFrame
from pyspark.sql import types as T

from . import common

KINDS = ("email", "ip", "card", "phone")
#: Look-alikes of Latin letters in Cyrillic and Greek script.
LOOKS_LIKE = dict(zip("аеорсухіјѕԁһԛԝАВЕКМНОРСТХІЈЅαοερνικτυΑΒΕΖΗΙΚΜΝΟΡΤΥΧ", "aeopcyxijsdhqwABEKMHOPCTXIJSaoepvikryABEZHIKMNOPTYX", strict=False))
#: The spelled digits.
DIGIT_WORDS = {"zero": "0", "oh": "0", "one": "1", "two": "2", "three": "3", "four": "4", "five": "5", "six": "6", "seven": "7", "eight": "8", "nine": "9"}
INVISIBLE = "­​‌‍⁠﻿"

EMAIL = re.compile(r"[A-Za-z0-9._%+-]++@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
EMAIL_START = re.compile(r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]++@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
IP = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++")
CARD = re.compile(r"[0-9](?:[ -]?[0-9])++")
PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")

WORD = "|".join(DIGIT_WORDS)
#: Characters that may stand for others: all but those of Latin script, and of these the no-break space and the soft hyphen.
ODD = r"(?-i:[\u0250-\U0010ffff\xa0\xad])"
#: What the transducer rewrites, leftmost first: bracketed and spoken at and dot, runs of spelled digits, odd characters.
REWRITE = re.compile(
    r"(?P<at>\s{0,3}[\[({<]\s?at\s?[\])}>]\s{0,3}|(?<=\w)\s{1,3}at\s{1,3}(?=[A-Za-z0-9-]{1,63}(?:\s{1,3}dot\s|\s{0,3}[\[({<]\s?dot\s?[\])}>]))|\s{0,3}[\[({<]@[\])}>]\s{0,3})"
    r"|(?P<dot>\s{0,3}[\[({<]\s?(?:dot|\.)\s?[\])}>]\s{0,3}|(?<=\w)\s{1,3}dot\s{1,3}(?=\w))"
    rf"|(?P<digits>(?<!\w)(?:plus[\s-]{{1,2}})?(?:{WORD})(?:[\s,.-]{{1,2}}(?:{WORD}|[0-9]+)){{3,}}(?!\w))"
    rf"|(?P<odd>{ODD})",
    re.I,
)
#: A text without any of these is left as it is; REWRITE finds nothing without one of them.
TRIGGER = re.compile(rf"{ODD}|[\[({{<]\s?(?:at|dot|@|\.)\s?[\])}}>]|\sdot\s|\b(?:{WORD})[\s,.-]{{1,2}}(?:{WORD}|[0-9])", re.I)
SPELLED = re.compile(rf"(?P<plus>plus)|(?P<word>{WORD})|(?P<number>[0-9]+)", re.I)


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c)
        if i % 2:
            d = d * 2 - 9 * (d > 4)
        total += d
    return total % 10 == 0


def emails(text: str) -> list[tuple[int, int]]:
    """A match can begin where a run of its characters begins, or right behind the match before it."""
    found, at = [], 0
    while "@" in text:
        m = (EMAIL.match(text, at) if at else None) or EMAIL_START.search(text, at)
        if not m:
            break
        found.append(m.span())
        at = m.end()
    return found


def detect(text: str) -> dict[str, list[tuple[int, int]]]:
    """Spans of each kind, leftmost and not overlapping, checks passed."""
    found = {"email": emails(text), "ip": [], "card": [], "phone": []}
    for m in IP.finditer(text):
        if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in m[0].split(".")):
            found["ip"].append(m.span())
    for m in CARD.finditer(text):
        if m.end() - m.start() >= 16:
            digits = m[0].replace(" ", "").replace("-", "")
            if 16 <= len(digits) <= 19 and luhn(digits):
                found["card"].append(m.span())
    if "+" in text:
        for m in PHONE.finditer(text):
            if 8 <= sum("0" <= c <= "9" for c in m[0]) <= 15:
                found["phone"].append(m.span())
    return found


def plain(c: str) -> str:
    """What an odd character stands for: nothing, one ASCII character, or itself."""
    if c in INVISIBLE:
        return ""
    if c in LOOKS_LIKE:
        return LOOKS_LIKE[c]
    if (d := unicodedata.decimal(c, None)) is not None:
        return str(d)
    if unicodedata.category(c) == "Pd":
        return "-"
    if unicodedata.category(c) == "Zs":
        return " "
    folded = unicodedata.normalize("NFKC", c)
    return folded if len(folded) == 1 and folded.isascii() else c


def transduce(text: str) -> tuple[str, list[tuple[int, int, int]]]:
    """The rewritten text, and its blocks as (where it begins there, source start, source end).

    A block whose source is as long as its output maps character by character, any other as a whole.
    """
    out: list[str] = []
    blocks: list[tuple[int, int, int]] = []
    size = at = 0

    def emit(piece: str, start: int, end: int) -> None:
        nonlocal size
        if piece:
            out.append(piece)
            blocks.append((size, start, end))
            size += len(piece)

    for m in REWRITE.finditer(text):
        emit(text[at : m.start()], at, m.start())
        at = m.end()
        if m["at"]:
            emit("@", *m.span())
        elif m["dot"]:
            emit(".", *m.span())
        elif m["odd"]:
            emit(plain(m[0]), *m.span())
        else:
            for d in SPELLED.finditer(text, *m.span()):
                emit("+" if d["plus"] else d[0] if d["number"] else DIGIT_WORDS[d[0].lower()], *d.span())
    emit(text[at:], at, len(text))
    return "".join(out), blocks


def to_source(span: tuple[int, int], blocks: list[tuple[int, int, int]], starts: list[int], size: int) -> tuple[int, int]:
    import bisect

    def block(at: int) -> tuple[int, int, int, int]:
        k = bisect.bisect_right(starts, at) - 1
        return (*blocks[k], (starts[k + 1] if k + 1 < len(starts) else size) - starts[k])

    began, s, e, n = block(span[0])
    left = s + span[0] - began if e - s == n else s
    began, s, e, n = block(span[1] - 1)
    right = s + span[1] - began if e - s == n else e
    return left, right


def find(text: str | None) -> tuple[dict[str, list[tuple[int, int]]], dict[str, list[tuple[int, int]]]]:
    """(base spans, all spans) of each kind, in code points of the source, end exclusive."""
    text = text or ""
    base = detect(text)
    spans = {k: list(v) for k, v in base.items()}
    if TRIGGER.search(text):
        written, blocks = transduce(text)
        starts = [b[0] for b in blocks]
        for kind, more in detect(written).items():
            for span in more:
                left, right = to_source(span, blocks, starts, len(written))
                if not any(a <= left and right <= b for a, b in base[kind]):
                    spans[kind].append((left, right))
            spans[kind].sort()
    return base, spans


def listed(spans: dict[str, list[tuple[int, int]]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k in KINDS for a, b in spans[k])


def redact(text: str | None) -> str | None:
    """The text with every span replaced by the name of its kind; overlapping spans become one."""
    if text is None:
        return None
    _, spans = find(text)
    merged: list[list] = []
    for a, b, kind in sorted((a, b, k) for k, v in spans.items() for a, b in v):
        if merged and a < merged[-1][1]:
            merged[-1][1] = max(merged[-1][1], b)
        else:
            merged.append([a, b, kind])
    out, at = [], 0
    for a, b, kind in merged:
        out += [text[at:a], f"<{kind.upper()}>"]
        at = b
    return "".join([*out, text[at:]]) if out else text


def personal_data(docs: DataFrame) -> DataFrame:
    """doc_id, counts and checksum of the base spans, all spans as a list, and how many were found behind disguises."""

    def make():
        def work(texts: list[str | None]) -> list:
            columns: list[list] = [[] for _ in range(7)]
            for text in texts:
                base, spans = find(text)
                row = [*(len(base[k]) for k in KINDS), hashlib.sha256(listed(base).encode()).hexdigest(), listed(spans), sum(map(len, spans.values())) - sum(map(len, base.values()))]
                for column, x in zip(columns, row, strict=True):
                    column.append(x)
            return columns

        return work

    fields = [*(T.StructField(f"n_{k}", T.LongType()) for k in KINDS), T.StructField("base_sha256", T.StringType()), T.StructField("spans", T.StringType()), T.StructField("n_disguised", T.LongType())]
    return common.map_texts(docs, ["doc_id"], ["text"], fields, make)


def redacted(docs: DataFrame, column: str = "__redacted") -> DataFrame:
    """All columns of docs, with the redacted text beside them as ``column``."""

    def make():
        return lambda texts: [[redact(x) for x in texts]]

    return common.map_texts(docs, docs.columns, ["text"], [T.StructField(column, T.StringType())], make)
