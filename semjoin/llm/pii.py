"""Personal data: expressions propose spans, validators confirm them, context adjusts the score.

Base kinds (always kept once confirmed): email, ip, card, phone, each leftmost and
non-overlapping within its kind; a match that fails its validator is dropped and not
tried again.  Further kinds need a score of at least ``LEAST``: iban (mod-97), short_card
(13 to 15 digits passing Luhn, near a card word) and national_id (near an id word).

Offsets are code points, the end exclusive.  Defined cases: null or empty text has no
spans; every search is linear in the text, whatever its runs of letters or digits.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .words import slices

BASE_KINDS = ("email", "ip", "card", "phone")
MORE_KINDS = ("iban", "short_card", "national_id")
LEAST = 0.5
NEAR = 40  # characters of context on either side of a span

# Patterns of the base kinds.
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
IP = re.compile(r"(?<![0-9])[0-9]+\.[0-9]+\.[0-9]+\.[0-9]+")
CARD = re.compile(r"[0-9](?:[ -]?[0-9])+")
PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")

IBAN = re.compile(r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?![A-Za-z0-9])")
NATIONAL_ID = re.compile(r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])")
CARD_WORDS = re.compile(r"card|credit|visa|amex|carte|karte|tarjeta", re.I)
ID_WORDS = re.compile(r"ssn|social security|national id|tax id", re.I)
BANK_WORDS = re.compile(r"iban|bank|account|konto|compte|cuenta", re.I)
_DIGIT = re.compile(r"[0-9]")


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if i & 1:
            d = 2 * d - 9 * (d > 4)
        total += d
    return total % 10 == 0


def mod97(iban: str) -> bool:
    turned = iban[4:] + iban[:4]
    return int("".join(str(int(c, 36)) for c in turned)) % 97 == 1


def digits_of(s: str) -> str:
    return "".join(c for c in s if "0" <= c <= "9")


def emails(text: str) -> Iterator[tuple[int, int]]:
    """Each @ is tried once: the longest local part to its left, then a domain."""
    free = 0
    at = text.find("@")
    while at >= 0:
        first = at
        while first > free and text[first - 1] in LOCAL:
            first -= 1
        m = DOMAIN.match(text, at + 1) if first < at else None
        if m:
            yield first, m.end()
            free = m.end()
        at = text.find("@", max(at + 1, free))


def _groups(m: str) -> bool:
    return all(len(p.lstrip("0")) < 4 and int(p.lstrip("0") or "0") <= 255 for p in m.split("."))


def _near(text: str, start: int, end: int, words: re.Pattern) -> bool:
    return words.search(text, max(0, start - NEAR), start) is not None or words.search(text, end, end + NEAR) is not None


def ibans(text: str) -> Iterator[tuple[int, int]]:
    """Of each match the longest part up to a space that mod-97 confirms: a word behind may have been taken for a group."""
    m = IBAN.search(text)
    while m:
        end = m.end()
        while end > m.start() and not (IBAN.fullmatch(text, m.start(), end) and mod97(text[m.start() : end].replace(" ", ""))):
            end = text.rfind(" ", m.start(), end)
        if end > m.start():
            yield m.start(), end
        m = IBAN.search(text, max(end, m.start() + 1))


def find(text: str) -> list[tuple[str, int, int, float]]:
    """(kind, start, end, score), base kinds first in their order, then by start."""
    out: list[tuple[str, int, int, float]] = []
    if "@" in text:
        out += [("email", a, b, 1.0) for a, b in emails(text)]
    if not _DIGIT.search(text):
        return out
    out += [("ip", m.start(), m.end(), 0.9) for m in IP.finditer(text) if _groups(m[0])]
    short = []
    for m in CARD.finditer(text):
        d = m[0] if m[0].isdigit() else digits_of(m[0])
        if 16 <= len(d) <= 19:
            if luhn(d):
                out.append(("card", m.start(), m.end(), min(1.0, 0.8 + 0.2 * _near(text, m.start(), m.end(), CARD_WORDS))))
        elif 13 <= len(d) <= 15 and luhn(d):
            short.append((m.start(), m.end(), 0.3 + 0.4 * _near(text, m.start(), m.end(), CARD_WORDS)))
    if "+" in text:
        out += [("phone", m.start(), m.end(), 0.9) for m in PHONE.finditer(text) if 8 <= len(digits_of(m[0])) <= 15]
    out += [("iban", a, b, min(1.0, 0.8 + 0.2 * _near(text, a, b, BANK_WORDS))) for a, b in ibans(text)]
    out += [("short_card", a, b, s) for a, b, s in short if s >= LEAST]
    for m in NATIONAL_ID.finditer(text):
        if (s := 0.2 + 0.5 * _near(text, m.start(), m.end(), ID_WORDS)) >= LEAST:
            out.append(("national_id", m.start(), m.end(), s))
    return out


def joined(spans: Iterable[tuple[str, int, int, float]]) -> str:
    return ",".join([f"{k}:{a}:{b}" for k, a, b, _ in spans])


def redacted(text: str, spans: list[tuple[str, int, int, float]]) -> str:
    """Every span, overlapping ones together, gives way to a mark of its first kind."""
    out, at = [], 0
    merged: list[list] = []
    for kind, a, b, _ in sorted(spans, key=lambda s: (s[1], -s[2])):
        if merged and a < merged[-1][2]:
            merged[-1][2] = max(merged[-1][2], b)
        else:
            merged.append([kind, a, b])
    for kind, a, b in merged:
        out += [text[at:a], f"[{kind.upper()}]"]
        at = b
    return "".join([*out, text[at:]])


SPANS = "n_email bigint, n_ip bigint, n_card bigint, n_phone bigint, base_sha256 string, spans string"


def _scan(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for rows, col in slices(batch):
            counts: dict[str, list[int]] = {k: [] for k in BASE_KINDS}
            digests, spans = [], []
            for text in col.to_pylist():
                got = find(text)
                base = [s for s in got if s[0] in counts]
                for k, n in counts.items():
                    n.append(sum(s[0] == k for s in base))
                digests.append(hashlib.sha256(joined(base).encode()).hexdigest())
                spans.append(joined(got))
            cols = [*(pa.array(counts[k], pa.int64()) for k in BASE_KINDS), pa.array(digests, pa.string()), pa.array(spans, pa.string())]
            yield pa.RecordBatch.from_arrays([rows.column(0), *cols], [rows.schema.names[0], *(f"n_{k}" for k in BASE_KINDS), "base_sha256", "spans"])


def detect(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Spans of every whole text; one scan, no shuffle."""
    rows = docs.select(F.col(id_col), F.col(text_col).alias("text"))
    kind = rows.schema[0].dataType.simpleString()
    return rows.mapInArrow(_scan, f"`{id_col}` {kind}, {SPANS}")


def redact(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """The same rows and columns, with every span in the text replaced by a mark; null stays null."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = batch.schema.get_field_index(text_col)
            for rows, _ in slices(batch, text_col, 1 << 20):
                new = [None if t is None else (redacted(t, s) if (s := find(t)) else t) for t in rows.column(at).to_pylist()]
                yield pa.RecordBatch.from_arrays([pa.array(new, pa.string()) if i == at else rows.column(i) for i in range(rows.num_columns)], rows.schema.names)

    return docs.mapInArrow(run, docs.schema)
