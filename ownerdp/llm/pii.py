"""Personal data: regular expressions propose, checksums confirm, words nearby adjust the score."""

from __future__ import annotations

import hashlib
import re
from bisect import bisect_left, insort
from collections.abc import Iterator
from itertools import accumulate

import pyarrow as pa
from pyspark.sql import DataFrame

from ownerdp.llm.common import map_batches, texts_of

#: The base kinds in their order and their patterns.
KINDS = ("email", "ip", "card", "phone")
# runs of digits are never given back: a match that fails behind a run fails from any place inside it, so each is read once
IP = re.compile(r"(?<![0-9])[0-9]++(\.[0-9]++)(\.[0-9]++)(\.[0-9]++)")
CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
EMAIL_REST = re.compile(r"@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
_LOCAL_CHARS = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")

#: The method's own kinds, in their order after the base kinds.
MORE_KINDS = ("iban", "national_id", "local_phone")
IBAN = re.compile(r"\b[A-Z]{2}[0-9]{2}(?:\x20?[A-Z0-9]){11,30}\b")
NATIONAL_ID = re.compile(r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])")
LOCAL_PHONE = re.compile(r"(?<![+0-9.-])\(?[0-9]{3}\)?[\x20.-][0-9]{3}[\x20.-][0-9]{4}(?![0-9.-])")

CONTEXT_CHARS = 48
ACCEPT = 0.6
#: kind: (score before context, words nearby that raise it, words nearby that lower it)
CONTEXT = {
    "email": (0.9, r"mail|contact|write", r"example only"),
    "ip": (0.65, r"ip|server|host|address", r"version|section|release"),
    "card": (0.8, r"card|visa|credit|pay|iban", r"isbn|order no|tracking"),
    "phone": (0.75, r"phone|call|tel|mobile|fax", r"score|result"),
    "iban": (0.85, r"iban|account|bank|transfer", r"serial|part no"),
    "national_id": (0.45, r"ssn|social|security|identity|tax", r"part no|serial|order"),
    "local_phone": (0.4, r"phone|call|tel|mobile|fax|dial", r"score|part no|serial"),
}
_CONTEXT = {k: (s, re.compile(up, re.I), re.compile(down, re.I)) for k, (s, up, down) in CONTEXT.items()}


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if i % 2:
            d = d * 2 - 9 if d > 4 else d * 2
        total += d
    return total % 10 == 0


def mod97(iban: str) -> bool:
    text = iban.replace(" ", "")
    return 15 <= len(text) <= 34 and int("".join(str(int(c, 36)) for c in text[4:] + text[:4])) % 97 == 1


def emails(text: str) -> Iterator[tuple[int, int]]:
    """The leftmost matches of the e-mail pattern, found from each ``@`` outwards instead of from each character."""
    done, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > done and text[start - 1] in _LOCAL_CHARS:
            start -= 1
        if start < at and (m := EMAIL_REST.match(text, at)):
            yield start, m.end()
            done = m.end()
            at = text.find("@", done)
        else:
            at = text.find("@", at + 1)


def base_spans(text: str) -> list[tuple[int, int, str]]:
    out = [(s, e, "email") for s, e in emails(text)]
    for m in IP.finditer(text):
        if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in m[0].split(".")):  # int() refuses very long runs of digits
            out.append((m.start(), m.end(), "ip"))
    for m in CARD.finditer(text):
        if m.end() - m.start() >= 14:
            digits = m[0].replace(" ", "").replace("-", "")
            if 14 <= len(digits) <= 19 and luhn(digits):
                out.append((m.start(), m.end(), "card"))
    if "+" in text:
        for m in PHONE.finditer(text):
            if 10 <= sum(c.isdigit() for c in m[0]) <= 15:
                out.append((m.start(), m.end(), "phone"))
    return sorted(out, key=lambda x: (x[0], KINDS.index(x[2])))


def proposals(text: str) -> Iterator[tuple[int, int, str]]:
    for m in IBAN.finditer(text):
        # the pattern is greedy: take the longest prefix of it that ends at a block and passes the checksum
        ends = [m.end(), *(m.start() + i for i in range(len(m[0]) - 1, 14, -1) if m[0][i] == " ")]
        end = next((e for e in ends if mod97(text[m.start() : e])), None)
        if end:
            yield m.start(), end, "iban"
    for kind, pattern in (("national_id", NATIONAL_ID), ("local_phone", LOCAL_PHONE)):
        yield from ((m.start(), m.end(), kind) for m in pattern.finditer(text))


def scored(text: str, start: int, end: int, kind: str) -> float:
    score, up, down = _CONTEXT[kind]
    near = text[max(0, start - CONTEXT_CHARS) : start] + "\n" + text[end : end + CONTEXT_CHARS // 2]
    score += 0.25 * bool(up.search(near)) - 0.3 * bool(down.search(near))
    return min(1.0, max(0.0, score))


def find(text: str) -> tuple[list[tuple[int, int, str]], list[tuple[int, int, str, float]]]:
    """The base spans, and all spans with their scores: those of the base whatever their score, others from ACCEPT on if they overlap none."""
    base = base_spans(text)
    spans = [(s, e, k, scored(text, s, e, k)) for s, e, k in base]
    starts, reached, added = [s for s, _, _ in base], list(accumulate((e for _, e, _ in base), max)), []
    for s, e, k in proposals(text):
        ahead, at = bisect_left(starts, e), bisect_left(added, (e,))  # of the base spans, and of those added, that begin before this one ends
        free = not (ahead and reached[ahead - 1] > s) and not (at and added[at - 1][1] > s)
        if free and (x := scored(text, s, e, k)) >= ACCEPT:
            spans.append((s, e, k, x))
            insort(added, (s, e))
    order = KINDS + MORE_KINDS
    return base, sorted(spans, key=lambda x: (x[0], order.index(x[2])))


def redact(text: str, spans: list[tuple[int, int, str, float]]) -> str:
    """The text with each span replaced by its kind; of overlapping spans the first one is named."""
    out, at = [], 0
    for s, e, k, _ in spans:
        if s >= at:
            out += [text[at:s], f"<{k.upper()}>"]
        at = max(at, e)
    return "".join([*out, text[at:]])


def find_pii(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", with_redacted: bool = False) -> DataFrame:
    """One row for each row of ``docs``: doc_id, base and spans as array<struct<start, end, kind, score>>, and on request the redacted text.

    Offsets are in code points, the end exclusive. Null and empty texts have no spans. Nothing is shuffled.
    """
    kind = docs.schema[doc_id].dataType.simpleString()
    span = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32()), ("kind", pa.string()), ("score", pa.float64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        name = ("start", "end", "kind", "score")
        for batch in batches:
            texts = texts_of(batch, "text")
            found = [find(t) for t in texts]
            columns = [
                batch.column(0),
                pa.array([[dict(zip(name, (*x, 1.0), strict=True)) for x in b] for b, _ in found], span),
                pa.array([[dict(zip(name, x, strict=True)) for x in a] for _, a in found], span),
            ]
            names = ["doc_id", "base", "spans"]
            if with_redacted:
                columns.append(pa.array([redact(t, a) for t, (_, a) in zip(texts, found, strict=True)], pa.string()))
                names.append("redacted")
            yield pa.RecordBatch.from_arrays(columns, names=names)

    spans = "array<struct<start:int,end:int,kind:string,score:double>>"
    return map_batches(docs.selectExpr(f"`{doc_id}` AS doc_id", f"`{text}` AS text"), run, f"doc_id {kind}, base {spans}, spans {spans}" + ", redacted string" * with_redacted)


def joined(spans) -> str:
    return ",".join(f"{k}:{s}:{e}" for s, e, k, *_ in spans)


def digest(spans) -> str:
    return hashlib.sha256(joined(spans).encode()).hexdigest()


