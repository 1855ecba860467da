"""Personal data: expressions propose spans, checksums confirm them, context words adjust the score."""

from __future__ import annotations

import hashlib
import math
import re
from bisect import bisect_left
from collections import Counter
from collections.abc import Iterator
from itertools import accumulate
from typing import NamedTuple

import pyarrow as pa
from pyspark.sql import DataFrame

#: The kinds, in the order in which spans with one start are listed; the first four are the base.
KINDS = ("email", "ip", "card", "phone", "iban", "ssn", "local_phone", "secret")
BASE = KINDS[:4]
#: Score of a proposal, and words that raise it when they stand nearby.
PRIOR = {"email": 0.9, "ip": 0.7, "card": 0.5, "phone": 0.7, "iban": 0.5, "ssn": 0.3, "local_phone": 0.3, "secret": 0.3}
CHECKED = 0.4
NEARBY = 0.4
CONTEXT = {
    "email": ("mail", "contact", "kontakt", "correo", "courriel"),
    "ip": ("ip", "host", "server", "address", "addr"),
    "card": ("card", "visa", "mastercard", "credit", "karte", "carte", "tarjeta"),
    "phone": ("phone", "tel", "call", "mobile", "fax", "telefon", "telefono", "portable"),
    "iban": ("iban", "account", "bank", "konto", "compte", "cuenta"),
    "ssn": ("ssn", "social", "security"),
    "local_phone": ("phone", "tel", "call", "mobile", "fax", "telefon", "telefono", "portable"),
    "secret": ("token", "secret", "key", "apikey", "password", "passwd", "bearer", "credential"),
}
#: A proposal counts from this score on; characters on either side in which context words are sought.
ACCEPT = 0.6
WINDOW = 40

_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
# a digit run is tried from its first digit only: what fails there fails at its later digits too
_IP = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++")
_DIGITS = re.compile(r"[0-9](?:[ -]?[0-9])++")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_IBAN = re.compile(r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?![A-Za-z0-9])")
_SSN = re.compile(r"(?<![0-9-])(?!000|666|9)[0-9]{3}-(?!00)[0-9]{2}-(?!0000)[0-9]{4}(?![0-9-])")
_LOCAL_PHONE = re.compile(r"(?<![0-9+.-])\(?[0-9]{3}\)?[ .-][0-9]{3}[ .-][0-9]{4}(?![0-9-])")
_SECRET = re.compile(r"(?<![A-Za-z0-9+/_-])[A-Za-z0-9+/_-]{20,}={0,2}(?![A-Za-z0-9+/_=-])|-----BEGIN [A-Z ]{0,40}PRIVATE KEY-----")
#: Beginnings of keys that say what they are.
_ISSUED = re.compile(r"AKIA[0-9A-Z]{16}$|gh[pousr]_[A-Za-z0-9]{36,}$|sk_live_[A-Za-z0-9]{16,}$|xox[abprs]-|AIza[A-Za-z0-9_-]{35}$|-----BEGIN ")
#: Bits a character that a drawn key has at least.
ENTROPY = 3.0
_WORD = re.compile(r"[^\W\d_]+")


class Span(NamedTuple):
    start: int
    rank: int
    end: int
    score: float

    @property
    def kind(self) -> str:
        return KINDS[self.rank]


def luhn(digits: str) -> bool:
    """Every second digit from the right doubled, nines cast out; the sum ends in 0."""
    odd, even = digits[-1::-2], digits[-2::-2]
    return (sum(map(int, odd)) + sum(int(c) * 2 - 9 * (c > "4") for c in even)) % 10 == 0


def mod97(code: str) -> bool:
    """First four characters moved to the end, letters as 10 to 35; the number leaves 1 when divided by 97."""
    rest = 0
    for c in code[4:] + code[:4]:
        v = int(c, 36)
        rest = (rest * (100 if v > 9 else 10) + v) % 97
    return rest == 1


def drawn(code: str) -> bool:
    """Whether a run of letters and digits looks drawn at random: both kinds, and few repeats."""
    if not (any(c.isdigit() for c in code) and any(c.isalpha() for c in code)):
        return False
    n = len(code)
    return -sum(k / n * math.log2(k / n) for k in Counter(code).values()) >= ENTROPY


def emails(text: str) -> Iterator[tuple[int, int]]:
    """Leftmost addresses in linear time: every @ is tried with the whole run before it that no earlier match has used."""
    used, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > used and text[start - 1] in _LOCAL:
            start -= 1
        m = _DOMAIN.match(text, at + 1) if start < at else None
        if m:
            used = m.end()
            yield start, used
        else:
            used = at + 1
        at = text.find("@", used)


def _octet(part: str) -> bool:
    part = part.lstrip("0")
    return len(part) <= 3 and int(part or 0) <= 255


def proposals(text: str) -> Iterator[tuple[str, int, int, bool]]:
    """Kind, start, end of every span that passes its own check, and whether a checksum confirmed it."""
    for start, end in emails(text):
        yield "email", start, end, False
    for m in _IP.finditer(text):
        if all(map(_octet, m.group().split("."))):
            yield "ip", m.start(), m.end(), False
    for m in _DIGITS.finditer(text):
        if m.end() - m.start() >= 12:
            digits = m.group().replace(" ", "").replace("-", "")
            if 12 <= len(digits) <= 19 and luhn(digits):
                yield "card", m.start(), m.end(), True
    for m in _PHONE.finditer(text):
        if 9 <= sum(c.isdigit() for c in m.group()) <= 15:
            yield "phone", m.start(), m.end(), False
    for m in _IBAN.finditer(text):
        code = m.group().replace(" ", "")
        if 15 <= len(code) <= 34 and mod97(code):
            yield "iban", m.start(), m.end(), True
    for m in _SSN.finditer(text):
        yield "ssn", m.start(), m.end(), False
    for m in _LOCAL_PHONE.finditer(text):
        yield "local_phone", m.start(), m.end(), False
    for m in _SECRET.finditer(text):
        issued = bool(_ISSUED.match(m.group()))
        if issued or drawn(m.group()):
            yield "secret", m.start(), m.end(), issued


def find_spans(text: str | None, accept: float = ACCEPT) -> list[Span]:
    """All spans by start, then kind. Base kinds always stay; the others need ``accept`` and must not overlap a base span."""
    if not text:
        return []
    base, more = [], []
    for kind, start, end, checked in proposals(text):
        around = text[max(0, start - WINDOW) : start] + " " + text[end : end + WINDOW]
        near = any(w.startswith(CONTEXT[kind]) for w in _WORD.findall(around.lower()))
        span = Span(start, KINDS.index(kind), end, round(min(1.0, PRIOR[kind] + CHECKED * checked + NEARBY * near), 2))
        (base if kind in BASE else more).append(span)
    base.sort()
    starts, ends = [b.start for b in base], [0, *accumulate((b.end for b in base), max)]
    more = [s for s in more if s.score >= accept and ends[bisect_left(starts, s.end)] <= s.start]
    return sorted(base + more)


def listed(spans: list[Span]) -> str:
    return ",".join(f"{s.kind}:{s.start}:{s.end}" for s in spans)


def redact(text: str | None, spans: list[Span]) -> str | None:
    """The text with every span replaced by its kind in angle brackets; overlapping spans become one, named by the first."""
    if not text or not spans:
        return text
    out, at = [], 0
    for s in spans:
        if s.start >= at:
            out += [text[at : s.start], f"<{s.kind}>"]
        at = max(at, s.end)
    return "".join([*out, text[at:]])


def detect(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", accept: float = ACCEPT, with_redacted: bool = False) -> DataFrame:
    """Personal data in every whole text.

    ``doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, scores`` and, on request, ``redacted``. Offsets are code
    points, ends exclusive. A null text is empty (zero counts, empty lists); its redacted text is null. Null or repeated
    identifiers pass through; other columns are not read; an empty table gives an empty result. One pass, no shuffle.
    """
    names = ["doc_id", *[f"n_{k}" for k in BASE], "base_sha256", "spans", "scores", *(["redacted"] if with_redacted else [])]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = b.column(1).to_pylist()
            found = [find_spans(t, accept) for t in texts]
            counts = [pa.array([sum(s.rank == i for s in f) for f in found], pa.int64()) for i in range(len(BASE))]
            base = [listed([s for s in f if s.rank < len(BASE)]) for f in found]
            columns = [b.column(0), *counts, pa.array([hashlib.sha256(x.encode()).hexdigest() for x in base], pa.string()), pa.array(map(listed, found), pa.string())]
            columns.append(pa.array([",".join(f"{s.score:.2f}" for s in f) for f in found], pa.string()))
            if with_redacted:
                columns.append(pa.array([redact(t, f) for t, f in zip(texts, found, strict=True)], pa.string()))
            yield pa.RecordBatch.from_arrays(columns, names=names)

    types = {"doc_id": "bigint"} | {f"n_{k}": "bigint" for k in BASE}
    rows = docs.selectExpr(f"cast(`{id_col}` as bigint) as doc_id", f"`{text_col}` as text")
    return rows.mapInArrow(run, ", ".join(f"{n} {types.get(n, 'string')}" for n in names))
