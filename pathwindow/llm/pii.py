"""Personal data: patterns propose spans, checksums confirm them, context words adjust a score.

Base kinds (email, ip, card, phone) follow fixed patterns and validators and always stay. The method proposes further
kinds (iban with mod-97, national id with context words, secrets by the name they are assigned to or a known form, and by
the entropy of their characters) and scores every span from 0 to 1 by its validator and by the words around it; proposed spans under ``min_score`` are dropped, base spans never.

Defined results: a null or empty text has no spans; positions are code points with an exclusive end; repeated rows each
get their row; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections import Counter

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_batches, texts

KINDS = ("email", "ip", "card", "phone", "iban", "national_id", "secret")
BASE = KINDS[:4]
CONTEXT_CHARS = 40

# Runs are possessive and start where a run of digits starts, so that no text costs more than linear time.
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++")
_IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])++")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_IBAN = re.compile(r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?:[ ]?[A-Z0-9]{4}){2,7}(?:[ ]?[A-Z0-9]{1,3})?(?![A-Za-z0-9])")
_NATIONAL = re.compile(r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])")
_ASSIGNED = re.compile(r"(?i)(?<![a-z0-9])(?:token|secret|passw(?:or)?d|pwd|credential|(?:api|access|private|secret|auth)[_ -]?(?:key|token))s?[\"']?\s{0,3}[:=]\s{0,3}[\"']?([A-Za-z0-9+/_.~-]{12,}+=*)")
# Fixed forms: keys that public services give out.
_ISSUED = re.compile(r"(?<![A-Za-z0-9])(?:(?:AKIA|ASIA)[0-9A-Z]{16}|gh[pousr]_[A-Za-z0-9]{30,}|xox[abprs]-[A-Za-z0-9-]{10,}|sk-[A-Za-z0-9_-]{20,}|eyJ[A-Za-z0-9_-]{10,}\.[A-Za-z0-9_-]{10,}\.[A-Za-z0-9_-]{10,})(?![A-Za-z0-9])")
_DIGIT = re.compile("[0-9]")
_IBAN_HINT = re.compile(r"[A-Z]{2}[0-9]{2}")
# Words near a span that speak for its kind.
_CONTEXT = {
    "email": ("mail", "contact", "write", "kontakt", "correo"),
    "ip": ("ip", "host", "server", "address", "adresse"),
    "card": ("card", "visa", "payment", "karte", "carte", "tarjeta"),
    "phone": ("phone", "tel", "call", "mobile", "telefon"),
    "iban": ("iban", "bank", "account", "konto", "compte", "cuenta"),
    "national_id": ("ssn", "social", "security", "id", "passport"),
    "secret": ("key", "token", "secret", "password", "auth", "login"),
}
_PRIOR = {"email": 0.9, "ip": 0.6, "card": 0.8, "phone": 0.6, "iban": 0.85, "national_id": 0.4, "secret": 0.6}


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if i % 2:
            d = d * 2 - 9 * (d > 4)
        total += d
    return total % 10 == 0


def mod97(iban: str) -> bool:
    turned = iban[4:] + iban[:4]
    return int("".join(c if c.isdigit() else str(ord(c) - 55) for c in turned)) % 97 == 1


def entropy(text: str) -> float:
    """Bits a character."""
    return -sum(n / len(text) * math.log2(n / len(text)) for n in Counter(text).values())


def _secrets(text: str) -> list[tuple[int, int]]:
    found = [m.span() for m in _ISSUED.finditer(text)]
    if "=" in text or ":" in text:
        # names and words have few bits a character or no digits; keys have both
        found += [m.span(1) for m in _ASSIGNED.finditer(text) if entropy(m[1]) >= 3 and _DIGIT.search(m[1])]
    out: list[tuple[int, int]] = []
    for a, b in sorted(set(found)):
        if not out or a >= out[-1][1]:
            out.append((a, b))
    return out


def _emails(text: str) -> list[tuple[int, int]]:
    """Leftmost matches: a local part is the whole run before an at sign, back to the last match."""
    found, free, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > free and text[start - 1] in _LOCAL:
            start -= 1
        if start < at and (m := _DOMAIN.match(text, at + 1)):
            found.append((start, m.end()))
            free = m.end()
        at = text.find("@", max(at + 1, free))
    return found


def _digits(s: str) -> str:
    return "".join(c for c in s if "0" <= c <= "9")


def _small(part: str) -> bool:
    part = part.lstrip("0")
    return len(part) <= 3 and int(part or "0") <= 255


def base_spans(text: str) -> dict[str, list[tuple[int, int]]]:
    out: dict[str, list[tuple[int, int]]] = {k: [] for k in BASE}
    if "@" in text:
        out["email"] = _emails(text)
    if _DIGIT.search(text):
        if "." in text:
            out["ip"] = [m.span() for m in _IP.finditer(text) if all(map(_small, m[0].split(".")))]
        for m in _CARD.finditer(text):
            if m.end() - m.start() >= 12 and 12 <= len(d := _digits(m[0])) <= 19 and luhn(d):
                out["card"].append(m.span())
        if "+" in text:
            out["phone"] = [m.span() for m in _PHONE.finditer(text) if 9 <= len(_digits(m[0])) <= 15]
    return out


def extra_spans(text: str) -> dict[str, list[tuple[int, int]]]:
    out: dict[str, list[tuple[int, int]]] = {"iban": [], "national_id": [], "secret": _secrets(text)}
    if _DIGIT.search(text):
        if _IBAN_HINT.search(text):
            out["iban"] = [m.span() for m in _IBAN.finditer(text) if 15 <= len(x := m[0].replace(" ", "")) <= 34 and mod97(x)]
        if "-" in text:
            out["national_id"] = [m.span() for m in _NATIONAL.finditer(text) if m[0][:3] not in ("000", "666") and m[0][0] != "9"]
    return out


def score(text: str, kind: str, start: int, end: int) -> float:
    near = set(re.findall("[a-z]+", text[max(0, start - CONTEXT_CHARS) : start].lower() + " " + text[end : end + CONTEXT_CHARS].lower()))
    value = _PRIOR[kind] + (0.3 if near.intersection(_CONTEXT[kind]) else 0.0)
    if kind == "card" and len(set(_digits(text[start:end]))) == 1:
        value -= 0.5
    return round(min(1.0, max(0.0, value)), 3)


def spans_of(text: str, min_score: float = 0.5) -> list[tuple[int, int, str, float]]:
    """All spans (start, end, kind, score) by start, then kind as listed."""
    found = []
    for kind, spans in base_spans(text).items():
        found += [(a, b, kind, score(text, kind, a, b)) for a, b in spans]
    for kind, spans in extra_spans(text).items():
        found += [(a, b, kind, s) for a, b in spans if (s := score(text, kind, a, b)) >= min_score]
    return sorted(found, key=lambda x: (x[0], KINDS.index(x[2])))


SCHEMA = "doc_id long, spans array<struct<start: long, end: long, kind: string, score: double>>"
_SPAN = pa.struct([("start", pa.int64()), ("end", pa.int64()), ("kind", pa.string()), ("score", pa.float64())])


def find_personal_data(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_score: float = 0.5) -> DataFrame:
    """One row a document with its spans. A map over rows: no shuffle, memory of one batch."""

    def each(batch):
        spans = [[{"start": a, "end": b, "kind": k, "score": s} for a, b, k, s in spans_of(t, min_score)] for t in texts(batch)]
        yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), pa.array(spans, pa.list_(_SPAN))], names=["doc_id", "spans"])

    return map_batches(docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")), each, SCHEMA)


def redact(text: str, min_score: float = 0.5) -> str:
    """The text with each span replaced by its kind; of overlapping spans the first stays."""
    out, at = [], 0
    for a, b, kind, _ in spans_of(text, min_score):
        if a >= at:
            out += [text[at:a], f"[{kind}]"]
            at = b
    return "".join([*out, text[at:]])


def digest(found: DataFrame) -> DataFrame:
    """The contract's columns from the operator's own output."""
    order = F.array(*(F.lit(k) for k in KINDS))
    listed = F.array_sort(F.transform("spans", lambda s: F.struct(s["start"], F.array_position(order, s["kind"]).alias("k"), s["end"], s["kind"])))
    told = lambda spans: F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")
    count = lambda kind: F.size(F.filter("spans", lambda s: s["kind"] == kind))
    base = F.filter(listed, lambda s: s["k"] <= len(BASE))
    return found.select(
        "doc_id",
        *(count(k).cast("long").alias(f"n_{k}") for k in BASE),
        F.sha2(told(base).cast("binary"), 256).alias("base_sha256"),
        told(listed).alias("spans"),
        F.size("spans").cast("long").alias("n_spans"),
        count("secret").cast("long").alias("n_secret"),
    )
