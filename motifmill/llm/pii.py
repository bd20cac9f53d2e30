"""Personal data: patterns propose spans, checksums confirm them, context moves the score.

Base kinds (email, ip, card, phone) are whole-text, leftmost, non-overlapping matches that
pass their check; a match that fails is dropped and not tried again from another place.
Further kinds come on top and never replace base spans: `iban` (mod-97), `secret`
(key, token or password assignments), `card_like` (13-15 digits that pass Luhn) and `phone_like` (local numbers).  A span's
score starts at its kind's prior, rises with a passed check and with the nearest context
word of its kind, before or (half as much) after it, the more the nearer; a further kind
is reported from the threshold on, and that alone decides.

Special cases: a null or empty text has no spans and the SHA-256 of nothing; rows are
judged each by itself, so repeats and ties repeat; no rows give none; extra columns are
ignored; a null doc_id stays null.  Offsets count code points, ends are exclusive.
Scanning is linear in the text, also for one very long run of digits or letters.
"""

from __future__ import annotations

import hashlib
import re

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import base

BASE_KINDS = ("email", "ip", "card", "phone")
MORE_KINDS = ("iban", "secret", "card_like", "phone_like")
PRIOR = {"iban": 0.25, "secret": 0.2, "card_like": 0.15, "phone_like": 0.1}
CHECKED, NEAR_WORD, THRESHOLD, REACH = 0.4, 0.3, 0.6, 48
# Context words of each further kind.
CONTEXT = {
    "iban": ("iban", "account", "konto", "compte", "cuenta", "bank"),
    "secret": ("password", "passwd", "token", "secret", "key", "apikey", "passwort", "clave"),
    "card_like": ("card", "visa", "amex", "credit", "karte", "carte", "tarjeta"),
    "phone_like": ("phone", "tel", "call", "mobile", "fax", "telefon", "téléphone", "teléfono"),
}

_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]+){3}")
_CARD = re.compile(r"[0-9](?:[ -]?[0-9])++")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_IBAN = re.compile(r"\b[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?\b")
_SECRET = re.compile(r"(?i)\b(?:password|passwd|pwd|token|secret|api[_-]?key)\b\s{0,3}[:=]\s{0,3}[\"']?([^\s\"']{6,256})")
_LOCAL_PHONE = re.compile(r"(?<![0-9+])(?:\([0-9]{2,5}\) ?|0)[0-9][0-9 ./-]{4,16}[0-9](?![0-9])")
_DIGIT_RUN = re.compile(r"(?<![0-9])[0-9]{13,15}(?![0-9])")
_NOT_DIGIT = re.compile(r"[^0-9]+")
_DOUBLED = [0, 2, 4, 6, 8, 1, 3, 5, 7, 9]


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        total += _DOUBLED[d] if i & 1 else d
    return total % 10 == 0


def mod97(iban: str) -> bool:
    s = iban.replace(" ", "")
    return 15 <= len(s) <= 34 and int("".join(str(int(c, 36)) for c in s[4:] + s[:4])) % 97 == 1


def emails(text: str) -> list[tuple[int, int]]:
    """Walks over the @ signs, so that a long run of name characters costs nothing."""
    out, floor, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > floor and text[start - 1] in _LOCAL:
            start -= 1
        m = _DOMAIN.match(text, at + 1) if start < at else None
        if m:
            out.append((start, m.end()))
            floor = m.end()
            at = text.find("@", floor)
        else:
            floor = at + 1
            at = text.find("@", at + 1)
    return out


def _octets(found: str) -> bool:
    return all(len(p := part.lstrip("0")) <= 3 and int(p or 0) <= 255 for part in found.split("."))


def _card(found: str) -> bool:
    digits = found.replace(" ", "").replace("-", "")
    return 16 <= len(digits) <= 19 and luhn(digits)


def base_spans(text: str) -> dict[str, list[tuple[int, int]]]:
    return {
        "email": emails(text),
        "ip": [m.span() for m in _IP.finditer(text) if _octets(m[0])],
        "card": [m.span() for m in _CARD.finditer(text) if _card(m[0])],
        "phone": [m.span() for m in _PHONE.finditer(text) if 8 <= len(_NOT_DIGIT.sub("", m[0])) <= 15],
    }


def nearness(text: str, a: int, b: int, words: tuple[str, ...]) -> float:
    """From 0 to 1: how near a context word is to the span; one after it counts half."""
    before, after = text[max(0, a - REACH) : a].lower(), text[b : b + REACH].lower()
    ends = [len(before) - (at + len(w)) for w in words if (at := before.rfind(w)) >= 0]
    begins = [at for w in words if (at := after.find(w)) >= 0]
    return max([0.0, *(1 - d / REACH for d in ends), *(0.5 * (1 - d / REACH) for d in begins)])


def more_spans(text: str, taken: list[tuple[int, int]]) -> list[tuple[str, int, int, float]]:
    """Further spans with their scores; those that touch a base span are left out."""
    proposed = [("iban", *m.span(), mod97(m[0])) for m in _IBAN.finditer(text)]
    proposed += [("secret", *m.span(1), any(c.isdigit() for c in m[1])) for m in _SECRET.finditer(text)]
    proposed += [("card_like", *m.span(), luhn(m[0])) for m in _DIGIT_RUN.finditer(text)]
    proposed += [("phone_like", *m.span(), 7 <= len(_NOT_DIGIT.sub("", m[0])) <= 12) for m in _LOCAL_PHONE.finditer(text)]
    out = []
    for kind, a, b, passed in proposed:
        if not passed or any(a < y and x < b for x, y in taken):
            continue
        score = min(1.0, PRIOR[kind] + CHECKED + NEAR_WORD * nearness(text, a, b, CONTEXT[kind]))
        if score >= THRESHOLD:
            out.append((kind, a, b, score))
    return out


_SCHEMA = {
    "doc_id": pa.int64(), "n_email": pa.int64(), "n_ip": pa.int64(), "n_card": pa.int64(), "n_phone": pa.int64(),
    "base_sha256": pa.string(), "spans": pa.string(), "n_more": pa.int64(), "best_score": pa.float64(),
}


def _scan(data, offsets, rows):
    out = {k: [] for k in _SCHEMA if k != "doc_id"}
    for text in base.as_texts(data, offsets):
        found = base_spans(text)
        listed = [f"{k}:{a}:{b}" for k in BASE_KINDS for a, b in found[k]]
        taken = [s for k in BASE_KINDS for s in found[k]]
        more = sorted(more_spans(text, taken), key=lambda s: (MORE_KINDS.index(s[0]), s[1]))
        for k in BASE_KINDS:
            out[f"n_{k}"].append(len(found[k]))
        out["base_sha256"].append(hashlib.sha256(",".join(listed).encode()).hexdigest())
        out["spans"].append(",".join(listed + [f"{k}:{a}:{b}" for k, a, b, _ in more]))
        out["n_more"].append(len(more))
        out["best_score"].append(max([1.0 if taken else 0.0, *(s[3] for s in more)]))
    return base.batch(_SCHEMA, doc_id=rows.column(0), **out)


def find_pii(docs: DataFrame) -> DataFrame:
    """One row per document with the counts of base spans and all spans; narrow, no shuffle."""
    df = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return base.over_texts(df, _scan, "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_more long, best_score double", "doc_id")


def redact(text: str, mark: str = "[{}]") -> str:
    """text with every span replaced by its kind."""
    found = base_spans(text)
    spans = [(a, b, k) for k in BASE_KINDS for a, b in found[k]]
    spans += [(a, b, k) for k, a, b, _ in more_spans(text, [s[:2] for s in spans])]
    out, last = [], 0
    for a, b, k in sorted(spans):
        if a >= last:
            out += [text[last:a], mark.format(k)]
            last = b
    return "".join(out) + text[last:]


def op1_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_pii(base.table(spark, sf_dir, "documents", "doc_id", "text"))
