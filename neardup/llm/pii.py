"""Personal data: regular expressions propose spans, checksums confirm them, nearby words adjust a score.

Base kinds (email, ip, card, phone) follow a fixed contract: leftmost non-overlapping matches per kind, those
that fail a check are dropped without another try, and the rest always stay. The further kinds (iban, ssn,
passport) are kept when their score, raised or lowered by words just before and after them, reaches
``KEEP``. Every expression is written so that a scan of any text takes linear time.

Defined cases: a null text counts as empty; an empty text has no spans; overlapping spans of different kinds
all stay in the list and are masked as one piece; repeated rows are treated alike; extra columns are kept by
``redact`` and ignored by ``find``; an empty table gives an empty result.
"""

from __future__ import annotations

import math
import re
from collections import Counter

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from neardup.llm.batches import by_row

BASE = ("email", "ip", "card", "phone")
KINDS = (*BASE, "iban", "ssn", "passport", "secret")
#: Characters of context on each side, and the least score at which a span of a further kind is kept.
CONTEXT, KEEP = 40, 0.5
#: Start score of each kind, and the words near a span that raise or lower it.
START = {"email": 0.9, "ip": 0.6, "card": 0.8, "phone": 0.7, "iban": 0.8, "ssn": 0.35, "passport": 0.3, "secret": 0.8}
RAISE = {
    "email": {"mail", "email", "contact"},
    "ip": {"ip", "host", "server", "address"},
    "card": {"card", "visa", "mastercard", "credit", "karte", "carte", "tarjeta"},
    "phone": {"phone", "tel", "call", "mobile", "telefon", "téléphone", "teléfono"},
    "iban": {"iban", "bank", "account", "konto", "compte", "cuenta"},
    "ssn": {"ssn", "social", "security"},
    "passport": {"passport", "reisepass", "passeport", "pasaporte"},
    "secret": {"token", "secret", "password", "key", "passwort", "clave"},
}
LOWER = {"version", "isbn", "order", "invoice", "build", "release", "serial"}
#: Characters of an account number by country.
IBAN_LENGTH = {
    "AD": 24, "AE": 23, "AL": 28, "AT": 20, "AZ": 28, "BA": 20, "BE": 16, "BG": 22, "BH": 22, "BR": 29, "BY": 28, "CH": 21, "CR": 22, "CY": 28,
    "CZ": 24, "DE": 22, "DK": 18, "DO": 28, "EE": 20, "EG": 29, "ES": 24, "FI": 18, "FO": 18, "FR": 27, "GB": 22, "GE": 22, "GI": 23, "GL": 18,
    "GR": 27, "GT": 28, "HR": 21, "HU": 28, "IE": 22, "IL": 23, "IQ": 23, "IS": 26, "IT": 27, "JO": 30, "KW": 30, "KZ": 20, "LB": 28, "LC": 32,
    "LI": 21, "LT": 20, "LU": 20, "LV": 21, "MC": 27, "MD": 24, "ME": 22, "MK": 19, "MR": 27, "MT": 31, "MU": 30, "NL": 18, "NO": 15, "PK": 24,
    "PL": 28, "PS": 29, "PT": 25, "QA": 29, "RO": 24, "RS": 22, "SA": 24, "SC": 31, "SE": 24, "SI": 19, "SK": 24, "SM": 27, "ST": 25, "SV": 28,
    "TL": 23, "TN": 24, "TR": 26, "UA": 29, "VA": 22, "VG": 24, "XK": 20,
}
#: Least entropy of a secret's characters, in bits each.
VARIED = 2.8

_LOCAL = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-"
_DOMAIN = re.compile(r"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
# A run of digits is taken whole from its first digit (a later start in it would end alike), never given back.
_IP = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++")
_CARD = re.compile(r"[0-9](?:[ -]?[0-9])++")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_IBAN = re.compile(r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?= ?[A-Z0-9])")
_IBAN_OF = {n: re.compile(rf"[A-Z]{{2}}[0-9]{{2}}(?: ?[A-Z0-9]){{{n - 4}}}(?![A-Za-z0-9])") for n in set(IBAN_LENGTH.values())}
_SECRET = re.compile(
    r"(?i:\b(?:token|secret|passw(?:or)?d|pwd|api[_-]?key|access[_-]?key|private[_-]?key|auth)\b[\"']?[ \t]{0,4}[:=]>?[ \t]{0,4}[\"']?)([A-Za-z0-9_+/=.-]{8,})"
    r"|\b((?:AKIA|ASIA)[A-Z0-9]{16}|gh[pousr]_[A-Za-z0-9]{36}|xox[abprs]-[A-Za-z0-9-]{10,}|sk_live_[A-Za-z0-9]{16,})"
)
_SSN = re.compile(r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])")
_PASSPORT = re.compile(r"\b[A-Z][0-9]{8}\b")
_WORD = re.compile(r"[^\W\d_]+")


def luhn(digits: str) -> bool:
    """Whether the Luhn sum of a digit string ends in 0."""
    total = 0
    for k, d in enumerate(reversed(digits)):
        n = int(d) * (1 + k % 2)
        total += n - 9 * (n > 9)
    return total % 10 == 0


def mod97(code: str) -> bool:
    """Whether an account number with its country and check digits leaves 1."""
    code = code.replace(" ", "")
    return int("".join(str(int(c, 36)) for c in code[4:] + code[:4])) % 97 == 1


def entropy(value: str) -> float:
    """Bits a character by how often each occurs in the value."""
    n = len(value)
    return -sum(k / n * math.log2(k / n) for k in Counter(value).values())


def _emails(text: str):
    end, at = 0, text.find("@")
    while at >= 0:
        before = text[end:at]
        start = end + len(before.rstrip(_LOCAL))
        if start < at and (m := _DOMAIN.match(text, at)):
            yield start, m.end()
            end = m.end()
        else:
            end = at + 1
        at = text.find("@", end)


def _numbers(text: str):
    """The base spans and proposals that hold digits."""
    if "." in text:
        for m in _IP.finditer(text):
            if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in m[0].split(".")):
                yield "ip", m.start(), m.end()
    for m in _CARD.finditer(text):
        if m.end() - m.start() >= 13:
            digits = m[0].replace(" ", "").replace("-", "")
            if 13 <= len(digits) <= 19 and luhn(digits):
                yield "card", m.start(), m.end()
    if "+" in text:
        for m in _PHONE.finditer(text):
            if 9 <= sum("0" <= c <= "9" for c in m[0]) <= 15:
                yield "phone", m.start(), m.end()
    for m in _IBAN.finditer(text):
        whole = _IBAN_OF[n].match(text, m.start()) if (n := IBAN_LENGTH.get(m[0][:2])) else None
        if whole and mod97(whole[0]):
            yield "iban", whole.start(), whole.end()
    for m in _SSN.finditer(text):
        if m[0][:3] not in ("000", "666") and m[0][0] != "9" and m[0][4:6] != "00" and m[0][7:] != "0000":
            yield "ssn", m.start(), m.end()
    for m in _PASSPORT.finditer(text):
        yield "passport", m.start(), m.end()
    for m in _SECRET.finditer(text):
        value = m[m.lastindex]
        if any("0" <= c <= "9" for c in value) and entropy(value) >= VARIED:
            yield "secret", *m.span(m.lastindex)


def score(text: str, kind: str, start: int, end: int) -> float:
    """Start score of the kind, moved by the words around the span."""
    near = {w.lower() for w in _WORD.findall(text[max(0, start - CONTEXT) : start] + "|" + text[end : end + CONTEXT])}
    return min(1.0, max(0.0, START[kind] + 0.3 * bool(near & RAISE[kind]) - 0.3 * bool(near & LOWER)))


def spans(text: str | None) -> list[tuple[str, int, int, float]]:
    """``(kind, start, end, score)`` of a text by kind as in ``KINDS``, then start; code points, end exclusive."""
    text = text or ""
    found = [("email", s, e) for s, e in _emails(text)]
    if re.search("[0-9]", text):
        found += _numbers(text)
    scored = [(k, s, e, round(score(text, k, s, e), 3)) for k, s, e in found]
    kept = [x for x in scored if x[0] in BASE or x[3] >= KEEP]
    return sorted(kept, key=lambda x: (KINDS.index(x[0]), x[1]))


_SPANS = "array<struct<kind:string,start:int,end:int,score:double>>"


def _mask(text: str) -> str:
    pieces: list[list] = []
    for kind, s, e, _ in sorted(spans(text), key=lambda x: (x[1], -x[2])):
        if pieces and s < pieces[-1][1]:
            pieces[-1][1] = max(pieces[-1][1], e)
        else:
            pieces.append([s, e, kind])
    out, upto = [], 0
    for s, e, kind in pieces:
        out += [text[upto:s], f"[{kind.upper()}]"]
        upto = e
    return "".join([*out, text[upto:]])


def find(docs: DataFrame) -> DataFrame:
    """``(doc_id, spans)`` for each row of ``docs(doc_id, text)``."""
    found = by_row(lambda: lambda t: ([dict(zip(("kind", "start", "end", "score"), x, strict=True)) for x in spans(t)],), f"spans {_SPANS}")
    return docs.select("doc_id", found("text").alias("f")).select("doc_id", "f.spans")


def redact(docs: DataFrame) -> DataFrame:
    """``docs`` with every span of its text replaced by its kind in brackets; ``n_chars``, if there, follows. A null text stays null."""
    masked = by_row(lambda: _mask, "string")
    out = docs.withColumn("text", F.when(F.col("text").isNotNull(), masked("text")))
    return out.withColumn("n_chars", F.char_length("text").cast("long")) if "n_chars" in docs.columns else out


def joined(found: str | Column) -> Column:
    """Spans as ``kind:start:end``, comma-joined."""
    text = lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))
    return F.array_join(F.transform(found, text), ",")


def digest(found: DataFrame) -> DataFrame:
    """Counts of the base kinds, hash of the base spans, all spans, their number and their scores in the same order, of ``find()``'s rows."""
    base = F.filter("spans", lambda s: s["kind"].isin(*BASE))
    count = lambda k: F.size(F.filter("spans", lambda s: s["kind"] == k)).cast("long")
    return found.select(
        "doc_id", *(count(k).alias(f"n_{k}") for k in BASE), F.sha2(joined(base).cast("binary"), 256).alias("base_sha256"), joined("spans").alias("spans"),
        F.size("spans").cast("long").alias("n_spans"), F.array_join(F.transform("spans", lambda s: s["score"].cast("string")), ",").alias("scores"),
    )
