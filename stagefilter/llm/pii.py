"""Operator 6: personal data by patterns, checksums and context.

Patterns propose spans; validators (part limits, Luhn, mod-97, digit counts) confirm
them; words near a span move its score. Four base kinds stay whatever their score; the
method adds bank account numbers (mod-97) and national phone numbers that a context word
backs. Positions are code points, ends exclusive.

Edge cases: null text counts as empty; long texts are scanned once per kind in linear
time (each search starts from a rare character); repeated rows are scanned each;
extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

BASE_KINDS = ("email", "ip", "card", "phone")
KINDS = (*BASE_KINDS, "iban", "local_phone")

# The patterns of the base kinds, possessive where the shorter match can't succeed.
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++")
_IP = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++")
_CARD = re.compile(r"(?<![0-9])[0-9](?:[ -]?[0-9])++")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_IBAN = re.compile(r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]){11,30}")
#: Characters of an account number by country, tried first; other lengths and countries are tried from the longest down.
_IBAN_LENGTH = {"AT": 20, "BE": 16, "CH": 21, "DE": 22, "DK": 18, "ES": 24, "FI": 18, "FR": 27, "GB": 22, "IE": 22, "IT": 27, "LU": 20, "NL": 18, "NO": 15, "PL": 28, "PT": 25, "SE": 24}
_LOCAL_PHONE = re.compile(r"(?<![0-9+])0[0-9]{1,4}[ /-][0-9]{2,4}(?:[ -][0-9]{2,4}){1,3}+(?![0-9])")

#: Score before context, and words within CONTEXT code points that raise or lower it.
PRIOR = {"email": 0.9, "ip": 0.6, "card": 0.8, "phone": 0.7, "iban": 0.8, "local_phone": 0.3}
CONTEXT = 40
RAISING = {
    "email": ("mail", "contact", "write"), "ip": ("ip", "host", "server", "address"), "card": ("card", "visa", "credit", "pay"),
    "phone": ("phone", "call", "tel", "mobile", "fax"), "iban": ("iban", "account", "bank"), "local_phone": ("phone", "call", "tel", "mobile", "fax"),
}
LOWERING = {"ip": ("version", "release"), "card": ("isbn", "order", "serial"), "phone": ("example",), "email": ("example",), "iban": ("example",), "local_phone": ("order", "serial", "isbn")}


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if i % 2:
            d = d * 2 - 9 * (d > 4)
        total += d
    return total % 10 == 0


def mod97(code: str) -> bool:
    code = code.replace(" ", "")
    return int("".join(str(int(c, 36)) for c in code[4:] + code[:4])) % 97 == 1


def _emails(text: str) -> Iterator[tuple[int, int]]:
    done = 0
    at = text.find("@")
    while at >= 0:
        start = at
        while start > done and text[start - 1] in _LOCAL:
            start -= 1
        if start < at and (m := _DOMAIN.match(text, at)):
            yield start, m.end()
            done = m.end()
        at = text.find("@", max(at + 1, done))


def _ibans(text: str) -> Iterator[tuple[int, int]]:
    """Account numbers: the words after a number may look like more of it, so each end of a word in the longest run is tried."""
    at = 0
    while m := _IBAN.search(text, at):
        start, n, ends = m.start(), 0, []
        for i in range(start, m.end()):
            n += text[i] != " "
            # an end is followed by no letter or digit
            if n >= 15 and text[i] != " " and not (text[i + 1 : i + 2].isascii() and text[i + 1 : i + 2].isalnum()):
                ends.append((n == _IBAN_LENGTH.get(m[0][:2]), i + 1))
        end = next((e for _, e in sorted(ends, reverse=True) if mod97(text[start:e])), None)
        if end:
            yield start, end
        # another number may begin inside a run that is none
        at = end or start + 4


def _parts_ok(ip: str) -> bool:
    return all(len(p) <= 3 and int(p or "0") <= 255 for p in (q.lstrip("0") for q in ip.split(".")))


def spans(text: str) -> list[tuple[str, int, int]]:
    """All confirmed spans in the order of KINDS, then start."""
    out: list[tuple[str, int, int]] = []
    if "@" in text:
        out += [("email", a, b) for a, b in _emails(text)]
    if "." in text:
        out += [("ip", m.start(), m.end()) for m in _IP.finditer(text) if _parts_ok(m[0])]
    for m in _CARD.finditer(text):
        if m.end() - m.start() >= 13 and 13 <= len(d := re.sub("[ -]", "", m[0])) <= 19 and luhn(d):
            out.append(("card", m.start(), m.end()))
    if "+" in text:
        for m in _PHONE.finditer(text):
            if 9 <= sum(c.isdigit() for c in m[0]) <= 15:
                out.append(("phone", m.start(), m.end()))
    out += [("iban", a, b) for a, b in _ibans(text)]
    taken = [(a, b) for _, a, b in out]
    for m in _LOCAL_PHONE.finditer(text):
        if not any(a < m.end() and m.start() < b for a, b in taken) and score(text, "local_phone", m.start(), m.end()) >= 0.5:
            out.append(("local_phone", m.start(), m.end()))
    return out


def score(text: str, kind: str, start: int, end: int) -> float:
    """Prior of the kind, moved by context words near the span, within 0 and 1."""
    near = (text[max(0, start - CONTEXT) : start] + " " + text[end : end + CONTEXT]).lower()
    value = PRIOR[kind] + 0.3 * any(w in near for w in RAISING.get(kind, ())) - 0.3 * any(w in near for w in LOWERING.get(kind, ()))
    return min(1.0, max(0.0, value))


SCHEMA = "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, lowest_score double"


def _scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names = [x.split()[0] for x in SCHEMA.split(", ")]
    for batch in batches:
        rows: list[list] = [[] for _ in names]
        for doc_id, value in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
            text = value.as_py() or ""
            found = spans(text)
            said = [f"{k}:{a}:{b}" for k, a, b in found]
            base = [s for s, (k, _, _) in zip(said, found, strict=True) if k in BASE_KINDS]
            row = [doc_id, *(sum(k == kind for k, _, _ in found) for kind in BASE_KINDS), hashlib.sha256(",".join(base).encode()).hexdigest(), ",".join(said), min((score(text, *s) for s in found), default=None)]
            for column, x in zip(rows, row, strict=True):
                column.append(x)
        types = [pa.int64()] * 5 + [pa.string()] * 2 + [pa.float64()]
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(rows, types, strict=True)], names=names)


def personal_data(docs: DataFrame) -> DataFrame:
    """One row per document: counts of the base kinds, digest of their spans, all spans, lowest score."""
    return docs.selectExpr("cast(doc_id as bigint) doc_id", "text").mapInArrow(_scan, SCHEMA)
