"""PII (operator 6) by anchor expansion.

An Aho-Corasick automaton passes once over each text and reports anchors: at-signs, plus-signs, digits, schemes and
identifier cues. Deterministic local parsers expand each anchor to its boundaries and validate it. The base kinds (email, ip, card,
phone) give exactly the leftmost non-overlapping matches of the contract's patterns; urls, accounts and street addresses are added.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BASE_KINDS = ("email", "ip", "card", "phone")
KINDS = (*BASE_KINDS, "url", "account", "address")
# fixed values: words that announce an account number, and street words that end or begin an address
CUES = ("IBAN", "iban", "Iban", "account", "Account", "ACCOUNT", "acct", "Acct", "Konto", "konto", "compte", "Compte", "cuenta", "Cuenta", "SSN", "ssn")
STREETS = ("Street", "Avenue", "Road", "Boulevard", "Lane", "Drive", "Straße", "Strasse")

_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_PHONE = re.compile(r"[\x20().0-9-]+")
_URL = re.compile(r"[^\s<>\"']+")
_ACCOUNT = re.compile(r"[\s:#.-]{0,4}(?:(?:no|nr|number|Nr|No)[\s:#.]{1,3})?([A-Z]{2}[0-9]{2}(?: ?[0-9A-Z]{4}){2,7}(?: ?[0-9A-Z]{1,3})?|[0-9][0-9 -]{5,24}[0-9])")
_HOUSE = re.compile(r"(?:[0-9]{1,5}[a-z]? )(?:[A-Z][a-zà-ÿ]+ ){1,3}$")
_SCHEME = frozenset("abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789+.-")


def _automaton() -> ahocorasick.Automaton:
    a = ahocorasick.Automaton()
    for c in "0123456789":
        a.add_word(c, ("d", 1))
    a.add_word("@", ("@", 1))
    a.add_word("+", ("+", 1))
    a.add_word("://", ("u", 3))
    for cue in CUES:
        a.add_word(cue, ("a", len(cue)))
    for street in STREETS:
        a.add_word(street, ("s", len(street)))
    a.make_automaton()
    return a


_anchors = None


def _luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if i % 2:
            d = d * 2 - 9 if d > 4 else d * 2
        total += d
    return total % 10 == 0


def _mod97(account: str) -> bool:
    turned = account[4:] + account[:4]
    rest = 0
    for c in turned:
        rest = (rest * 10 + int(c)) % 97 if c.isdigit() else (rest * 100 + ord(c) - 55) % 97
    return rest == 1


def _emails(text: str, ats: list[int]) -> list[tuple[int, int]]:
    out, end = [], 0
    for at in ats:
        if at < end:
            continue
        start = at
        while start > end and text[start - 1] in _LOCAL:
            start -= 1
        if start < at and (m := _DOMAIN.match(text, at + 1)):
            end = m.end()
            out.append((start, end))
    return out


def _ips(text: str, runs: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out, i = [], 0
    while i + 3 < len(runs):
        if all(runs[j][1] + 1 == runs[j + 1][0] and text[runs[j][1]] == "." for j in (i, i + 1, i + 2)):
            if all(len(p) <= 3 and int(p) <= 255 for p in (text[a:b].lstrip("0") or "0" for a, b in runs[i : i + 4])):
                out.append((runs[i][0], runs[i + 3][1]))
            i += 4
        else:
            i += 1
    return out


def _cards(text: str, runs: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out, i = [], 0
    while i < len(runs):
        j, n = i, runs[i][1] - runs[i][0]
        while j + 1 < len(runs) and runs[j][1] + 1 == runs[j + 1][0] and text[runs[j][1]] in " -":
            j += 1
            n += runs[j][1] - runs[j][0]
        if 16 <= n <= 19 and _luhn("".join(text[a:b] for a, b in runs[i : j + 1])):
            out.append((runs[i][0], runs[j][1]))
        i = j + 1
    return out


def _phones(text: str, pluses: list[int], digits: set[int]) -> list[tuple[int, int]]:
    out, end = [], 0
    for at in pluses:
        if at < end or at + 1 not in digits or not (m := _PHONE.match(text, at + 2)):
            continue
        last = m.end()
        while last > at + 3 and last - 1 not in digits:
            last -= 1
        if last <= at + 3:
            continue
        end = last
        if 8 <= sum(k in digits for k in range(at, last)) <= 15:
            out.append((at, last))
    return out


def find_spans(text: str | None) -> dict[str, list[tuple[int, int]]]:
    """Spans of each kind, (start, end) in code points, end exclusive."""
    global _anchors
    if not text:
        return {}
    if _anchors is None:
        _anchors = _automaton()
    ats, pluses, urls, cues, streets, runs, digits = [], [], [], [], [], [], set()
    for last, (kind, length) in _anchors.iter(text):
        if kind == "d":
            digits.add(last)
            if runs and runs[-1][1] == last:
                runs[-1] = (runs[-1][0], last + 1)
            else:
                runs.append((last, last + 1))
        else:
            {"@": ats, "+": pluses, "u": urls, "a": cues, "s": streets}[kind].append((last - length + 1, last + 1) if kind in "uas" else last)
    found = {}
    if ats:
        found["email"] = _emails(text, ats)
    if runs:
        found["ip"] = _ips(text, runs)
        found["card"] = _cards(text, runs)
    if pluses:
        found["phone"] = _phones(text, pluses, digits)
    end = 0
    for a, b in urls:
        start = a
        while start > end and text[start - 1] in _SCHEME:
            start -= 1
        if start < a and text[start].isalpha() and (m := _URL.match(text, b)):
            end = m.end()
            found.setdefault("url", []).append((start, end))
    end = 0
    for a, b in cues:
        if a >= end and (m := _ACCOUNT.match(text, b)):
            body = re.sub("[ -]", "", m[1])
            if not body[0].isalpha() or _mod97(body):
                end = m.end(1)
                found.setdefault("account", []).append(m.span(1))
    end = 0
    for a, b in streets:
        near = max(end, a - 80)
        if m := _HOUSE.search(text[near:a]):
            end = b
            found.setdefault("address", []).append((near + m.start(), b))
    return {k: v for k, v in found.items() if v}


def _joined(found: dict[str, list[tuple[int, int]]], kinds: tuple[str, ...]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k in kinds for a, b in found.get(k, ()))


def _rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        counts: dict[str, list[int]] = {k: [] for k in BASE_KINDS}
        digest, spans = [], []
        for text in batch.column("text"):
            found = find_spans(text.as_py())
            for k in BASE_KINDS:
                counts[k].append(len(found.get(k, ())))
            digest.append(hashlib.sha256(_joined(found, BASE_KINDS).encode()).hexdigest())
            spans.append(_joined(found, KINDS))
        yield pa.record_batch([batch.column("doc_id"), *[pa.array(counts[k], pa.int64()) for k in BASE_KINDS], pa.array(digest, pa.string()), pa.array(spans, pa.string())], names=["doc_id", *[f"n_{k}" for k in BASE_KINDS], "base_sha256", "spans"])


def find_pii(docs: DataFrame) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone (base spans), base_sha256, spans for every row of ``docs`` (doc_id, text).

    A null or empty text has no spans; its digest is that of the empty string.
    """
    schema = "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string"
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(_rows, schema)


def mask_pii(docs: DataFrame, fill: str = "*") -> DataFrame:
    """``docs`` with every code point of a span replaced in ``text``; other columns and rows as they are."""

    def cover(text: str | None) -> str | None:
        found = find_spans(text)
        if not found:
            return text
        chars = list(text)
        for spans in found.values():
            for a, b in spans:
                chars[a:b] = fill * (b - a)
        return "".join(chars)

    @F.pandas_udf("string")
    def covered(texts):
        return texts.map(cover)

    return docs.withColumn("text", covered("text"))
