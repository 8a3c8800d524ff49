"""Personal data in texts: patterns propose spans, checksums confirm them, context words adjust a score.

Base kinds (email, ip, card, phone) are kept whenever pattern and check hold.  Further kinds (iban,
routing, ssn, secret) start from a prior that their check raises and that words nearby raise or lower; a
span is kept from ``threshold`` on.  A secret is a key or token: its check is the entropy of its characters.  All offsets count code points, ends exclusive.
"""

from __future__ import annotations

import hashlib
import re
from collections import Counter
from math import log2

from pyspark.sql import DataFrame, SparkSession

from flowrings.llm.arrow import documents_view, map_rows

KINDS = ("email", "ip", "card", "phone", "iban", "routing", "ssn", "secret")
BASE = KINDS[:4]

# The patterns. Runs are matched possessively or from their first character only, which
# leaves the leftmost matches as they are and keeps the time linear in the text.
_DOMAIN = re.compile(r"@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
_LOCAL = re.compile(r"[A-Za-z0-9._%+-]+\Z")
_LOCAL_CHARS = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_IBAN = re.compile(r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?:\x20?[A-Z0-9]{4}){2,7}(?:\x20?[A-Z0-9]{1,3})?(?![A-Za-z0-9])")
_ROUTING = re.compile(r"(?<![0-9A-Za-z.-])[0-9]{9}(?![0-9A-Za-z-])")
_SSN = re.compile(r"(?<![0-9-])(?!000|666|9)[0-9]{3}-(?!00)[0-9]{2}-(?!0000)[0-9]{4}(?![0-9-])")
_SECRET = re.compile(r"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9+/_-]{20,200}={0,2}(?![A-Za-z0-9+/_=-])")
_NOT_DIGIT = re.compile(r"[^0-9]")
# Context words, by kind; prior, gain of a passed checksum, gain or loss by a word nearby.
_CONTEXT = {
    "iban": (re.compile(r"iban|account|konto|compte|cuenta|bank", re.I), re.compile(r"example|sample|dummy", re.I)),
    "routing": (re.compile(r"routing|aba|transit|bank", re.I), re.compile(r"order|ticket|invoice|serial", re.I)),
    "ssn": (re.compile(r"ssn|social security|tax", re.I), re.compile(r"order|ticket|part no|serial", re.I)),
    "secret": (re.compile(r"token|secret|passw|credential|bearer|(?:api|access|private|auth)[ _-]?key", re.I), re.compile(r"sha-?[0-9]|md5|commit|checksum|digest|uuid", re.I)),
}
_PRIOR = {"iban": 0.3, "routing": 0.1, "ssn": 0.35, "secret": 0.1}
_CHECKED, _NEAR, _AGAINST = 0.4, 0.3, 0.3


def luhn(digits: str) -> bool:
    """The card checksum: every second digit from the right doubled, digit sums, total divisible by 10."""
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        total += d if k % 2 == 0 else d * 2 - 9 * (d > 4)
    return total % 10 == 0


def mod97(iban: str) -> bool:
    """The IBAN checksum: country and check digits moved to the end, letters as numbers, remainder 1."""
    moved = iban[4:] + iban[:4]
    return int("".join(str(int(c, 36)) for c in moved)) % 97 == 1


def aba(digits: str) -> bool:
    """The bank routing checksum: weights 3, 7, 1."""
    return digits != "000000000" and sum(w * int(c) for w, c in zip((3, 7, 1) * 3, digits)) % 10 == 0


def random_looking(text: str, bits: float = 3.0) -> bool:
    """Letters and digits both, and at least ``bits`` of entropy a character."""
    if text.isalpha() or not any(c.isalpha() for c in text):
        return False
    return -sum(n / len(text) * log2(n / len(text)) for n in Counter(text).values()) >= bits


def emails(text: str) -> list[tuple[int, int]]:
    """Leftmost non-overlapping matches, found from their domains: the local part is the run before the @."""
    found, last = [], 0
    for m in _DOMAIN.finditer(text):
        at = start = m.start()
        while start > last and text[start - 1] in _LOCAL_CHARS:
            start -= 1
        if start < at:
            found.append((start, m.end()))
            last = m.end()
    return found


def base_spans(text: str) -> list[tuple[str, int, int]]:
    out = []
    if "@" in text:
        out += [("email", s, e) for s, e in emails(text)]
    if "." in text:
        out += [("ip", *m.span()) for m in _IP.finditer(text) if all(len(p.lstrip("0")) <= 3 and int(p) <= 255 for p in m[0].split("."))]
    for m in _CARD.finditer(text):
        if 12 <= m.end() - m.start() and 12 <= len(d := _NOT_DIGIT.sub("", m[0])) <= 19 and luhn(d):
            out.append(("card", *m.span()))
    if "+" in text:
        out += [("phone", *m.span()) for m in _PHONE.finditer(text) if 9 <= len(_NOT_DIGIT.sub("", m[0])) <= 15]
    return out


def scored_spans(text: str, near: int = 40) -> list[tuple[str, int, int, float]]:
    """Spans of the further kinds with their scores (0 to 1)."""
    out = []
    for kind, pattern in (("iban", _IBAN), ("routing", _ROUTING), ("ssn", _SSN), ("secret", _SECRET)):
        for m in pattern.finditer(text):
            score = _PRIOR[kind]
            if kind == "iban" and mod97(m[0].replace(" ", "")) or kind == "routing" and aba(m[0]) or kind == "secret" and random_looking(m[0]):
                score += _CHECKED
            elif kind != "ssn":
                continue
            around = text[max(0, m.start() - near) : m.start()] + " " + text[m.end() : m.end() + near]
            good, bad = _CONTEXT[kind]
            score += _NEAR * bool(good.search(around)) - _AGAINST * bool(bad.search(around))
            out.append((kind, *m.span(), min(1.0, max(0.0, score))))
    return out


def find_spans(text: str, threshold: float = 0.6, near: int = 40) -> list[tuple[str, int, int, float]]:
    """All spans by start, then kind.  A further span that overlaps a base span gives way to it."""
    base = [(k, s, e, 1.0) for k, s, e in base_spans(text)]
    more = [x for x in scored_spans(text, near) if x[3] >= threshold and not any(s < x[2] and x[1] < e for _, s, e, _ in base)]
    return sorted(base + more, key=lambda x: (x[1], KINDS.index(x[0])))


def mask(text: str, spans: list[tuple[str, int, int, float]]) -> str:
    """The text with each span replaced by its kind in angle brackets; of overlapping spans the first counts."""
    out, last = [], 0
    for kind, s, e, _ in spans:
        if s >= last:
            out += [text[last:s], f"<{kind}>"]
            last = e
    return "".join([*out, text[last:]])


def _show(spans) -> str:
    return ",".join(f"{x[0]}:{x[1]}:{x[2]}" for x in spans)


def detect(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", threshold: float = 0.6, near: int = 40) -> DataFrame:
    """One row per input row: doc_id, counts by base kind, base_sha256, spans, n_secret, masked (the text with its spans masked).

    Null and empty texts have no spans.  Rows are judged by their own text, whatever their ids.  Nothing is
    shuffled; a batch holds a bounded number of bytes.
    """

    def row(doc_id, raw):
        text = (raw or b"").decode()
        spans = find_spans(text, threshold, near)
        base = [x for x in spans if x[0] in BASE]
        counts = [sum(x[0] == k for x in base) for k in BASE]
        return doc_id, *counts, hashlib.sha256(_show(base).encode()).hexdigest(), _show(spans), sum(x[0] == "secret" for x in spans), mask(text, spans)

    schema = "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_secret long, masked string"
    return map_rows(documents_view(docs, id_col, text_col), row, schema, ["doc_id", "text"])


def op5_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return detect(spark.read.parquet(f"{sf_dir}/documents.parquet")).drop("masked")
