"""Personal data in whole texts: patterns propose, checksums confirm, context adjusts.

Base kinds are found leftmost and non-overlapping per kind. Two kinds are added beside
them: ``iban`` (mod-97 confirmed) and ``ssn`` (three-two-four digits that need a context
word). Every span gets a score: a prior of its kind, raised when a context word stands
within ``CONTEXT`` characters and, for cards and ibans, by the checksum. Base spans stay
whatever their score; added ones need ``ADDED_SCORE``.
"""

from __future__ import annotations

import hashlib
import re

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import small_batches, texts_of, tidy

KINDS = ("email", "ip", "card", "phone")
ADDED = ("iban", "ssn")
CONTEXT = 40
ADDED_SCORE = 0.6

# The base patterns, in forms that try each run of characters once. A run that
# fails from its first character fails from all its others, and one that a match ends is used
# up, so the leftmost matches are the same.
LOCAL = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-"
DOMAIN = re.compile(r"[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++")
IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
CARD = re.compile(r"[0-9]++(?:[\x20-][0-9]++)*+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")

IBAN = re.compile(r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?![A-Za-z0-9])")
SSN = re.compile(r"(?<![0-9-])(?!000|666|9)[0-9]{3}-(?!00)[0-9]{2}-(?!0000)[0-9]{4}(?![0-9-])")

# Prior score and context words of each kind.
PRIOR = {"email": 0.9, "ip": 0.6, "card": 0.7, "phone": 0.6, "iban": 0.7, "ssn": 0.4}
WORDS = {
    "email": ("mail", "contact", "write"),
    "ip": ("ip", "address", "host", "server"),
    "card": ("card", "visa", "credit", "payment", "pay"),
    "phone": ("phone", "call", "tel", "mobile", "fax"),
    "iban": ("iban", "account", "bank", "transfer"),
    "ssn": ("ssn", "social", "security", "tax"),
}
_CONTEXT = {k: re.compile(r"\b(?:" + "|".join(w) + r")", re.I) for k, w in WORDS.items()}
_DIGIT = re.compile(r"[0-9]")


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if i % 2:
            d = d * 2 - 9 if d > 4 else d * 2
        total += d
    return total % 10 == 0


def mod97(iban: str) -> bool:
    """The account number check: country and check digits go last, letters count from 10, remainder 1."""
    s = iban.replace(" ", "")
    return 15 <= len(s) <= 34 and int("".join(str(int(c, 36)) for c in s[4:] + s[:4])) % 97 == 1


def _digits(s: str) -> str:
    return "".join(c for c in s if "0" <= c <= "9")


def emails(text: str) -> list[tuple[int, int]]:
    """From each ``@``: the characters before it that may stand there, back to the last match, and the domain after it."""
    out, free = [], 0
    at = text.find("@")
    while at >= 0:
        before = text[free:at]
        size = len(before) - len(before.rstrip(LOCAL))
        domain = DOMAIN.match(text, at + 1) if size else None
        if domain:
            out.append((at - size, domain.end()))
        free = domain.end() if domain else at + 1
        at = text.find("@", free)
    return out


def _is_ip(found: str) -> bool:
    return all(len(p := part.lstrip("0")) <= 3 and int(p or "0") <= 255 for part in found.split("."))


def base_spans(text: str) -> list[tuple[str, int, int]]:
    """(kind, start, end) in code points, by kind as listed, then start."""
    out = []
    if "@" in text:
        out += [("email", *s) for s in emails(text)]
    if _DIGIT.search(text):
        if "." in text:
            out += [("ip", *m.span()) for m in IP.finditer(text) if _is_ip(m[0])]
        for m in CARD.finditer(text):
            if 16 <= m.end() - m.start() <= 37 and 16 <= len(d := _digits(m[0])) <= 19 and luhn(d):
                out.append(("card", *m.span()))
        if "+" in text:
            out += [("phone", *m.span()) for m in PHONE.finditer(text) if 8 <= len(_digits(m[0])) <= 15]
    return out


def score(kind: str, start: int, end: int, text: str) -> float:
    near = text[max(0, start - CONTEXT) : start] + " " + text[end : end + CONTEXT]
    return round(min(1.0, PRIOR[kind] + (0.3 if _CONTEXT[kind].search(near) else 0.0)), 3)


def all_spans(text: str) -> list[tuple[str, int, int, float]]:
    """Base spans and confirmed added ones, with scores; by kind, then start."""
    out = [(*s, score(*s, text)) for s in base_spans(text)]
    if _DIGIT.search(text):
        found = [("iban", *m.span()) for m in IBAN.finditer(text) if mod97(m[0])] + [("ssn", *m.span()) for m in SSN.finditer(text)]
        out += [(*s, v) for s in found if (v := score(*s, text)) >= ADDED_SCORE]
    return out


def joined(spans) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b, *_ in spans)


def find_pii(docs: DataFrame) -> DataFrame:
    """doc_id, counts of the base kinds, base_sha256, spans, scores for every row.

    A null text is an empty one: no spans. Rows are independent; repeated ids and null ids
    give a row each. An empty table gives an empty result; columns other than doc_id and
    text are ignored. ``scores`` lists the spans' scores in the order of ``spans``.
    """
    small_batches(docs.sparkSession)
    ids = docs.schema["doc_id"].dataType.simpleString()

    def run(batches):
        for batch in batches:
            cols: list[list] = [[] for _ in range(7)]
            for text in texts_of(batch.column(1)).to_pylist():
                spans = all_spans(text)
                base = [s for s in spans if s[0] in KINDS]
                for k, kind in enumerate(KINDS):
                    cols[k].append(sum(s[0] == kind for s in base))
                cols[4].append(hashlib.sha256(joined(base).encode()).hexdigest())
                cols[5].append(joined(spans))
                cols[6].append(",".join(f"{s[3]:g}" for s in spans))
            arrays = [pa.array(c, pa.int64() if k < 4 else pa.string()) for k, c in enumerate(cols)]
            yield pa.RecordBatch.from_arrays([batch.column(0), *arrays], names)
        tidy()

    names = ["doc_id", *[f"n_{k}" for k in KINDS], "base_sha256", "spans", "scores"]
    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {ids}, " + ", ".join(f"n_{k} long" for k in KINDS) + ", base_sha256 string, spans string, scores string")


def masked(text: str) -> str:
    """The text with every span, overlapping ones merged, replaced by ``[KIND]``."""
    spans = sorted((a, -b, k) for k, a, b, _ in all_spans(text))
    if not spans:
        return text
    out, at = [], 0
    for a, b, kind in spans:
        if -b <= at:
            continue
        if a >= at:
            out += [text[at:a], f"[{kind.upper()}]"]
        at = -b
    return "".join(out) + text[at:]


def mask_pii(docs: DataFrame, text: str = "text") -> DataFrame:
    """The same rows and columns with personal data masked in ``text``; nulls stay null.

    Rows are independent, repeated ones stay repeated; an empty table stays empty.
    """
    small_batches(docs.sparkSession)
    at = docs.columns.index(text)

    def run(batches):
        for batch in batches:
            clean = pa.array([None if t is None else masked(t) for t in batch.column(at).to_pylist()], batch.schema.field(at).type)
            yield batch.set_column(at, batch.schema.field(at), clean)
        tidy()

    return docs.mapInArrow(run, docs.schema)
