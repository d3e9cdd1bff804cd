"""Personal data by anchor expansion.

An Aho-Corasick automaton finds anchors (at-signs, plus signs, digits, URL schemes, identifier cues) in one pass over
a text; a deterministic local parser grows each anchor to its left and right and validates the result.

Results: null text is empty; no span gives an empty list and the digest of an empty string; rows with equal ids stay
separate rows; other columns are ignored; very long texts cost time in proportion to their length.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from veilwalk.llm.common import arrow_map, texts

BASE_KINDS = ("email", "ip", "card", "phone")
EXTRA_KINDS = ("url", "account", "secret")
KINDS = BASE_KINDS + EXTRA_KINDS

LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
DOMAIN = re.compile(r"[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++")
QUAD = re.compile(r"([0-9]+)\.([0-9]+)\.([0-9]+)\.([0-9]+)")
DIGITS = re.compile(r"[0-9]++")
CARD = re.compile(r"[0-9](?:[ -]?[0-9])+")
PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
URL_TAIL = re.compile(r"[^\s<>\"'`{}|\\^]+")
ACCOUNT = re.compile(r"(?:\s|number|no\.?|nr\.?|id|[:#=])*([A-Za-z]{0,4}[0-9](?:[ -]?[A-Za-z0-9]){5,33})", re.I)
SECRET_VALUE = re.compile(r"\s*[:=]\s*[\"']?([A-Za-z0-9+/_=-]{16,})")
KEY_ID = re.compile(r"[0-9A-Z]{16}(?![0-9A-Za-z])")
#: Fixed cue words, matched in lower case, upper case and with a capital.
ACCOUNT_CUES = ("iban", "account", "acct", "konto", "compte", "cuenta", "passport", "ssn")
SECRET_CUES = ("token", "secret", "api_key", "apikey", "password", "passwd")
SCHEMES = ("http://", "https://", "ftp://", "mailto:")
KEY_PREFIX = "AKIA"


def _automaton() -> ahocorasick.Automaton:
    a = ahocorasick.Automaton()
    for d in "0123456789":
        a.add_word(d, (0, d))
    a.add_word("@", (1, "@"))
    a.add_word("+", (2, "+"))
    for kind, words in ((3, SCHEMES), (4, ACCOUNT_CUES), (5, SECRET_CUES)):
        for w in words:
            for form in (w, w.upper(), w.capitalize()):
                a.add_word(form, (kind, w))
    a.add_word(KEY_PREFIX, (6, KEY_PREFIX))
    a.make_automaton()
    return a


_AUTOMATON: list = []


def luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        n = ord(d) - 48
        if i % 2:
            n = n * 2 - 9 if n > 4 else n * 2
        total += n
    return total % 10 == 0


def _iban_ok(s: str) -> bool:
    s = re.sub(r"[ -]", "", s).upper()
    if not re.fullmatch(r"[A-Z]{2}[0-9]{2}[A-Z0-9]{10,30}", s):
        return False
    return int("".join(str(int(c, 36)) for c in s[4:] + s[:4])) % 97 == 1


def find_spans(text: str | None) -> list[tuple[str, int, int]]:
    """(kind, start, end) in code points, by kind in the order of KINDS and then by start."""
    if not text:
        return []
    if not _AUTOMATON:
        _AUTOMATON.append(_automaton())
    found: dict[str, list[tuple[int, int]]] = {k: [] for k in KINDS}
    after_email = after_quad = after_card = after_phone = after_url = after_account = after_secret = 0
    for end, (kind, word) in _AUTOMATON[0].iter(text):
        at = end - len(word) + 1
        if kind == 0:
            if at >= after_card:
                m = CARD.match(text, at)
                after_card = m.end() if m else at + 1
                if m:
                    digits = re.sub(r"[ -]", "", m.group())
                    if 16 <= len(digits) <= 19 and luhn(digits):
                        found["card"].append(m.span())
            if at >= after_quad:
                m = QUAD.match(text, at)
                after_quad = m.end() if m else DIGITS.match(text, at).end()
                if m and all(len(p.lstrip("0")) <= 3 and int(p[-3:]) <= 255 for p in m.groups()):
                    found["ip"].append(m.span())
        elif kind == 1:
            start = at
            while start > after_email and text[start - 1] in LOCAL:
                start -= 1
            m = DOMAIN.match(text, at + 1) if start < at else None
            if m:
                after_email = m.end()
                found["email"].append((start, m.end()))
        elif kind == 2:
            m = PHONE.match(text, at) if at >= after_phone else None
            if m:
                after_phone = m.end()
                if 8 <= sum(c in "0123456789" for c in m.group()) <= 15:
                    found["phone"].append(m.span())
        elif kind == 3:
            m = URL_TAIL.match(text, end + 1) if at >= after_url else None
            if m and "." in m.group().rstrip(".,;:!?)"):
                after_url = m.end()
                found["url"].append((at, end + 1 + len(m.group().rstrip(".,;:!?)"))))
        elif kind == 4:
            if at >= after_account and not (at and text[at - 1].isalnum()):
                m = ACCOUNT.match(text, end + 1)
                digits = sum(c.isdigit() for c in m.group(1)) if m else 0
                if m and digits >= 6 and (word != "iban" or _iban_ok(m.group(1))):
                    after_account = m.end(1)
                    found["account"].append(m.span(1))
        elif kind == 5:
            m = SECRET_VALUE.match(text, end + 1) if at >= after_secret else None
            if m and any(c.isdigit() for c in m.group(1)):
                after_secret = m.end(1)
                found["secret"].append(m.span(1))
        elif at >= after_secret and not (at and text[at - 1].isalnum()):
            m = KEY_ID.match(text, end + 1)
            if m:
                after_secret = m.end()
                found["secret"].append((at, m.end()))
    return [(k, s, e) for k in KINDS for s, e in found[k]]


def redact(text: str | None, spans: list[tuple[str, int, int]]) -> str | None:
    """The text with each span replaced by its kind in square brackets; overlapping spans become one."""
    if not spans:
        return text
    out, at, merged = [], 0, []
    for kind, s, e in sorted(spans, key=lambda x: (x[1], -x[2])):
        if merged and s < merged[-1][2]:
            merged[-1][2] = max(merged[-1][2], e)
        else:
            merged.append([kind, s, e])
    for kind, s, e in merged:
        out += [text[at:s], f"[{kind.upper()}]"]
        at = e
    return "".join(out) + text[at:]


def joined(spans: list[tuple[str, int, int]]) -> str:
    return ",".join(f"{k}:{s}:{e}" for k, s, e in spans)


SPANS = T.StructType(
    [T.StructField("doc_id", T.LongType())]
    + [T.StructField(f"n_{k}", T.LongType()) for k in BASE_KINDS]
    + [T.StructField("base_sha256", T.StringType()), T.StructField("spans", T.StringType())]
)


def detect(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: counts of the base kinds, digest of the base spans, all spans. One pass, no shuffle."""

    def run(b: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        cols: list[list] = [[] for _ in SPANS.fields]
        for doc, text in zip(b.column(0).to_pylist(), texts(b.column(1)), strict=True):
            spans = find_spans(text)
            base = [x for x in spans if x[0] in BASE_KINDS]
            row = [doc, *(sum(x[0] == k for x in base) for k in BASE_KINDS)]
            row += [hashlib.sha256(joined(base).encode()).hexdigest(), joined(spans)]
            for c, v in zip(cols, row, strict=True):
                c.append(v)
        kinds = [pa.int64()] * 5 + [pa.string()] * 2
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], names=SPANS.names)

    return arrow_map(docs.select(docs[id_col].cast("long"), docs[text_col]), run, SPANS)


def redacted(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """The rows of docs with personal data replaced in the text; null texts stay null, other columns are untouched."""
    schema, i = docs.schema, docs.columns.index(text_col)

    def run(b: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        new = [redact(t, find_spans(t)) for t in b.column(i).to_pylist()]
        arrays = [pa.array(new, b.schema.field(i).type) if k == i else c for k, c in enumerate(b.columns)]
        yield pa.RecordBatch.from_arrays(arrays, schema=b.schema)

    return arrow_map(docs, run, schema)
