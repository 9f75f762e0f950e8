"""Personal data: patterns propose spans, checksums confirm them, nearby words adjust the score.

The four base kinds (email, ip, card, phone) follow fixed patterns, leftmost and non-overlapping
per kind; a match that fails its check (octets up to 255, 12-19 digits passing Luhn, 9-15 digits) is dropped without a retry.
Further kinds are added beside them: ``iban`` (confirmed by mod-97), ``secret`` (a long random-looking string, accepted by
its digit mix or by a context word before it) and ``national_phone`` (9-15 digits without a plus sign, only with a context word).

Patterns are not run over whole texts. A span can only lie inside a run of characters that its pattern allows, so runs
with an ``@``, a plus sign, or enough digits and dots are located on the batch's bytes first.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rarespan.llm import textkit as T

# The kinds in their order, the base patterns and the words that raise a score.
KINDS = ("email", "ip", "card", "phone", "iban", "secret", "national_phone")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])[0-9]++(\.[0-9]++)(\.[0-9]++)(\.[0-9]++)")
_CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_IBAN = re.compile(r"\b[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?\b")
_SECRET = re.compile(r"(?<![A-Za-z0-9_])[A-Za-z0-9_]{20,}(?![A-Za-z0-9_])")
_NATIONAL = re.compile(r"(?<![0-9+(])\(?[0-9][\x20().0-9-]{7,}[0-9]")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_CONTEXT = {
    "email": ("mail", "contact", "write to", "address"),
    "ip": ("ip", "host", "server", "login", "address"),
    "card": ("card", "visa", "credit", "payment", "carte", "karte", "tarjeta"),
    "phone": ("phone", "call", "tel", "mobile", "fax", "telefon", "téléphone", "teléfono"),
    "iban": ("iban", "account", "bank", "konto", "compte", "cuenta"),
    "secret": ("token", "secret", "password", "passwd", "api_key", "apikey", "api key", "key =", "key="),
    "national_phone": ("phone", "call", "tel", "mobile", "fax", "telefon", "téléphone", "teléfono"),
}
WINDOW = 40
_PRIOR = {"email": 0.9, "ip": 0.7, "card": 0.8, "phone": 0.8, "iban": 0.9, "secret": 0.3, "national_phone": 0.3}


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if i % 2:
            d = 2 * d - 9 * (d > 4)
        total += d
    return total % 10 == 0


def mod97(iban: str) -> bool:
    code = iban.replace(" ", "")
    number = "".join(str(int(c, 36)) for c in code[4:] + code[:4])
    return 15 <= len(code) <= 34 and int(number) % 97 == 1


def _digits(s: str) -> str:
    return "".join(c for c in s if "0" <= c <= "9")


@dataclass
class Span:
    kind: str
    start: int
    end: int
    score: float


def _class(chars: bytes) -> np.ndarray:
    out = np.zeros(256, bool)
    out[list(chars)] = True
    return out


_ALNUM = bytes(range(48, 58)) + bytes(range(65, 91)) + bytes(range(97, 123))
_MAIL = _class(_ALNUM + b"._%+-@")
_DOTTED = _class(bytes(range(48, 58)) + b".")
_NUMBER = _class(bytes(range(48, 58)) + b" ().-+")
_TOKEN = _class(_ALNUM + b"_ ")
_WORDY = _class(_ALNUM + b"_")
_IS_DIGIT = _class(bytes(range(48, 58)))


def _runs(inside: np.ndarray, heads: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the maximal runs of True, cut at text starts."""
    before = np.empty_like(inside)
    before[0] = False
    before[1:] = inside[:-1]
    before[heads] = False
    after = np.empty_like(inside)
    after[-1] = False
    after[:-1] = inside[1:]
    after[heads[heads > 0] - 1] = False
    return np.flatnonzero(inside & ~before), np.flatnonzero(inside & ~after) + 1


def _count(flags: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    at = np.flatnonzero(flags)
    return np.searchsorted(at, end) - np.searchsorted(at, start)


def _base(kind: str, text: str) -> Iterator[tuple[int, int]]:
    if kind == "email":
        done, at = 0, text.find("@")
        while at >= 0:  # the local part reaches back as far as it can, but not into the match or the @ before
            start = at
            while start > done and text[start - 1] in _LOCAL:
                start -= 1
            m = _DOMAIN.match(text, at + 1) if start < at else None
            if m:
                yield start, m.end()
            done = m.end() if m else at + 1
            at = text.find("@", done)
    elif kind == "ip":
        for m in _IP.finditer(text):
            if all(len(p) <= 3 and int(p or "0") <= 255 for p in (p.lstrip("0") for p in m[0].split("."))):
                yield m.span()
    elif kind == "card":
        for m in _CARD.finditer(text):
            d = _digits(m[0])
            if 12 <= len(d) <= 19 and luhn(d):
                yield m.span()
    elif kind == "phone":
        for m in _PHONE.finditer(text):
            if 9 <= len(_digits(m[0])) <= 15:
                yield m.span()


def _added(kind: str, text: str) -> Iterator[tuple[int, int]]:
    if kind == "iban":
        for m in _IBAN.finditer(text):
            if mod97(m[0]):
                yield m.span()
    elif kind == "secret":
        for m in _SECRET.finditer(text):
            if any("0" <= c <= "9" for c in m[0]) and any(not "0" <= c <= "9" for c in m[0]):
                yield m.span()
    elif kind == "national_phone":
        for m in _NATIONAL.finditer(text):
            if 9 <= len(_digits(m[0])) <= 15:
                yield m.span()


def _score(kind: str, before: str, span: str) -> float:
    low = before.lower()
    near = any(w in low for w in _CONTEXT[kind])
    score = _PRIOR[kind] + (0.35 if near else 0.0)
    if kind == "secret":
        digits = sum("0" <= c <= "9" for c in span)
        turns = sum((a in "0123456789") != (b in "0123456789") for a, b in zip(span, span[1:], strict=False))
        score += 0.35 if turns >= len(span) // 4 and digits >= len(span) // 4 else 0.0
    return min(1.0, score)


def scan(raw: np.ndarray, offsets: np.ndarray, threshold: float = 0.6) -> list[list[Span]]:
    """Accepted spans of each text, in code points, ordered by start and then by kind."""
    n = len(offsets) - 1
    out: list[list[Span]] = [[] for _ in range(n)]
    if len(raw) == 0:
        return out
    heads = offsets[:-1][offsets[:-1] < offsets[1:]]
    digit = _IS_DIGIT[raw]
    jobs: list[tuple[str, np.ndarray, np.ndarray]] = []
    at = raw == 0x40
    if at.any():
        s, e = _runs(_MAIL[raw], heads)
        hit = _count(at, s, e) > 0
        jobs.append(("email", s[hit], e[hit]))
    if digit.any():
        s, e = _runs(_DOTTED[raw], heads)
        hit = (_count(raw == 0x2E, s, e) >= 3) & (_count(digit, s, e) >= 4)
        jobs.append(("ip", s[hit], e[hit]))
        s, e = _runs(_NUMBER[raw], heads)
        count = _count(digit, s, e)
        hit = count >= 9
        plus = _count(raw == 0x2B, s, e) > 0
        jobs.append(("phone", s[hit & plus], e[hit & plus]))
        jobs.append(("national_phone", s[hit], e[hit]))
        jobs.append(("card", s[count >= 12], e[count >= 12]))
        s, e = _runs(_WORDY[raw], heads)
        hit = (e - s >= 20) & (_count(digit, s, e) >= 1)
        jobs.append(("secret", s[hit], e[hit]))
        upper = (raw >= 65) & (raw <= 90)
        two = np.zeros(len(raw), bool)
        if len(raw) > 14:
            two[:-3] = upper[:-3] & upper[1:-2] & digit[2:-1] & digit[3:]
        if two.any():
            s, e = _runs(_TOKEN[raw], heads)
            hit = (_count(two, s, e) > 0) & (_count(digit, s, e) >= 8)
            jobs.append(("iban", s[hit], e[hit]))
    inner = None
    found: dict[int, list[tuple[int, int, str, int, int]]] = {}
    for kind, s, e in jobs:
        doc = np.searchsorted(offsets, s, "right") - 1
        for i, j, d in zip(s.tolist(), e.tolist(), doc.tolist(), strict=True):
            text = raw[i:j].tobytes().decode()
            for a, b in (_base if kind in KINDS[:4] else _added)(kind, text):
                found.setdefault(d, []).append((i + a, KINDS.index(kind), kind, i + b, 0))
    for d, spans in found.items():
        if inner is None:
            inner = np.concatenate(([0], np.cumsum((raw & 0xC0) != 0x80)))
        origin = inner[offsets[d]]
        taken: list[tuple[int, int]] = [(a, b) for a, k, _, b, _ in spans if k < 4]
        for a, k, kind, b, _ in sorted(spans):
            context = raw[max(offsets[d], a - WINDOW) : a].tobytes().decode("utf-8", "ignore")
            score = _score(kind, context, raw[a:b].tobytes().decode())
            if k >= 4:
                if score < threshold or any(a < y and x < b for x, y in taken):
                    continue
                taken.append((a, b))
            out[d].append(Span(kind, int(inner[a] - origin), int(inner[b] - origin), score))
    return out


def _joined(spans: list[Span]) -> str:
    return ",".join(f"{s.kind}:{s.start}:{s.end}" for s in spans)


def find_pii(docs: DataFrame, threshold: float = 0.6, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: doc_id and its spans, an array of (kind, start, end, score); code points, end exclusive.

    Null and empty texts have no spans; every row of a repeated id is scanned for itself; other columns are ignored.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64()), ("score", pa.float64())]))
        for b in batches:
            raw, offsets = T.text_buffers(b.column(1))
            rows: list[list[dict]] = []
            for lo, hi in T.blocks(offsets):
                at = offsets[lo : hi + 1]
                rows += [[vars(s) for s in spans] for spans in scan(raw[at[0] : at[-1]], at - at[0], threshold)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(rows, kind)], ["doc_id", "spans"])

    schema = "doc_id long, spans array<struct<kind:string,start:long,end:long,score:double>>"
    return docs.select(F.col(id_col).cast("long"), F.col(text_col)).mapInArrow(run, schema)


def digest(found: DataFrame) -> DataFrame:
    """The counts, the hash of the base spans and all spans as one string, from the output of ``find_pii``."""
    base = F.filter("spans", lambda s: s["kind"].isin(*KINDS[:4]))
    text = lambda spans: F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")
    count = lambda kind: F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    counts = [count(kind) for kind in KINDS[:4]]
    return found.select("doc_id", *counts, F.sha2(text(base), 256).alias("base_sha256"), text(F.col("spans")).alias("spans"))


def redact_text(text: str, spans: list[Span]) -> str:
    """The text with each accepted span replaced by its kind in angle brackets; of overlapping spans the earliest, then longest, wins."""
    out, at = [], 0
    for s in sorted(spans, key=lambda s: (s.start, -s.end)):
        if s.start < at:
            at = max(at, s.end)
            continue
        out += [text[at : s.start], f"<{s.kind}>"]
        at = s.end
    return "".join(out) + text[at:]


def redact(docs: DataFrame, threshold: float = 0.6, text_col: str = "text") -> DataFrame:
    """The documents with personal data masked in ``text``; every other column and row is kept as it is, nulls too."""
    place = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            raw, offsets = T.text_buffers(b.column(place))
            changed: dict[int, str] = {}
            for lo, hi in T.blocks(offsets):
                at = offsets[lo : hi + 1]
                for i, spans in enumerate(scan(raw[at[0] : at[-1]], at - at[0], threshold)):
                    if spans:
                        changed[lo + i] = redact_text(raw[offsets[lo + i] : offsets[lo + i + 1]].tobytes().decode(), spans)
            if changed:
                texts = b.column(place).to_pylist()
                for i, t in changed.items():
                    texts[i] = t
                b = b.set_column(place, b.schema.field(place), pa.array(texts, b.schema.field(place).type))
            yield b

    return docs.mapInArrow(run, docs.schema)
