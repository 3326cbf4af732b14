"""Personal data in text: regular expressions propose, checksums confirm, context words weigh.

Base kinds (their spans are fixed by the patterns and checks alone): email; ip, parts at most 255; card, 13 to 19 digits
that pass Luhn; phone, 9 to 15 digits. Each kind takes leftmost matches that do not overlap; a match that fails its
check is dropped and not tried again from a later place.

Added kinds go through a score: a prior for the pattern, plus what a passed checksum adds, plus or minus what words
within ``window`` code points say; spans that reach ``threshold`` are kept.

* iban: country, two check digits, 11 to 30 more; mod-97 must be 1. What follows may look like a part of the number, so every
  end between groups is tried, that at the country's length first, then from the longest.
* account: 8 to 12 digits near a word such as "account" or "konto".
* ssn: three-two-four digits that the numbering allows; a context word, or no sign of the contrary, is needed.
* secret: ``name=value`` or ``name: value`` for names such as password or token, the value as long as it runs, and well-known key prefixes.

All searches take time linear in the text: runs of pattern characters are found once and looked at from the inside, so
very long runs of letters or digits cost no more than others.

Defined cases: null text is an empty text without spans; rows that repeat are each scanned; an empty table gives an empty
result; offsets are code points, ends exclusive; columns of any other name pass through ``redact``.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from taskmesh.llm.words import lean, numbered
from taskmesh.sources import load

BASE = ("email", "ip", "card", "phone")
KINDS = (*BASE, "iban", "account", "ssn", "secret")

_LOCAL = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-"
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_DIGITS_AND_DOTS = re.compile(r"[0-9][0-9.]*")
_CARD = re.compile(r"[0-9](?:[ -]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_NOT_DIGIT = re.compile(r"[^0-9]+")
_ANY_DIGIT = re.compile(r"[0-9]")

_IBAN = re.compile(r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]){11,30}")
_ALNUM = re.compile(r"[A-Za-z0-9]")
_IBAN_LENGTHS = {
    **dict.fromkeys(("NO",), 15), **dict.fromkeys(("BE",), 16), **dict.fromkeys(("DK", "FO", "FI", "GL", "NL"), 18), **dict.fromkeys(("MK", "SI"), 19),
    **dict.fromkeys(("AT", "BA", "EE", "KZ", "XK", "LT", "LU"), 20), **dict.fromkeys(("HR", "LV", "LI", "CH"), 21),
    **dict.fromkeys(("BH", "BG", "CR", "GE", "DE", "IE", "ME", "RS", "GB", "VA"), 22), **dict.fromkeys(("TL", "GI", "IQ", "IL", "AE"), 23),
    **dict.fromkeys(("AD", "CZ", "MD", "PK", "RO", "SA", "SK", "ES", "SE", "TN", "VG"), 24), **dict.fromkeys(("PT",), 25), **dict.fromkeys(("IS", "TR"), 26),
    **dict.fromkeys(("FR", "GR", "IT", "MR", "MC", "SM"), 27), **dict.fromkeys(("AL", "AZ", "BY", "CY", "DO", "GT", "HU", "LB", "PL"), 28),
    **dict.fromkeys(("BR", "PS", "QA", "UA"), 29), **dict.fromkeys(("JO", "KW", "MU"), 30), **dict.fromkeys(("MT", "SC"), 31), **dict.fromkeys(("LC",), 32),
}
_ACCOUNT = re.compile(r"(?<![\w.+-])[0-9]{8,12}(?![\w.-])")
_SSN = re.compile(r"(?<![\w.-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![\w-])")
_SECRET = re.compile(r"(?:password|passwd|pwd|secret|token|api[_-]?key)\s{0,3}[=:]\s{0,3}[\"']?([^\s\"',;]{6,})", re.I)
_KEY = re.compile(r"(?<![A-Za-z0-9])(?:AKIA[A-Z0-9]{16}|gh[pousr]_[A-Za-z0-9]{36})(?![A-Za-z0-9])")

# Context words: what they add to the score of a kind when they stand near.
CONTEXT = {
    "iban": {"iban": 0.3, "bank": 0.2, "konto": 0.2, "compte": 0.2, "cuenta": 0.2},
    "account": {"account": 0.5, "acct": 0.5, "konto": 0.5, "compte": 0.5, "cuenta": 0.5, "order": -0.3, "invoice": -0.3},
    "ssn": {"ssn": 0.5, "social": 0.3, "security": 0.3, "part": -0.3, "model": -0.3},
    "secret": {"example": -0.2, "sample": -0.2, "placeholder": -0.4},
}
PRIOR = {"iban": 0.3, "account": 0.2, "ssn": 0.5, "secret": 0.8}
CHECKED = {"iban": 0.5}
_WORD = re.compile(r"[^\W\d_]+")


def luhn(digits: str) -> bool:
    """The check digit of payment cards."""
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if i % 2:
            d = d * 2 - 9 * (d > 4)
        total += d
    return total % 10 == 0


def mod97(code: str) -> bool:
    """The check digits of bank account numbers with a country code."""
    moved = code[4:] + code[:4]
    return int("".join(str(int(c, 36)) for c in moved)) % 97 == 1


def ibans(text: str) -> list[tuple[int, int]]:
    out, m = [], _IBAN.search(text)
    while m:
        start, run = m.start(), m.group()
        ends = [k for k in range(len(run), 14, -1) if run[k - 1] != " " and not _ALNUM.match(text, start + k)]
        codes = [(k, run[:k].replace(" ", "")) for k in ends]
        usual = _IBAN_LENGTHS.get(run[:2])
        codes.sort(key=lambda c: len(c[1]) != usual)
        end = next((k for k, code in codes if len(code) >= 15 and mod97(code)), None)
        if end is not None:
            out.append((start, start + end))
        m = _IBAN.search(text, start + (end or 1))
    return out


def emails(text: str) -> list[tuple[int, int]]:
    """Each "@" has one run of local characters before it, so a match starts where that run does, or where the last match ended."""
    out, done, before = [], 0, 0
    at = text.find("@")
    while at >= 0:
        low = max(done, before)
        run = text[low:at]
        start = low + len(run.rstrip(_LOCAL))
        if start < at and (m := _DOMAIN.match(text, at + 1)):
            out.append((start, m.end()))
            done = m.end()
        before = at + 1
        at = text.find("@", at + 1)
    return out


def addresses(text: str) -> list[tuple[int, int]]:
    """Four groups of digits joined by single dots, leftmost first within each run of digits and dots."""
    out = []
    for m in _DIGITS_AND_DOTS.finditer(text):
        run = m.group()
        if run.count(".") < 3:
            continue
        groups, place = [], m.start()
        for g in run.split("."):
            groups.append((g, place))
            place += len(g) + 1
        i = 0
        while i + 3 < len(groups):
            four = groups[i : i + 4]
            if all(g for g, _ in four):
                if all(len(g.lstrip("0")) <= 3 and int(g.lstrip("0") or "0") <= 255 for g, _ in four):
                    out.append((four[0][1], four[3][1] + len(four[3][0])))
                i += 4
            else:
                i += 1
    return out


def cards(text: str) -> list[tuple[int, int]]:
    out = []
    for m in _CARD.finditer(text):
        if m.end() - m.start() >= 13:
            digits = _NOT_DIGIT.sub("", m.group())
            if 13 <= len(digits) <= 19 and luhn(digits):
                out.append(m.span())
    return out


def phones(text: str) -> list[tuple[int, int]]:
    return [m.span() for m in _PHONE.finditer(text) if 9 <= len(_NOT_DIGIT.sub("", m.group())) <= 15]


def context_score(text: str, kind: str, start: int, end: int, window: int) -> float:
    """What the words near a span add to its score; a word counts once."""
    near = f"{text[max(0, start - window):start]} {text[end:end + window]}".lower()
    words = CONTEXT[kind]
    return sum(words[w] for w in {*_WORD.findall(near)} & words.keys())


def added(text: str, window: int = 48, threshold: float = 0.6) -> list[tuple[str, int, int, float]]:
    """Spans of the added kinds, with their scores."""
    proposed: list[tuple[str, int, int, bool]] = []
    if _ANY_DIGIT.search(text):
        proposed += [("iban", *span, True) for span in ibans(text)]
        proposed += [("account", *m.span(), False) for m in _ACCOUNT.finditer(text)]
        for m in _SSN.finditer(text):
            area, group, serial = m.group().split("-")
            if area not in ("000", "666") and area < "900" and group != "00" and serial != "0000":
                proposed.append(("ssn", *m.span(), False))
    if "=" in text or ":" in text:
        proposed += [("secret", *m.span(1), False) for m in _SECRET.finditer(text)]
    proposed += [("secret", *m.span(), False) for m in _KEY.finditer(text)]
    out, seen = [], set()
    for kind, start, end, sure in proposed:
        score = PRIOR[kind] + CHECKED.get(kind, 0.0) * sure + context_score(text, kind, start, end, window)
        need = threshold if kind != "ssn" else threshold - 0.1
        if score >= need - 1e-9 and (kind, start) not in seen:
            seen.add((kind, start))
            out.append((kind, start, end, round(min(1.0, score), 4)))
    return sorted(out, key=lambda s: (KINDS.index(s[0]), s[1]))


def find_spans(text: str, window: int = 48, threshold: float = 0.6) -> list[tuple[str, int, int, float]]:
    """Every span of a text as (kind, start, end, score), by kind as listed in ``KINDS``, then by start."""
    base: list[tuple[str, int, int, float]] = []
    if "@" in text:
        base += [("email", s, e, 1.0) for s, e in emails(text)]
    if _ANY_DIGIT.search(text):
        base += [("ip", s, e, 1.0) for s, e in addresses(text)]
        base += [("card", s, e, 1.0) for s, e in cards(text)]
        base += [("phone", s, e, 1.0) for s, e in phones(text)] if "+" in text else []
    return base + added(text, window, threshold)


def masked(text: str, spans: list[tuple[str, int, int, float]]) -> str:
    """The text with each span, or each group of spans that overlap, replaced by a mark of the first one's kind."""
    out, place = [], 0
    merged: list[list] = []
    for kind, start, end, _ in sorted(spans, key=lambda s: (s[1], -s[2])):
        if merged and start < merged[-1][2]:
            merged[-1][2] = max(merged[-1][2], end)
        else:
            merged.append([kind, start, end])
    for kind, start, end in merged:
        out += [text[place:start], f"[{kind.upper()}]"]
        place = end
    return "".join([*out, text[place:]])


def _joined(spans: list[tuple[str, int, int, float]]) -> str:
    return ",".join(f"{k}:{s}:{e}" for k, s, e, _ in spans)


def scan(docs: DataFrame, window: int = 48, threshold: float = 0.6) -> DataFrame:
    """doc_id and its spans: an array of kind, start, end, score."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = [
                [{"kind": k, "start": s, "end": e, "score": x} for k, s, e, x in find_spans(t or "", window, threshold)]
                for t in b.column("text").to_pylist()
            ]
            yield pa.RecordBatch.from_arrays(
                [b.column("doc_id"), pa.array(found, pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64()), ("score", pa.float64())])))],
                ["doc_id", "spans"],
            )

    return docs.select("doc_id", "text").mapInArrow(lean(run), "doc_id long, spans array<struct<kind:string,start:long,end:long,score:double>>")


def redact(docs: DataFrame, window: int = 48, threshold: float = 0.6) -> DataFrame:
    """The same rows and columns, with marks in place of personal data; n_chars, where there is one, follows the text."""
    plain, names = numbered(docs)
    text_at, chars_at = names.index("text"), names.index("n_chars") if "n_chars" in names else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = [None if t is None else masked(t, find_spans(t, window, threshold)) for t in b.column(text_at).to_pylist()]
            columns = [*b.columns]
            columns[text_at] = pa.array(texts, pa.string())
            if chars_at is not None:
                columns[chars_at] = pa.array([None if t is None else len(t) for t in texts], pa.int64()).cast(b.column(chars_at).type)
            yield pa.RecordBatch.from_arrays(columns, b.schema.names)

    return plain.mapInArrow(lean(run), plain.schema).toDF(*names)


def op10_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            counts: dict[str, list[int]] = {k: [] for k in BASE}
            digests, everything = [], []
            for text in b.column("text").to_pylist():
                spans = find_spans(text or "")
                base = [s for s in spans if s[0] in BASE]
                for k in BASE:
                    counts[k].append(sum(s[0] == k for s in base))
                digests.append(hashlib.sha256(_joined(base).encode()).hexdigest())
                everything.append(_joined(spans))
            yield pa.RecordBatch.from_arrays(
                [b.column("doc_id"), *[pa.array(counts[k], pa.int64()) for k in BASE], pa.array(digests, pa.string()), pa.array(everything, pa.string())],
                ["doc_id", *[f"n_{k}" for k in BASE], "base_sha256", "spans"],
            )

    docs = load(spark, sf_dir, "documents", ["doc_id", "text"])
    return docs.mapInArrow(lean(run), "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string")
