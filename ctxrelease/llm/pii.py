"""Personal data: base patterns, and offset-preserving deobfuscation.

Base spans come from fixed patterns over the source text. The deobfuscator is a transducer: it rewrites
look-alike letters, spelled digits, invisible characters and at/dot disguises, and keeps for every written
character the source range it came from. The same patterns run on its output; a find that rests on at least one
rewrite, and that overlaps no base span of its kind, is added with its source range. Plain text is left to the
base patterns alone, so nothing is found twice.

Null texts are empty. Offsets are code points, ends exclusive. Whole texts of any length are read.
"""

from __future__ import annotations

import hashlib
import re
from bisect import bisect_right

import ahocorasick
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from .common import append_columns

KINDS = ("email", "ip", "card", "phone")
Span = tuple[int, int]

# Fixed patterns.
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_EMAIL = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
_CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_NOT_DIGIT = re.compile(r"[^0-9]")
_DIGIT = re.compile(r"[0-9]")

# Look-alikes of ASCII characters, one to one.
LOOKALIKES = {
    "а": "a", "е": "e", "о": "o", "р": "p", "с": "c", "х": "x", "у": "y", "і": "i", "ј": "j", "ѕ": "s", "һ": "h", "ԁ": "d", "ո": "n", "ѵ": "v", "ԝ": "w",
    "А": "A", "В": "B", "Е": "E", "К": "K", "М": "M", "Н": "H", "О": "O", "Р": "P", "С": "C", "Т": "T", "Х": "X", "У": "Y", "І": "I", "Ј": "J", "Ѕ": "S",
    "α": "a", "ο": "o", "ν": "v", "ρ": "p", "ι": "i", "Α": "A", "Β": "B", "Ε": "E", "Η": "H", "Ι": "I", "Κ": "K", "Μ": "M", "Ν": "N", "Ο": "O", "Ρ": "P", "Τ": "T", "Χ": "X", "Ζ": "Z",
    "․": ".", "。": ".", "‐": "-", "‑": "-", "‒": "-", "–": "-", "−": "-", " ": " ", " ": " ", " ": " ", " ": " ",
} | {chr(0xFEE0 + c): chr(c) for c in range(0x21, 0x7F)} | {chr(base + d): str(d) for base in (0x660, 0x6F0, 0x966, 0x1D7CE, 0x1D7D8, 0x1D7E2, 0x1D7EC, 0x1D7F6) for d in range(10)}
_LOOKALIKE = re.compile("[" + "".join(map(re.escape, LOOKALIKES)) + "]")
_TABLE = str.maketrans(LOOKALIKES)
#: Digits in words, in English, German, Spanish and French.
DIGIT_WORDS = {
    "zero": "0", "oh": "0", "one": "1", "two": "2", "three": "3", "four": "4", "five": "5", "six": "6", "seven": "7", "eight": "8", "nine": "9",
    "null": "0", "eins": "1", "zwei": "2", "zwo": "2", "drei": "3", "vier": "4", "fünf": "5", "fuenf": "5", "sechs": "6", "sieben": "7", "acht": "8", "neun": "9",
    "cero": "0", "uno": "1", "dos": "2", "tres": "3", "cuatro": "4", "cinco": "5", "seis": "6", "siete": "7", "ocho": "8", "nueve": "9",
    "zéro": "0", "un": "1", "deux": "2", "trois": "3", "quatre": "4", "cinq": "5", "sept": "7", "huit": "8", "neuf": "9",
}
_INVISIBLE = "​‌‍⁠﻿­"
_word = "(?:" + "|".join(sorted(DIGIT_WORDS, key=len, reverse=True)) + ")"
#: The signs in words.
_at, _dot = "(?:at|arroba|arobase)", "(?:dot|punkt|punto|point)"
#: Endings that make bare "at" and "dot" a disguise.
_ending = r"(?:com|org|net|edu|gov|io|info|biz|de|fr|es|uk|eu|us|co|at|ch|it|nl|example|test)(?![A-Za-z0-9])"
#: Any ending will do after a full "at ... dot", unless the host would be a determiner, as in prose.
_any_ending = r"[A-Za-z]{2,}(?![A-Za-z0-9])"
_prose = r"(?!(?:the|a|an|this|that|these|those|each|every|any|some|my|your|his|her|its|our|their)\s)"
_label = r"[A-Za-z0-9-]+"
_box = r"[\[({<]\s*(?P<box>at|dot|punkt|arroba|arobase|punto|point)\s*[\])}>]"
_REWRITE = re.compile(
    rf"(?P<gone>[{_INVISIBLE}]+)"
    rf"|\s*{_box}\s*"
    rf"|(?<=[A-Za-z0-9])\s+(?P<at>{_at})\s+(?=(?:{_label}(?:\s+{_dot}\s+{_label})*\s+{_dot}\s+{_ending}|{_prose}{_label}(?:\s+{_dot}\s+{_label})*\s+{_dot}\s+{_any_ending}))"
    rf"|(?<=[A-Za-z0-9])\s+(?P<dot>{_dot})\s+(?={_label})"
    rf"|(?<![A-Za-z])(?P<digits>(?:(?:plus|más|mas)[\s-]+)?(?:{_word}|[0-9]+)(?:[\s,-]+(?:{_word}|[0-9]+))+)(?![A-Za-z])",
    re.IGNORECASE,
)
# What may follow a bare "dot": before the "at" or with a known ending, and inside a host.
_DOT_AHEAD = re.compile(rf"(?:{_label}\s+(?:{_at}|{_dot})\s+)*{_ending}|(?:{_label}\s+{_dot}\s+)*{_label}\s+{_at}\s+{_prose}{_label}(?:\s+{_dot}\s+{_label})*\s+{_dot}\s+{_any_ending}", re.IGNORECASE)
_HOST_AHEAD = re.compile(rf"{_any_ending}|{_label}\s+{_dot}\s", re.IGNORECASE)
_HOST = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789.-")
# The gate, from the same parts: no text without one of these has a rewrite.
_BOX = re.compile(_box, re.IGNORECASE)
_BARE = re.compile(rf"\s{_dot}\s", re.IGNORECASE)
_RUN = re.compile(rf"(?<![A-Za-z])(?:{_word}|[0-9]+)[\s,-]+(?:{_word}|[0-9]+)[\s,-]+(?:{_word}|[0-9]+)", re.IGNORECASE)
_WIDE_SPACE = "".join(chr(c) for c in range(0x1680, 0x3001) if chr(c).isspace())
_GAP = re.compile(r"[\s,-]+(?:[0-9]+[\s,-]+)*")
#: Characters that equal ASCII letters when case is ignored.
_CASES = "ſıİ\u212a"
_DIGIT_FINDER = ahocorasick.Automaton()
for _w in DIGIT_WORDS:
    _DIGIT_FINDER.add_word(_w, len(_w))
_DIGIT_FINDER.make_automaton()
_DIGIT_PART = re.compile(rf"plus|más|mas|{_word}|[0-9]+", re.IGNORECASE)


def luhn(digits: str) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        total += d if k % 2 == 0 else (2 * d if d < 5 else 2 * d - 9)
    return total % 10 == 0


def base_spans(text: str) -> dict[str, list[Span]]:
    """Spans of the fixed patterns, leftmost and without overlap within a kind; failing finds are dropped."""
    out: dict[str, list[Span]] = {k: [] for k in KINDS}
    at, end = text.find("@"), 0
    while at >= 0:  # a find's first part is the run of its characters before the sign
        start = at
        while start > end and text[start - 1] in _LOCAL:
            start -= 1
        m = _EMAIL.match(text, start) if start < at else None
        if m:
            out["email"].append(m.span())
            end = m.end()
        at = text.find("@", max(at + 1, end))
    if not _DIGIT.search(text):
        return out
    for m in _IP.finditer(text):
        if all(len(p := x.lstrip("0")) <= 3 and int(p or "0") <= 255 for x in m.group().split(".")):
            out["ip"].append(m.span())
    for m in _CARD.finditer(text):
        if m.end() - m.start() >= 16:
            digits = _NOT_DIGIT.sub("", m.group())
            if 16 <= len(digits) <= 19 and luhn(digits):
                out["card"].append(m.span())
    if "+" in text:
        for m in _PHONE.finditer(text):
            if 8 <= len(_NOT_DIGIT.sub("", m.group())) <= 15:
                out["phone"].append(m.span())
    return out


def _disguised(text: str) -> bool:
    """Whether the transducer may rewrite something: true of every text that it rewrites."""
    if not text.isascii() and (_LOOKALIKE.search(text) or any(c in text for c in _INVISIBLE)):
        return True
    low = text.lower()
    if any(c in text for c in "[({<") and _BOX.search(text) or any(w in low for w in ("dot", "punkt", "punto", "point")) and _BARE.search(text):
        return True
    return _counted(low) if text.isascii() or not any(c in text for c in _CASES) else _RUN.search(text) is not None


def _counted(low: str) -> bool:
    """Whether three digit words follow one another, with separators and numerals between them."""
    chain, end = 0, -1
    for last, size in _DIGIT_FINDER.iter(low):
        start = last + 1 - size
        if "a" <= low[start - 1 : start] <= "z" or "a" <= low[last + 1 : last + 2] <= "z":
            continue
        if start < end:  # within a longer word found before
            continue
        chain = chain + 1 if end >= 0 and low[end : end + 1] in " \t\n\r\v\f,-\x1c\x1d\x1e\x1f\x85\xa0" + _WIDE_SPACE and _GAP.fullmatch(low, end, start) else 1
        end = last + 1
        if chain == 3:
            return True
    return False


class Transducer:
    """Rewrites a text; `source(i, j)` is the range that written characters i to j come from."""

    def __init__(self, text: str):
        even = text.translate(_TABLE) if not text.isascii() and _LOOKALIKE.search(text) else text
        self.changed: list[Span] = [m.span() for m in _LOOKALIKE.finditer(text)] if even is not text else []
        written: list[str] = []
        # starts of segments in the output and in the source; a segment copies or is one rewrite
        self.out_at: list[int] = []
        self.src: list[tuple[int, int, bool]] = []
        size = at = 0
        host = -1  # where the host begins or goes on, after the last accepted sign

        def put(piece: str, a: int, b: int, copied: bool) -> None:
            nonlocal size
            self.out_at.append(size)
            self.src.append((a, b, copied))
            written.append(piece)
            size += len(piece)

        for m in _REWRITE.finditer(even):
            a, b = m.span()
            if m["gone"]:
                new = ""
            elif m["digits"]:
                parts = _DIGIT_PART.findall(m["digits"])
                if sum(p.lower() in DIGIT_WORDS for p in parts) < 3:
                    continue
                if a > at:
                    put(even[at:a], at, a, True)
                for p in _DIGIT_PART.finditer(even, a, b):
                    got = p.group().lower()
                    put("+" if got in ("plus", "más", "mas") else DIGIT_WORDS.get(got, got), p.start(), p.end(), False)
                self.changed.append((a, b))
                at = b
                continue
            elif m["box"]:
                new = "@" if m["box"].lower() in ("at", "arroba", "arobase") else "."
            elif m["at"]:
                new = "@"
            else:
                new = "."
            if new:
                k = a
                while k > max(host, 0) and even[k - 1] in _HOST:
                    k -= 1
                inside = new == "." and k < a and (k == host or even[k - 1 : k] == "@")
                if m["dot"] and not _DOT_AHEAD.match(even, b) and not (inside and _HOST_AHEAD.match(even, b)):
                    continue
                if new == "@" or inside:
                    host = b
            if a > at:
                put(even[at:a], at, a, True)
            if new:
                put(new, a, b, False)
            self.changed.append((a, b))
            at = b
        if at < len(even):
            put(even[at:], at, len(even), True)
        self.text = "".join(written)
        self.changed.sort()

    def source(self, i: int, j: int) -> Span:
        def of(k: int, last: bool) -> int:
            s = bisect_right(self.out_at, k) - 1
            a, b, copied = self.src[s]
            if copied:
                return a + k - self.out_at[s] + last
            return b if last else a

        return of(i, False), of(j - 1, True)

    def touched(self, span: Span) -> bool:
        k = bisect_right(self.changed, (span[0], 1 << 60))
        return any(a < span[1] and b > span[0] for a, b in self.changed[max(0, k - 1) : k + 1])


def find(text: str) -> tuple[dict[str, list[Span]], dict[str, list[Span]]]:
    """Base spans, and all spans: base ones and those behind disguises."""
    base = base_spans(text)
    if not _disguised(text):
        return base, base
    seen = Transducer(text)
    if not seen.changed:
        return base, base
    full = {k: list(v) for k, v in base.items()}
    for kind, found in base_spans(seen.text).items():
        for i, j in found:
            span = seen.source(i, j)
            if seen.touched(span) and not any(a < span[1] and b > span[0] for a, b in base[kind]):
                full[kind].append(span)
        full[kind].sort()
    return base, full


def joined(spans: dict[str, list[Span]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k in KINDS for a, b in spans[k])


def redact(text: str | None) -> str | None:
    """The text with each found span replaced by its kind; overlapping spans become one."""
    if not text:
        return text
    _, spans = find(text)
    flat = sorted((a, -b, k) for k in KINDS for a, b in spans[k])
    if not flat:
        return text
    out, at = [], 0
    for a, minus_b, kind in flat:
        b = -minus_b
        if a >= at:
            out += [text[at:a], f"<{kind}>"]
        at = max(at, b)
    return "".join([*out, text[at:]])


def detect(docs: DataFrame, keep: list[str] | None = None) -> DataFrame:
    """The columns in `keep` (all, if None), counts of base spans, their digest, all spans, and how many the deobfuscator added."""
    names = [f"n_{k}" for k in KINDS]
    fields = [*(T.StructField(n, T.LongType()) for n in names), T.StructField("base_sha256", T.StringType()), T.StructField("spans", T.StringType()), T.StructField("n_added", T.LongType())]

    def work(texts: list[str | None]) -> list[list]:
        out: list[list] = [[] for _ in fields]
        for t in texts:
            base, full = find(t or "")
            for c, k in zip(out, KINDS):
                c.append(len(base[k]))
            out[4].append(hashlib.sha256(joined(base).encode()).hexdigest())
            out[5].append(joined(full))
            out[6].append(sum(map(len, full.values())) - sum(map(len, base.values())))
        return out

    return append_columns(docs, "text", fields, lambda: work, keep, "pii")


def op6_pii(spark, sf_dir: str) -> DataFrame:
    return detect(spark.read.parquet(f"{sf_dir}/documents.parquet"), ["doc_id"])
