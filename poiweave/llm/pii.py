r"""Personal data in texts: plain matches, and disguised ones found by offset-preserving normalisation.

Plain matches follow the contract's four patterns. They are found by linear scans from the characters that each
needs (``@``, digits, ``+``), which gives the same matches as a leftmost search without its backtracking.

Disguises pass through a chain of transducers, each a list of (start, end, replacement) over the source: look-alike and
full-width characters, invisible characters, ``[at]`` and ``(dot)`` in several languages, spelled digits. The
normalised text keeps where each piece came from; the same detectors run on it, and a match that touches a replaced
piece is mapped back to the source span.
"""

from __future__ import annotations

import hashlib
import re
import unicodedata
from bisect import bisect_right
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

from .textkit import byte_chunks

KINDS = ("email", "ip", "card", "phone")
Span = tuple[str, int, int]

_LOCAL = re.compile(r"[A-Za-z0-9._%+-]+\Z")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_DOTTED = re.compile(r"[0-9]+(?:\.[0-9]+){3,}")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_LOCAL_CHARS = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")

#: Letters of other scripts that look like Latin ones, and invisible characters.
LOOKALIKES = dict(zip("аеорсухіјѕһԁԛԝвкмнтАВЕКМНОРСТХІЈЅУΑΒΕΖΗΙΚΜΝΟΡΤΥΧοανικρτυχӏ", "aeopcyxijshdqwbkmhtABEKMHOPCTXIJSYABEZHIKMNOPTYXoavikptuxl", strict=True))
INVISIBLE = "­​‌‍‎‏⁠﻿"
#: Other forms of signs.
SIGNS = {"＠": "@", "﹫": "@", "。": ".", "․": ".", "．": ".", "‐": "-", "‑": "-", "–": "-", "—": "-", "−": "-", " ": " ", " ": " ", " ": " ", "＋": "+"}
#: Digits spelled in English, German, French and Spanish.
SPELLED = {
    **dict.fromkeys(("zero", "oh", "null", "zéro", "cero"), "0"),
    **dict.fromkeys(("one", "eins", "un", "uno"), "1"),
    **dict.fromkeys(("two", "zwei", "zwo", "deux", "dos"), "2"),
    **dict.fromkeys(("three", "drei", "trois", "tres"), "3"),
    **dict.fromkeys(("four", "vier", "quatre", "cuatro"), "4"),
    **dict.fromkeys(("five", "fünf", "cinq", "cinco"), "5"),
    **dict.fromkeys(("six", "sechs", "seis"), "6"),
    **dict.fromkeys(("seven", "sieben", "sept", "siete"), "7"),
    **dict.fromkeys(("eight", "acht", "huit", "ocho"), "8"),
    **dict.fromkeys(("nine", "neun", "neuf", "nueve"), "9"),
}
#: Words that start a look for spelled digits; "un" is an article far more often than a digit.
_TRIGGERS = frozenset(SPELLED) - {"un"}
_TO_SPACE = str.maketrans(",.()-", "     ")
_AT = r"(?:at|@|ät|arroba|arobase|klammeraffe)"
_DOT = r"(?:dot|punkt|point|punto|\.)"
_OPEN, _SHUT = r"\s{0,3}[\[({<]\s{0,3}", r"\s{0,3}[\])}>]\s{0,3}"
_NUMBER = "(?:" + "|".join(sorted(SPELLED, key=len, reverse=True)) + ")"
#: Top-level domains that a disguise without brackets must end with.
_TLD = r"(?:com|org|net|edu|gov|info|io|ai|app|dev|biz|me|tv|eu|at|au|be|br|ca|ch|cn|cz|de|dk|es|fi|fr|gr|hu|ie|in|it|jp|kr|mx|nl|no|nz|pl|pt|ru|se|tr|uk|us|za)\b"
#: Words before a bare "at" that make it a preposition, and words that announce an address.
_PROSE = frozenset("i you he she it we they am is are was were be been being met meet meets look looks looked looking arrive arrives arrived stay stays stayed live lives lived work works worked sit sits sat stand stands stood laugh laughed aim aimed stare stared point pointed good bad here there home open opens opened closed start starts started end ends ended not and or only even just while that this".split())
_SUBJECT = frozenset("i you he she it we they who".split())
_CUE = frozenset("mail email e-mail mailto contact write reach address to kontakt schreib an adresse courriel contacter ecrire escribe correo contacto".split())
_WORD = re.compile(r"\w+|\+|\.")
_RUN = re.compile(rf"(?<!\w)(?:(?:plus\s{{1,3}}|\+\s{{0,3}})?(?:{_NUMBER}|[0-9]+)(?!\w))(?:[\s,.()-]{{1,3}}(?:(?:dot|punkt|point|punto)\s{{1,3}})?(?:{_NUMBER}|[0-9]+)(?!\w))+")
_BETWEEN = r"[\s,.()-]{1,3}(?:(?:dot|punkt|point|punto)\s{1,3})?"
_PAIR = re.compile(rf"(?<!\w)(?:{_NUMBER}{_BETWEEN}(?:{_NUMBER}|[0-9]+)|[0-9]+{_BETWEEN}{_NUMBER})(?!\w)")
_BRACKETED_AT = re.compile(rf"{_OPEN}{_AT}{_SHUT}", re.IGNORECASE)
_BRACKETED_DOT = re.compile(rf"{_OPEN}{_DOT}{_SHUT}", re.IGNORECASE)
_BARE_DOT = re.compile(r"(?<=\w)\s{1,3}(?:dot|punkt|punto)\s{1,3}(?=\w)", re.IGNORECASE)
#: A bare "at": what stands before it, and a domain whose dots are disguised (all of them doubled disguises) or plain; it ends with a known top-level domain.
_BARE_AT = re.compile(
    rf"(?P<local>[\w.+%-]{{1,64}})(?P<at>\s{{1,3}}(?P<word>at|arroba|arobase)\s{{1,3}})(?=[\w-]{{1,63}}(?:(?P<dot>\s{{1,3}}(?:dot|punkt|punto)\s{{1,3}}|{_OPEN}{_DOT}{_SHUT})|\.)(?:[\w-]{{1,63}}(?:\s{{1,3}}(?:dot|punkt|punto)\s{{1,3}}|{_OPEN}{_DOT}{_SHUT}|\.)){{0,4}}{_TLD})",
    re.IGNORECASE,
)
_BEFORE = re.compile(r"([\w-]+)\W{1,3}\Z")


def _folded(ch: str) -> str | None:
    """The ASCII character that ``ch`` stands for, by compatibility form or digit value."""
    form = unicodedata.normalize("NFKC", ch)
    if len(form) == 1 and form.isascii() and form.isalnum():
        return form
    digit = unicodedata.digit(ch, None)
    return str(digit) if digit is not None and not ch.isascii() else None


def _lookalike_table() -> dict[str, str]:
    """By rule: all characters of the scripts' digit rows, full-width and mathematical alphabets that fold to one ASCII character."""
    ranges = ((0x0660, 0x0AF0), (0x2070, 0x208A), (0x2100, 0x2150), (0x2460, 0x2500), (0xFF10, 0xFF5B), (0x1D400, 0x1D800))
    own = {chr(c): f for a, b in ranges for c in range(a, b) if (f := _folded(chr(c))) is not None}
    return own | LOOKALIKES | SIGNS | dict.fromkeys(INVISIBLE, "")


_TABLE = _lookalike_table()
_ODD = re.compile("[" + "".join(map(re.escape, _TABLE)) + "]")


def luhn(digits: str) -> bool:
    total = 0
    for k, d in enumerate(reversed(digits)):
        n = int(d) * (1 + k % 2)
        total += n - 9 if n > 9 else n
    return total % 10 == 0


def plain_spans(text: str) -> list[Span]:
    """The contract's matches of all kinds, ordered by start, then kind."""
    found: list[Span] = []
    at, free = text.find("@"), 0
    while at >= 0:
        start = at
        while start > free and text[start - 1] in _LOCAL_CHARS:
            start -= 1
        m = _DOMAIN.match(text, at + 1) if start < at else None
        if m:
            found.append(("email", start, m.end()))
            free = m.end()
        at = text.find("@", max(at + 1, free))
    for m in _DOTTED.finditer(text):
        parts, begin = m[0].split("."), m.start()
        for k in range(0, len(parts) - 3, 4):
            four = parts[k : k + 4]
            end = begin + sum(map(len, four)) + 3
            if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in four):
                found.append(("ip", begin, end))
            begin = end + 1
    for m in _CARD.finditer(text):
        digits = re.sub(r"[\x20-]", "", m[0])
        if 14 <= len(digits) <= 19 and luhn(digits):
            found.append(("card", m.start(), m.end()))
    if "+" in text:
        for m in _PHONE.finditer(text):
            if 10 <= sum(c.isdigit() for c in m[0]) <= 15:
                found.append(("phone", m.start(), m.end()))
    return sorted(found, key=lambda s: (s[1], KINDS.index(s[0])))


class Normalised:
    """A text after replacements, with the way back to the source."""

    def __init__(self, text: str):
        self.text, self.begin, self.source, self.exact = text, [0], [(0, len(text))], [True]

    def apply(self, edits: list[tuple[int, int, str]]) -> None:
        """Replace ordered, disjoint spans of the present text."""
        if not edits:
            return
        parts, begin, source, exact, at = [], [], [], [], 0
        size = 0

        def keep(a: int, b: int) -> None:
            nonlocal size
            while a < b:
                k = bisect_right(self.begin, a) - 1
                stop = min(b, self.begin[k + 1] if k + 1 < len(self.begin) else len(self.text))
                begin.append(size)
                if self.exact[k]:
                    s = self.source[k][0] + a - self.begin[k]
                    source.append((s, s + stop - a))
                else:
                    source.append(self.source[k])
                exact.append(self.exact[k])
                parts.append(self.text[a:stop])
                size += stop - a
                a = stop

        for a, b, new in edits:
            keep(at, a)
            if new:
                begin.append(size)
                source.append((self.back(a, b)))
                exact.append(False)
                parts.append(new)
                size += len(new)
            at = b
        keep(at, len(self.text))
        self.text, self.begin, self.source, self.exact = "".join(parts), begin or [0], source or [(0, 0)], exact or [True]

    def back(self, a: int, b: int) -> tuple[int, int]:
        """Source span of the present span ``a`` to ``b`` (not empty)."""
        i, j = bisect_right(self.begin, a) - 1, bisect_right(self.begin, b - 1) - 1
        start = self.source[i][0] + (a - self.begin[i] if self.exact[i] else 0)
        end = self.source[j][0] + b - self.begin[j] if self.exact[j] else self.source[j][1]
        return start, end

    def touched(self, a: int, b: int) -> bool:
        """Does the span hold a replaced piece, or bridge a removed one?"""
        i, j = bisect_right(self.begin, a) - 1, bisect_right(self.begin, b - 1) - 1
        s, e = self.back(a, b)
        return not all(self.exact[i : j + 1]) or e - s != b - a


def _digit_edits(text: str, low: str) -> list[tuple[int, int, str]]:
    """Spelled digits in runs: words become digits, dot words dots, and what stands between them goes."""
    edits: list[tuple[int, int, str]] = []
    for run in _RUN.finditer(low):
        words = [m for m in _WORD.finditer(low, run.start(), run.end()) if m[0] != "."]
        if not any(m[0] in SPELLED for m in words):
            continue
        before = None
        for m in words:
            new = SPELLED.get(m[0]) or ("." if m[0] in ("dot", "punkt", "point", "punto") else "+" if m[0] == "plus" else None)
            gap = (before.end(), m.start()) if before else None
            if gap and gap[0] < gap[1] and (new or before_new) and "." not in text[gap[0] : gap[1]]:
                edits.append((*gap, ""))
            if new:
                edits.append((m.start(), m.end(), new))
            before, before_new = m, new
    return edits


def _bare_ats(text: str) -> list[tuple[int, int, str]]:
    """Bare "at"s that stand for the sign: the dot is disguised as well, or the local part looks like one, or an address is announced; never a preposition's place."""
    edits = []
    for m in _BARE_AT.finditer(text):
        local = m["local"]
        ahead = _BEFORE.search(text, max(0, m.start("local") - 40), m.start("local"))
        word = ahead[1].lower() if ahead else ""
        shaped = any(c in "._+%" or c.isdigit() for c in local.strip("."))
        if m["word"].lower() == "at" and not shaped and (local.lower() in _PROSE or word in _SUBJECT):
            continue
        if m["dot"] or shaped or word in _CUE:
            edits.append((*m.span("at"), "@"))
    return edits


def disguised_spans(text: str, plain: list[Span]) -> list[Span]:
    """Spans that only normalisation shows, mapped to the source; none inside a plain span of its kind."""
    n = Normalised(text)
    if not text.isascii() and not _TABLE.keys().isdisjoint(set(text)):
        n.apply([(m.start(), m.end(), _TABLE[m[0]]) for m in _ODD.finditer(text)])
    low = n.text.lower()
    if len(low) != len(n.text):  # a character whose lower case is longer
        low = "".join(c if len(c.lower()) > 1 else c.lower() for c in n.text)
    if not _TRIGGERS.isdisjoint(low.translate(_TO_SPACE).split()) and _PAIR.search(low):
        n.apply(_digit_edits(n.text, low))
        low = n.text.lower()
    if any(x in low for x in ("dot", "punkt", "point", "punto", ".]", ".)", ". )", ". ]", ".}")) or any(x in low for x in ("at]", "at)", "at }", "at}", "at >", "at>", "at ]", "at )", "@]", "@)", "@ ]", "@ )", "arroba", "arobase", "affe", " at ")):
        n.apply(_bare_ats(n.text))
        n.apply([(m.start(), m.end(), "@") for m in _BRACKETED_AT.finditer(n.text)])
        n.apply([(m.start(), m.end(), ".") for m in _BRACKETED_DOT.finditer(n.text)])
        n.apply([(m.start(), m.end(), ".") for m in _BARE_DOT.finditer(n.text)])
    if n.text == text:
        return []
    added = []
    for kind, a, b in plain_spans(n.text):
        if n.touched(a, b):
            s, e = n.back(a, b)
            if not any(k == kind and x <= s and e <= y for k, x, y in plain):
                added.append((kind, s, e))
    return added


def find_spans(text: str | None) -> tuple[list[Span], list[Span]]:
    """Plain spans and all spans of a text, each ordered by start, then kind."""
    if not text:
        return [], []
    plain = plain_spans(text)
    return plain, sorted({*plain, *disguised_spans(text, plain)}, key=lambda s: (s[1], KINDS.index(s[0]), s[2]))


def joined(spans: list[Span]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in spans)


def find_pii(documents: DataFrame) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone (plain matches), base_sha256, spans, n_added (disguised ones) for every row.

    Null and empty texts have no spans. Null ids and repeated rows get rows like others; extra columns are ignored.
    """
    kind = documents.schema["doc_id"].dataType.simpleString()
    names = ["doc_id", *(f"n_{k}" for k in KINDS), "base_sha256", "spans", "n_added"]

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in byte_chunks(whole, "text"):
                found = [find_spans(t) for t in b.column(1).to_pylist()]
                counts = [pa.array([sum(s[0] == k for s in plain) for plain, _ in found], pa.int64()) for k in KINDS]
                digests = pa.array([hashlib.sha256(joined(plain).encode()).hexdigest() for plain, _ in found], pa.string())
                spans = pa.array([joined(every) for _, every in found], pa.string())
                added = pa.array([len(every) - len(plain) for plain, every in found], pa.int64())
                yield pa.RecordBatch.from_arrays([b.column(0), *counts, digests, spans, added], names=names)

    return documents.select("doc_id", "text").mapInArrow(scan, f"doc_id {kind}, " + ", ".join(f"n_{k} long" for k in KINDS) + ", base_sha256 string, spans string, n_added long")
