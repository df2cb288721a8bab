"""Personal data in plain and disguised form, with offsets into the source text.

Plain identifiers are found in the source itself. A chain of small transducers then rewrites look-alike characters, spelled-out
digits and at/dot disguises while keeping, for every character written, the span of source it came from. Identifiers
found in the rewritten text are mapped back; those that touch no plain one of their kind are added.
"""

from __future__ import annotations

import hashlib
import re
import unicodedata
from bisect import bisect_left
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from provgraph.llm.wordkernel import batches

KINDS = ("email", "ip", "card", "phone")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_CHAIN = re.compile(r"[0-9]+(?:\.[0-9]+)*")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_DIGIT = re.compile(r"[0-9]")

Span = tuple[int, int]


def luhn(digits: str) -> bool:
    total = 0
    for i, ch in enumerate(reversed(digits)):
        d = int(ch) * (1 + i % 2)
        total += d - 9 * (d > 9)
    return total % 10 == 0


def _emails(t: str) -> list[Span]:
    """Leftmost matches, by way of each @: a local part cannot hold one, so it begins where its run of characters does."""
    out, floor, at = [], 0, t.find("@")
    while at >= 0:
        start = at
        while start > floor and t[start - 1] in _LOCAL:
            start -= 1
        m = _DOMAIN.match(t, at + 1) if start < at else None
        if m:
            out.append((start, m.end()))
        floor = m.end() if m else at + 1
        at = t.find("@", floor)
    return out


def _ips(t: str) -> list[Span]:
    """A chain of numbers joined by single dots is taken four by four."""
    out = []
    for m in _CHAIN.finditer(t):
        nums, at = m.group().split("."), m.start()
        for k in range(0, len(nums) - 3, 4):
            four = nums[k : k + 4]
            size = sum(map(len, four)) + 3
            if all(len(x.lstrip("0")) <= 3 and int(x.lstrip("0") or 0) <= 255 for x in four):
                out.append((at, at + size))
            at += size + 1
    return out


def _digits(s: str) -> str:
    return "".join(ch for ch in s if "0" <= ch <= "9")


def detect(t: str) -> dict[str, list[Span]]:
    """Spans by kind, in code points."""
    out: dict[str, list[Span]] = {k: [] for k in KINDS}
    if "@" in t:
        out["email"] = _emails(t)
    if _DIGIT.search(t):
        out["ip"] = _ips(t)
        out["card"] = [m.span() for m in _CARD.finditer(t) if 12 <= len(d := _digits(m.group())) <= 19 and luhn(d)]
        if "+" in t:
            out["phone"] = [m.span() for m in _PHONE.finditer(t) if 9 <= len(_digits(m.group())) <= 15]
    return out


class Traced:
    """A text with, for each of its characters, the source span it stands for."""

    def __init__(self, text: str, starts: list[int] | None = None, ends: list[int] | None = None):
        self.text = text
        self.starts = list(range(len(text))) if starts is None else starts
        self.ends = list(range(1, len(text) + 1)) if ends is None else ends

    def rewrite(self, edits: list[tuple[int, int, str]]) -> Traced:
        """``edits``: disjoint (start, end, replacement) in this text, ascending."""
        if not edits:
            return self
        text, starts, ends, at = [], [], [], 0
        for a, b, new in edits:
            text += [self.text[at:a], new]
            starts += self.starts[at:a] + [self.starts[a]] * len(new)
            ends += self.ends[at:a] + [self.ends[b - 1]] * len(new)
            at = b
        text.append(self.text[at:])
        return Traced("".join(text), starts + self.starts[at:], ends + self.ends[at:])

    def back(self, span: Span) -> Span:
        return self.starts[span[0]], self.ends[span[1] - 1]


# Letters of other scripts that look like Latin ones.
LOOKALIKES = {
    "а": "a", "в": "b", "е": "e", "к": "k", "м": "m", "н": "h", "о": "o", "р": "p", "с": "c", "т": "t", "у": "y", "х": "x",
    "і": "i", "ј": "j", "ѕ": "s", "һ": "h", "ԁ": "d", "ԛ": "q", "ԝ": "w", "ո": "n", "ս": "u", "օ": "o",
    "А": "A", "В": "B", "Е": "E", "К": "K", "М": "M", "Н": "H", "О": "O", "Р": "P", "С": "C", "Т": "T", "У": "Y", "Х": "X",
    "І": "I", "Ј": "J", "Ѕ": "S", "α": "a", "ε": "e", "ι": "i", "κ": "k", "ν": "v", "ο": "o", "ρ": "p", "τ": "t", "υ": "u", "χ": "x",
    "Α": "A", "Β": "B", "Ε": "E", "Ζ": "Z", "Η": "H", "Ι": "I", "Κ": "K", "Μ": "M", "Ν": "N", "Ο": "O", "Ρ": "P", "Τ": "T", "Υ": "Y", "Χ": "X",
    "ı": "i", "ɑ": "a", "ɡ": "g", "ⅼ": "l", "‐": "-", "‑": "-", "‒": "-", "–": "-", "—": "-", "−": "-", "․": ".", "。": ".", "·": ".",
}
_DROPPED = "​‌‍⁠﻿­"


def _lookalike_table() -> dict[str, str]:
    """The fixed values, and every character whose compatibility form or digit value is one printable ASCII character."""
    table = dict(LOOKALIKES)
    for c in (*range(0xA0, 0x3100), *range(0xFF00, 0xFFF0), *range(0x1D400, 0x1D800), *range(0x1F100, 0x1F16A)):
        ch = chr(c)
        d = unicodedata.digit(ch, None)
        to = str(d) if d is not None else unicodedata.normalize("NFKC", ch)
        if ch not in table and len(to) == 1 and 0x20 <= ord(to) < 0x7F:
            table[ch] = to
    return table | {ch: "" for ch in _DROPPED}


_TABLE = _lookalike_table()
_STRANGE = frozenset(_TABLE)

# Names of digits, of the at sign, the dot and the plus sign.
DIGITS = {"zero": "0", "oh": "0", "one": "1", "two": "2", "three": "3", "four": "4", "five": "5", "six": "6", "seven": "7", "eight": "8", "nine": "9"}
_AT = "at|arroba|chez"
_DOT = "dot|punto|point|punkt"
_NUM = "|".join(DIGITS)
_DOTS = frozenset(_DOT.split("|"))
_NAME = re.compile(rf"(?<![^\W_])(?:{_NUM})(?![^\W_])", re.I)
_WORD = re.compile(r"[^\W_]+")
_UNITS = re.compile(rf"(?:{_NUM}|[0-9])+", re.I)
_UNIT = re.compile(rf"({_NUM})|[0-9]+", re.I)
_PLUS = re.compile(r"(?<![^\W_])plus\s+(?=[0-9])", re.I)
_BRACKETED = re.compile(rf"[\[({{<]\s*(?:(?P<at>{_AT}|@)|(?P<dot>{_DOT}|\.))\s*[\])}}>]", re.I)
_ENTITY = re.compile(r"&(?:#0*64|#x0*40|commat);|&(?:#0*46|#x0*2e|period);", re.I)
_SIGN = re.compile(rf"@|(?<=\s)(?:{_AT})(?=\s)", re.I)
_LABEL = re.compile(r"[A-Za-z0-9-]+")
_SPACE = re.compile(r"\s*")
_SOME_AT = re.compile(rf"\s(?:{_AT})\s|\s@|@\s|@[^\s@]*\s+(?:{_DOT})\s|@[^\s@]*\s\.", re.I)
# Last parts of a domain that is spoken in full, "name at host dot com".
_LAST = "com net org edu gov mil int info biz io ai app dev co me uk de fr es it nl be ch at eu us ca au jp cn in br mx ru pl se no dk fi pt ie".split()


def _letters(x: Traced) -> Traced:
    if x.text.isascii() or _STRANGE.isdisjoint(x.text):
        return x
    return x.rewrite([(i, i + 1, _TABLE[ch]) for i, ch in enumerate(x.text) if ch in _STRANGE])


def _digit_runs(t: str) -> Iterator[list[tuple[int, int, bool]]]:
    """Longest sequences of words made of digits and their names, as (start, end, whether a spoken dot comes before it); between two
    words stand spaces with at most one hyphen, comma or full stop, or a spoken dot. One pass over the words."""
    run: list[tuple[int, int, bool]] = []
    dot, at = False, 0
    for w in _WORD.finditer(t):
        a, b = w.span()
        gap, at = t[at:a], b
        if _UNITS.fullmatch(t, a, b):
            goes_on = run and (gap.isspace() if dot else gap.strip() in ("", "-", ",", "."))
            if run and not goes_on:
                yield run
                run = []
            run.append((a, b, bool(goes_on and dot)))
            dot = False
        elif run and not dot and b - a <= 6 and gap.isspace() and t[a:b].lower() in _DOTS:
            dot = True
        elif run:
            yield run
            run, dot = [], False
    if run:
        yield run


def _numbers(x: Traced) -> Traced:
    """Names of digits as digits, in runs of four digits or more with a name that stands alone."""
    t = x.text
    if len(_NAME.findall(t)) < 3:
        return x
    edits: list[tuple[int, int, str]] = []
    for run in _digit_runs(t):
        units = [list(_UNIT.finditer(t, a, b)) for a, b, _ in run]
        if sum(1 if u[1] else u.end() - u.start() for us in units for u in us) < 4 or not any(len(us) == 1 and us[0][1] for us in units):
            continue
        for k, ((a, _, dot), us) in enumerate(zip(run, units, strict=True)):
            before = run[k - 1][1] if k else a
            if dot:
                edits.append((before, a, "."))
            elif k and "." not in t[before:a] and (units[k - 1][-1][1] or us[0][1]):
                edits.append((before, a, ""))
            edits += [(*u.span(), DIGITS[u[1].lower()]) for u in us if u[1]]
    x = x.rewrite(edits)
    return x.rewrite([(m.start(), m.end(), "+") for m in _PLUS.finditer(x.text)])


def _spaces_before(t: str, at: int, floor: int) -> int:
    while at > floor and t[at - 1].isspace():
        at -= 1
    return at


def _local_before(t: str, end: int, floor: int) -> tuple[int, list[tuple[int, int]]]:
    """Where the local part that ends at ``end`` begins (``end``: there is none), and its spoken dots with the spaces around them."""
    at = end
    while at > floor and t[at - 1] in _LOCAL:
        at -= 1
    dots: list[tuple[int, int]] = []
    while at < end and "." not in t[at : dots[-1][0] if dots else end]:  # only the first part may hold a full stop
        gap = _spaces_before(t, at, floor)
        word = gap
        while word > floor and gap - word <= 6 and t[word - 1] in _LOCAL:
            word -= 1
        left = _spaces_before(t, word, floor)
        first = left
        while first > floor and t[first - 1] in _LOCAL:
            first -= 1
        if gap == at or left == word or first == left or t[word:gap].lower() not in _DOTS:
            break
        dots.append((left, at))
        at = first
    return at, dots


def _domain_after(t: str, at: int) -> tuple[int, list[tuple[int, int, bool]]]:
    """The end of a domain of two parts or more from ``at`` (-1: there is none), and what stands between its parts: (start, end, spoken)."""
    m, gaps = _LABEL.match(t, at), []
    if not m:
        return -1, gaps
    end = m.end()
    while True:
        a = _SPACE.match(t, end).end()
        if t[a : a + 1] == ".":
            spoken, b = False, a + 1 + (t[a + 1 : a + 2].isspace())
        else:
            w = _LABEL.match(t, a, a + 7)
            b = _SPACE.match(t, w.end()).end() if w else a
            if a == end or not w or b == w.end() or w[0].lower() not in _DOTS:
                break
            spoken = True
        m = _LABEL.match(t, b)
        if not m:
            break
        gaps.append((end, b, spoken))
        end = m.end()
    return (end if gaps else -1), gaps


def _signs(x: Traced) -> Traced:
    edits, floor = [], 0
    for m in _BRACKETED.finditer(x.text):
        a, floor = _spaces_before(x.text, m.start(), floor), _SPACE.match(x.text, m.end()).end()
        edits.append((a, floor, "@" if m["at"] else "."))
    x = x.rewrite(edits)
    if "&" in x.text:
        x = x.rewrite([(m.start(), m.end(), "@" if re.search("64|40|commat", m.group(), re.I) else ".") for m in _ENTITY.finditer(x.text)])
    if not _SOME_AT.search(x.text):
        return x
    t, edits, floor = x.text, [], 0
    for m in _SIGN.finditer(t):
        if m.start() < floor:
            continue
        left, right = _spaces_before(t, m.start(), floor), _SPACE.match(t, m.end()).end()
        end, gaps = _domain_after(t, right)
        if end < 0:
            continue
        first, dots = _local_before(t, left, floor)
        spoken_at, spoken_dot = m[0] != "@", any(s for _, _, s in gaps)
        if first == left or spoken_at and not (spoken_dot and t[gaps[-1][1] : end].lower() in _LAST):
            continue  # nobody's name, or "at" between ordinary words
        if not spoken_at and not spoken_dot and right - left == 1:
            continue
        edits += [(a, b, ".") for a, b in reversed(dots)]
        edits.append((left, right, "@"))
        wide = not spoken_dot and _WIDE.fullmatch(t, *gaps[0][:2])
        edits += [(a, b, ".") for a, b, s in gaps if s or wide and _WIDE.fullmatch(t, a, b)]
        floor = end
    return x.rewrite(edits)


_WIDE = re.compile(r"\s\.\s")
_TWO_NAMES = re.compile(rf"(?:{_NUM})(?:[^a-z]+|[^a-z]+(?:{_DOT})[^a-z]+)(?:{_NUM}|[0-9])")
_BRACKET_SIGN = re.compile(rf"[\[({{<]\s*(?:{_AT}|@|{_DOT}|\.)\s*[\])}}>]|&(?:#|commat|period)")


def disguised(t: str) -> bool:
    """Whether a transducer may have anything to do. Cheap tests for parts come before the patterns."""
    if not t.isascii() and not _STRANGE.isdisjoint(t):
        return True
    low = t.lower()
    if any(ch in low for ch in "[({<&") and _BRACKET_SIGN.search(low):
        return True
    if ("@" in low or any(w in low for w in _DOT.split("|"))) and _SOME_AT.search(low):
        return True
    return sum(map(low.count, DIGITS)) >= 3 and bool(_TWO_NAMES.search(low))


def added(t: str, base: dict[str, list[Span]]) -> dict[str, list[Span]]:
    out: dict[str, list[Span]] = {k: [] for k in KINDS}
    if not disguised(t):
        return out
    x = _signs(_numbers(_letters(Traced(t))))
    if x.text == t:
        return out
    for kind, spans in detect(x.text).items():
        starts, free = [a for a, _ in base[kind]], 0  # both lists ascend and hold disjoint spans
        for a, b in map(x.back, spans):
            k = bisect_left(starts, b)
            if a >= free and not (k and base[kind][k - 1][1] > a):
                out[kind].append((a, b))
                free = b
    return out


def _text(spans: dict[str, list[Span]]) -> str:
    rows = sorted((a, i, b) for i, k in enumerate(KINDS) for a, b in spans[k])
    return ",".join(f"{KINDS[i]}:{a}:{b}" for a, i, b in rows)


def find_pii(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id_col, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_added) of each row.

    The counts and the digest are of the plain identifiers; ``spans`` has those and the disguised ones. Null text is
    empty; repeated rows are searched each on its own; other columns are not read.

    A spoken "at" is taken for a sign only if the dot is spoken too and the last part is one of ``_LAST``: "jane at example dot gr"
    and "jane at example.com" are not found.
    """

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b, texts in batches(it, "t"):
            rows = []
            for raw in texts:
                t = raw.decode("utf-8", "replace")
                base = detect(t)
                more = added(t, base)
                rows.append((*(len(base[k]) for k in KINDS), hashlib.sha256(_text(base).encode()).hexdigest(), _text({k: base[k] + more[k] for k in KINDS}), sum(map(len, more.values()))))
            cols = list(zip(*rows, strict=True))
            kinds = [pa.int64()] * 4 + [pa.string()] * 2 + [pa.int64()]
            yield pa.RecordBatch.from_arrays([b.column("i"), *(pa.array(c, k) for c, k in zip(cols, kinds, strict=True))], [id_col, *(f"n_{k}" for k in KINDS), "base_sha256", "spans", "n_added"])

    kind = df.schema[id_col].dataType.simpleString()
    return df.select(F.col(id_col).alias("i"), F.col(text_col).alias("t")).mapInArrow(run, f"`{id_col}` {kind}, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_added long")
