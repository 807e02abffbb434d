"""Personal data: exact base patterns plus offset-preserving deobfuscation.

The base patterns run on the text as it is. Transducers then rewrite disguises (look-alike and
full-width characters, invisible characters, spelled digits, at/dot words) into plain text while they
keep, for every piece of the result, where it came from. The same patterns run on the rewritten text;
what they find is mapped back to source positions and added where no base span of its kind holds it.
Null and empty texts have no spans. Positions are code points, end exclusive.
"""

from __future__ import annotations

import bisect
import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import DOCUMENT_COLUMNS

KINDS = ("email", "ip", "card", "phone")
Span = tuple[int, int]

# Cyrillic and Greek letters that look like Latin ones.
LOOKALIKES = {
    "а": "a", "е": "e", "о": "o", "р": "p", "с": "c", "у": "y", "х": "x", "і": "i", "ј": "j", "ѕ": "s", "ԁ": "d", "ԛ": "q", "ԝ": "w", "һ": "h",
    "А": "A", "В": "B", "Е": "E", "К": "K", "М": "M", "Н": "H", "О": "O", "Р": "P", "С": "C", "Т": "T", "Х": "X", "І": "I", "Ј": "J", "Ѕ": "S",
    "α": "a", "ο": "o", "ν": "v", "ρ": "p", "ι": "i", "κ": "k", "Α": "A", "Β": "B", "Ε": "E", "Ζ": "Z", "Η": "H", "Ι": "I", "Κ": "K", "Μ": "M",
    "Ν": "N", "Ο": "O", "Ρ": "P", "Τ": "T", "Υ": "Y", "Χ": "X", "․": ".", "。": ".", "‐": "-", "‑": "-", "‒": "-", "–": "-", "\u00a0": " ",
}
#: Code points of the zeros of decimal digit rows: Arabic-Indic, extended Arabic-Indic, Devanagari, Bengali, and mathematical.
DIGIT_ROWS = (0x660, 0x6F0, 0x966, 0x9E6, 0x1D7CE, 0x1D7D8, 0x1D7E2, 0x1D7EC, 0x1D7F6)
DIGIT_WORDS = {"zero": "0", "oh": "0", "one": "1", "two": "2", "three": "3", "four": "4", "five": "5", "six": "6", "seven": "7", "eight": "8", "nine": "9"}
#: Last labels that make words around "at" and "dot" an address rather than prose.
LAST_LABELS = frozenset("com org net edu gov mil int info biz name io co ai app dev eu uk us ca au de at ch fr es it nl be pl pt br in jp cn ru test example".split())
#: Spelled digits count as an identifier only in runs of at least so many.
MIN_SPELLED = 4

_ONE_TO_ONE = {ord(k): v for k, v in LOOKALIKES.items()}
_ONE_TO_ONE |= {c: chr(c - 0xFEE0) for c in range(0xFF01, 0xFF5F)}
_ONE_TO_ONE |= {row + d: str(d) for row in DIGIT_ROWS for d in range(10)}
_ODD = re.compile("[" + "".join(map(re.escape, map(chr, sorted(_ONE_TO_ONE)))) + "]")
_HIDDEN = re.compile("[\u00ad\u200b-\u200f\u2060\ufeff]+")
_BRACKET = re.compile(r"[ \t]?[\[({<][ \t]?(at|dot|punkt|point|punto|arroba)[ \t]?[\])}>][ \t]?", re.I)
_WORDY = re.compile(
    r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]+((?:[ \t]+(?:at|arroba)[ \t]+)|@)[A-Za-z0-9-]+(?:(?:[ \t]+(?:dot|punto|point|punkt)[ \t]+|\.)[A-Za-z0-9-]+)+", re.I
)
_WORD_AT = re.compile(r"[ \t]+(?:at|arroba)[ \t]+", re.I)
_WORD_DOT = re.compile(r"[ \t]+(?:dot|punto|point|punkt)[ \t]+", re.I)
_DIGIT = "(?:" + "|".join(DIGIT_WORDS) + ")"
_SPELLED = re.compile(rf"(?<![A-Za-z0-9])(?:plus[ -])?{_DIGIT}(?:[ ,-]{{1,2}}(?:{_DIGIT}|dot|point))+(?![A-Za-z0-9])", re.I)
_TOKEN = re.compile(r"[a-z]+", re.I)

_LOCAL = re.compile(r"[A-Za-z0-9._%+-]")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_LOCAL_TAIL = re.compile(r"[A-Za-z0-9._%+-]+\Z")
_IP = re.compile(r"(?<![0-9])([0-9]++)\.([0-9]++)\.([0-9]++)\.([0-9]++)")
_CARD = re.compile(r"[0-9](?:[ -]?[0-9])++")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_HAS_DIGIT = re.compile(r"[0-9]")


def _local_start(text: str, at: int, least: int) -> int:
    """Where the run of local-part characters before ``at`` begins, looked up in growing windows."""
    width = 64
    while True:
        lo = max(least, at - width)
        m = _LOCAL_TAIL.search(text[lo:at])
        if m is None:
            return at
        if m.start() > 0 or lo == least:
            return lo + m.start()
        width *= 8


def emails(text: str) -> list[Span]:
    """Leftmost matches found from each @ outwards: the same matches as the pattern's scan, in linear time."""
    out, end, at = [], 0, text.find("@")
    while at >= 0:
        start = _local_start(text, at, end)
        m = _DOMAIN.match(text, at + 1) if start < at else None
        if m:
            out.append((start, m.end()))
            end = m.end()
        at = text.find("@", max(at + 1, end))
    return out


def _small(part: str) -> bool:
    part = part.lstrip("0")
    return len(part) < 3 or len(part) == 3 and part <= "255"


def ips(text: str) -> list[Span]:
    return [m.span() for m in _IP.finditer(text) if all(map(_small, m.groups()))]


def luhn(digits: str) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = int(c) * (1 + k % 2)
        total += d - 9 * (d > 9)
    return total % 10 == 0


def cards(text: str) -> list[Span]:
    out = []
    for m in _CARD.finditer(text):
        if m.end() - m.start() <= 37:
            digits = m[0].replace(" ", "").replace("-", "")
            if 16 <= len(digits) <= 19 and luhn(digits):
                out.append(m.span())
    return out


def phones(text: str) -> list[Span]:
    if "+" not in text:
        return []
    return [m.span() for m in _PHONE.finditer(text) if 8 <= sum(c in "0123456789" for c in m[0]) <= 15]


def base_spans(text: str) -> dict[str, list[Span]]:
    if not _HAS_DIGIT.search(text):
        return {"email": emails(text), "ip": [], "card": [], "phone": []}
    return {"email": emails(text), "ip": ips(text), "card": cards(text), "phone": phones(text)}


class Rewritten:
    """A text and, for each stretch of it, the stretch of the source that it came from."""

    def __init__(self, text: str):
        self.text, self.starts, self.pieces = text, [0], [(0, len(text), 0, len(text))]
        self.changed: list[Span] = []

    def apply(self, edits: list[tuple[int, int, str]]) -> None:
        """Replace stretches (start, end, by) of the current text, which are in order and apart."""
        if not edits:
            return
        pieces, parts, at, size = [], [], 0, 0

        def copy(a: int, b: int) -> None:
            nonlocal size
            k = bisect.bisect_right(self.starts, a) - 1
            while a < b:
                n0, n1, s0, s1 = self.pieces[k]
                if n1 <= a:
                    k += 1
                    continue
                e = min(b, n1)
                if n1 - n0 == s1 - s0:
                    pieces.append((size, size + e - a, s0 + a - n0, s0 + e - n0))
                else:
                    pieces.append((size, size + e - a, s0, s1))
                parts.append(self.text[a:e])
                size += e - a
                a = e
                k += 1

        for a, b, by in edits:
            copy(at, a)
            s0, s1 = self.source(a, b)
            self.changed.append((s0, s1))
            if by:
                pieces.append((size, size + len(by), s0, s1))
                parts.append(by)
                size += len(by)
            at = b
        copy(at, len(self.text))
        self.text, self.pieces = "".join(parts), pieces
        self.starts = [p[0] for p in pieces]

    def source(self, a: int, b: int) -> Span:
        """The source stretch of the current stretch [a, b), b > a."""
        i = bisect.bisect_right(self.starts, a) - 1
        j = bisect.bisect_right(self.starts, b - 1) - 1
        n0, n1, s0, s1 = self.pieces[i]
        start = s0 + a - n0 if n1 - n0 == s1 - s0 else s0
        n0, n1, s0, s1 = self.pieces[j]
        return start, (s0 + b - n0 if n1 - n0 == s1 - s0 else s1)


def _spelled(m: re.Match) -> str | None:
    tokens = [t.lower() for t in _TOKEN.findall(m[0])]
    while tokens and tokens[-1] in ("dot", "point"):
        tokens.pop()
    if sum(t in DIGIT_WORDS for t in tokens) < MIN_SPELLED:
        return None
    return "".join("+" if t == "plus" else "." if t in ("dot", "point") else DIGIT_WORDS[t] for t in tokens)


def rewrite(text: str) -> Rewritten | None:
    """The text without its disguises, or None if it has none."""
    r = Rewritten(text)
    touched = False
    if _HIDDEN.search(text):
        r.apply([(m.start(), m.end(), "") for m in _HIDDEN.finditer(text)])
        touched = True
    if _ODD.search(r.text):
        r.changed += [r.source(m.start(), m.end()) for m in _ODD.finditer(r.text)]
        r.text = r.text.translate(_ONE_TO_ONE)
        touched = True
    if any(x in r.text for x in "[({<"):
        edits = [(m.start(), m.end(), "@" if m[1].lower() in ("at", "arroba") else ".") for m in _BRACKET.finditer(r.text)]
        r.apply(edits)
        touched |= bool(edits)
    low = r.text.lower()
    if any(x in low for x in (" dot ", " punto ", " point ", " punkt ")) or " at " in low or " arroba " in low:
        edits = []
        for m in _WORDY.finditer(r.text):
            dots = list(_WORD_DOT.finditer(r.text, m.end(1), m.end()))
            if dots and re.split(r"[. \t]+", m[0].lower())[-1] in LAST_LABELS:
                if m[1] != "@":
                    edits.append((m.start(1), m.end(1), "@"))
                edits += [(d.start(), d.end(), ".") for d in dots]
        r.apply(edits)
        touched |= bool(edits)
    edits = [(m.start(), m.end(), by) for m in _SPELLED.finditer(r.text) if (by := _spelled(m))]
    r.apply(edits)
    return r if touched or edits else None


def _meets(spans: list[Span], s: Span) -> bool:
    return any(a < s[1] and s[0] < b for a, b in spans)


def find(text: str | None) -> tuple[dict[str, list[Span]], dict[str, list[Span]]]:
    """Base spans and all spans by kind."""
    text = text or ""
    base = base_spans(text)
    r = rewrite(text)
    if r is None:
        return base, base
    every = {}
    for kind, found in base_spans(r.text).items():
        more = {r.source(a, b) for a, b in found}
        more = [s for s in sorted(more) if _meets(r.changed, s) and not any(a <= s[0] and s[1] <= b for a, b in base[kind])]
        every[kind] = sorted(base[kind] + more)
    return base, every


def render(spans: dict[str, list[Span]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k in KINDS for a, b in spans[k])


def detect(docs: DataFrame) -> DataFrame:
    """doc_id, the base counts, the digest of the base spans and all spans, a row per row of ``docs``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = [find(t.as_py()) for t in b.column(1)]
            counts = [pa.array([len(base[k]) for base, _ in rows], pa.int64()) for k in KINDS]
            digest = pa.array([hashlib.sha256(render(base).encode()).hexdigest() for base, _ in rows], pa.string())
            spans = pa.array([render(every) for _, every in rows], pa.string())
            yield pa.RecordBatch.from_arrays([b.column(0), *counts, digest, spans], ["doc_id", *(f"n_{k}" for k in KINDS), "base_sha256", "spans"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(
        run, "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string"
    )


def redact(text: str | None) -> str | None:
    """The text with every span replaced by its kind in angle brackets; overlapping spans merge under the first kind."""
    if not text:
        return text
    _, every = find(text)
    spans = sorted((a, -b, k) for k in KINDS for a, b in every[k])
    if not spans:
        return text
    out, at = [], 0
    for a, b, k in spans:
        if a >= at:
            out += [text[at:a], f"<{k.upper()}>"]
        at = max(at, -b)
    return "".join([*out, text[at:]])


def redact_documents(docs: DataFrame) -> DataFrame:
    """``documents`` with personal data replaced and n_chars following the new text; other columns go."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            old = b.column(1).to_pylist()
            new = [redact(t) for t in old]
            n = [len(x) if x is not None and x is not y else c for x, y, c in zip(new, old, b.column(4).to_pylist())]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(new, pa.string()), b.column(2), b.column(3), pa.array(n, pa.int64())], list(DOCUMENT_COLUMNS))

    typed = [F.col(c).cast(t) for c, t in zip(DOCUMENT_COLUMNS, ("long", "string", "string", "string", "long"))]
    return docs.select(*typed).mapInArrow(run, "doc_id long, text string, lang string, source string, n_chars long")
