"""Personal data in text, with spans in code points of the source, and disguised forms found by normalising.

Four kinds, in the order email, ip, card, phone. The base pass takes the plain forms, leftmost and without
overlap per kind; a match that fails its check is dropped and not tried again.

The second pass undoes disguises. Transducers rewrite a passage and keep, for every character they write,
the source span that it came from: (1) homoglyphs, full-width and other decimal digits, and invisible
characters; (2) spelled digits, "four one five" or "double seven"; (3) "(at)", " at ", "[dot]", " dot ".
The same detectors then read the normalised passage, and what they find is mapped back to source offsets.
Only passages around a trigger are rewritten, and a found span is added if it does not overlap a base span of its
kind and if a disguise stands inside it; base spans stay as they are.

Defined cases: null text is the empty text; repeated rows are scanned each for itself; offsets count code
points, end exclusive; very long texts, and long runs of one character, cost time in proportion to their length (every pattern is
anchored and possessive); numbers of any length are read as text, never as integers.
"""

from __future__ import annotations

import bisect
import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from annspark.llm.common import sliced, texts

KINDS = ("email", "ip", "card", "phone")
Span = tuple[int, int]

# The plain forms of the four kinds.
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
# A match starts at the first digit of its run or behind an earlier match, which ends with a run; possessive, since nothing given back would match.
IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++)(?:\.[0-9]++)(?:\.[0-9]++)")
CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])++")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")

# Look-alikes of ASCII letters, one code point each.
CYRILLIC = ("асеіјорѕухвкмнтАВСЕНІЈКМОРЅТХУ", "aceijopsyxbkmhtABCEHIJKMOPSTXY")
GREEK = ("αοεικνρτυχΑΒΕΖΗΙΚΜΝΟΡΤΥΧ", "aoeiknptuxABEZHIKMNOPTYX")
SIGNS = ("＠﹫。．․＋﹢‐‑‒–－−", "@@...++------")
INVISIBLE = "­​‌‍⁠﻿"
DIGIT_WORDS = {"zero": "0", "oh": "0", "one": "1", "two": "2", "three": "3", "four": "4", "five": "5", "six": "6", "seven": "7", "eight": "8", "nine": "9"}
REPEATS = {"double": 2, "triple": 3}
MARKS = {"plus": "+", "dot": ".", "point": ".", "dash": "-", "hyphen": "-"}

#: Anchored on the bracket; white space around it is taken in by ``_bracketed``.
BRACKETED = re.compile(r"[\(\[\{<]\s*+(?:(at|@)|dot|\.)\s*+[\)\]\}>]\s*+", re.I)
_PART = r"[A-Za-z0-9_%+-]++"
# Endings that alone make "name at host dot ending" an address; none is a common word of prose.
ENDINGS = ("com", "org", "net", "edu", "gov", "mil", "int", "info", "biz", "dev", "app", "io", "ai", "co", "uk", "de", "fr", "es", "eu", "ca", "ch", "nl", "pl", "pt", "ru", "se", "dk", "fi", "cz", "gr", "hu", "ie", "jp", "cn", "kr", "br", "mx", "ar", "cl", "au", "nz", "za", "tv", "test", "example", "invalid")
#: name at host dot ending; ``worded`` asks for a known ending or other evidence, prose seldom has either.
#: Starts where a run of name characters does; every piece is possessive, since what follows it cannot stand inside it.
WORDED = re.compile(rf"(?<![A-Za-z0-9_%+-]){_PART}(?:(?:\.|\s++dot\s++){_PART}){{0,3}}(?:\s++at\s++|@)(?!(?:the|a|an|this|that)\s)[A-Za-z0-9-]++(?:(?:\.|\s++dot\s++)[A-Za-z0-9-]++){{0,3}}\s++dot\s++[A-Za-z]{{2,}}+(?![A-Za-z0-9])", re.I)
_CUE = re.compile(r"mail|contact|address", re.I)
# Each starts where its white space does, so long white space is read once.
_AT_WORD, _DOT_WORD = re.compile(r"(?<!\s)\s++at\s++", re.I), re.compile(r"(?<!\s)\s++dot\s++", re.I)
_SIGN, _HOST_DOT = re.compile(r"((?<!\s)\s++at\s++|@)", re.I), re.compile(r"\.|(?<!\s)\s++dot\s++", re.I)
_NUM = "|".join([*DIGIT_WORDS, *REPEATS])
_GAP = re.compile(r"[\s,.()-]*+")
_TOKEN = re.compile(rf"\b(?:{_NUM}|plus|dot|point|dash|hyphen)\b|[0-9]+", re.I)
_DOTS = re.compile(r"\b(?:dot|point)\b", re.I)
_HAS_NUMBER_WORD = re.compile(rf"\b(?:{'|'.join(DIGIT_WORDS)})\b", re.I)


def _homoglyphs() -> dict[int, str]:
    out = {ord(a): b for src, dst in (CYRILLIC, GREEK, SIGNS) for a, b in zip(src, dst, strict=True)}
    out |= {0xFF01 + i: chr(0x21 + i) for i in range(94) if chr(0x21 + i).isalnum() or chr(0x21 + i) in "@._%+-()"}
    return out


GLYPHS = _homoglyphs()
_GLYPH = re.compile("[" + "".join(re.escape(chr(c)) for c in GLYPHS) + INVISIBLE + r"]|(?![0-9])\d")


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if i % 2:
            d = d * 2 - 9 * (d > 4)
        total += d
    return total % 10 == 0


def _digits(s: str) -> str:
    return "".join(c for c in s if "0" <= c <= "9")


def emails(t: str) -> list[Span]:
    """Each '@' has the run of local characters before it, back to the last match, and the domain behind it."""
    out, free, at = [], 0, t.find("@")
    while at >= 0:
        i = at
        while i > free and t[i - 1] in LOCAL:
            i -= 1
        if i < at and (m := DOMAIN.match(t, at + 1)):
            out.append((i, m.end()))
            free = m.end()
        at = t.find("@", max(at + 1, free))
    return out


def ips(t: str) -> list[Span]:
    return [m.span() for m in IP.finditer(t) if all(len(q := p.lstrip("0")) <= 3 and int(q or "0") <= 255 for p in m.group().split("."))] if "." in t else []


def cards(t: str) -> list[Span]:
    return [m.span() for m in CARD.finditer(t) if m.end() - m.start() >= 16 and 16 <= len(d := _digits(m.group())) <= 19 and luhn(d)]


def phones(t: str) -> list[Span]:
    return [m.span() for m in PHONE.finditer(t) if 8 <= len(_digits(m.group())) <= 15] if "+" in t else []


DETECT = {"email": emails, "ip": ips, "card": cards, "phone": phones}
_DIGIT = re.compile("[0-9]")


def base_spans(t: str) -> dict[str, list[Span]]:
    some = _DIGIT.search(t) is not None
    return {k: f(t) if some or k == "email" else [] for k, f in DETECT.items()}


class Tape:
    """Characters with the source span of each, and whether a transducer wrote it."""

    def __init__(self, text: str, start: int):
        self.text = text
        self.lo = list(range(start, start + len(text)))
        self.hi = [i + 1 for i in self.lo]
        self.new = [False] * len(text)

    def rewrite(self, edits: list[tuple[int, int, str]]) -> None:
        """Replace [a, b) by the string; edits are in order and apart."""
        if not edits:
            return
        text, lo, hi, new, at = [], [], [], [], 0
        for a, b, put in edits:
            text.append(self.text[at:a] + put)
            lo += self.lo[at:a] + [self.lo[a]] * len(put)
            hi += self.hi[at:a] + [self.hi[b - 1]] * len(put)
            new += self.new[at:a] + [True] * len(put)
            at = b
        self.text = "".join(text) + self.text[at:]
        self.lo, self.hi, self.new = lo + self.lo[at:], hi + self.hi[at:], new + self.new[at:]


def undo_glyphs(tape: Tape) -> None:
    edits = []
    for m in _GLYPH.finditer(tape.text):
        c = m.group()
        put = "" if c in INVISIBLE else GLYPHS.get(ord(c)) or str(int(c))
        edits.append((*m.span(), put))
    tape.rewrite(edits)


def _bracketed(t: str) -> Iterator[tuple[int, int, str]]:
    """(start, end, sign) of bracketed signs with the white space around them."""
    free = 0
    for m in BRACKETED.finditer(t):
        a = m.start()
        while a > free and t[a - 1].isspace():
            a -= 1
        free = m.end()
        yield a, free, "@" if m.group(1) else "."


def undo_brackets(tape: Tape) -> None:
    tape.rewrite(list(_bracketed(tape.text)))


def worded(t: str) -> Iterator[re.Match[str]]:
    """Worded addresses: a known ending, "@", a name with dots, signs or digits, a host of several parts, or a cue before them."""
    at = 0
    while m := WORDED.search(t, at):
        name, sign, host = _SIGN.split(m.group(), maxsplit=1)
        known = host.split()[-1].lower() in ENDINGS
        if known or sign == "@" or re.search(r"[^A-Za-z]", name) or len(_HOST_DOT.findall(host)) > 1 or _CUE.search(t, max(0, m.start() - 40), m.start()):
            yield m
            at = m.end()
        else:
            at = m.start() + 1


def undo_words(tape: Tape) -> None:
    edits = []
    for w in worded(tape.text):
        found = [(*m.span(), "@") for m in _AT_WORD.finditer(tape.text, *w.span())] + [(*m.span(), ".") for m in _DOT_WORD.finditer(tape.text, *w.span())]
        edits += sorted(found)
    tape.rewrite([e for i, e in enumerate(edits) if not i or e[0] >= edits[i - 1][1]])


def _runs(t: str) -> Iterator[list[re.Match[str]]]:
    """Figures, spelled digits and signs with nothing but white space and punctuation of numbers between them. Each gap is read once."""
    run: list[re.Match[str]] = []
    for m in _TOKEN.finditer(t):
        if run and _GAP.match(t, run[-1].end()).end() < m.start():
            yield run
            run = []
        run.append(m)
    if run:
        yield run


def _telling(run: list[re.Match[str]]) -> bool:
    """Whether a run has spelled digits, or dots of an address, and the four digits that the shortest identifier has."""
    n, times, spelled, dots = 0, 1, False, 0
    for m in run:
        w = m.group().lower()
        n += times * (1 if w in DIGIT_WORDS else len(w) if w.isdigit() else 0)
        times, spelled, dots = REPEATS.get(w, 1), spelled or w in DIGIT_WORDS, dots + (w in ("dot", "point"))
    return n >= 4 and (spelled or dots >= 3)


def undo_spelled(tape: Tape) -> None:
    """Spelled digits become digits, however few of them stand among others; the detectors decide what they make.

    Spaces and commas go between two words and beside a sign, and are one space between a digit and a spelled one.
    """
    edits: list[tuple[int, int, str]] = []
    for run in _runs(tape.text):
        if not _telling(run):
            continue
        times, last, before = 1, None, ""
        for m in run:
            w = m.group().lower()
            if last is not None and re.fullmatch(r"[\s,]++", between := tape.text[last : m.start()]):
                figures = before.isdigit() + w.isdigit()
                put = between if figures == 2 else "" if not figures or w in MARKS or before in MARKS or before in REPEATS else " "
                if put != between:
                    edits.append((last, m.start(), put))
            if w in REPEATS:
                times = REPEATS[w]
                edits.append((*m.span(), ""))
            else:
                put = w * (times if len(w) == 1 else 1) if w.isdigit() else DIGIT_WORDS[w] * times if w in DIGIT_WORDS else MARKS[w]
                if put != w:
                    edits.append((*m.span(), put))
                times = 1
            last, before = m.end(), w
    tape.rewrite(edits)


def _windows(t: str, room: int = 200) -> list[Span]:
    """Passages around triggers, wide enough for any identifier, merged where they meet."""
    hits = [m.span() for m in _GLYPH.finditer(t)] if not t.isascii() else []
    if "(" in t or "[" in t or "{" in t or "<" in t:
        hits += [(a, b) for a, b, _ in _bracketed(t)]
    low = t.lower() if len(t.lower()) == len(t) else t
    if " dot " in low and (" at " in low or "@" in low):
        hits += [m.span() for m in worded(t)]
    if _HAS_NUMBER_WORD.search(t) or len(_DOTS.findall(t)) >= 3:
        hits += [(run[0].start(), run[-1].end()) for run in _runs(t) if _telling(run)]
    out: list[list[int]] = []
    for a, b in sorted(hits):
        a, b = max(0, a - room), min(len(t), b + room)
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [(a, b) for a, b in out]


def _free(span: Span, taken: list[Span]) -> bool:
    """Whether a span overlaps none of these, which are sorted and apart."""
    i = bisect.bisect_left(taken, (span[1],))
    return not i or taken[i - 1][1] <= span[0]


def disguised_spans(t: str, base: dict[str, list[Span]]) -> dict[str, list[Span]]:
    """Spans that only the normalised text shows."""
    out: dict[str, list[Span]] = {k: [] for k in KINDS}
    for a, b in _windows(t):
        tape = Tape(t[a:b], a)
        for undo in (undo_glyphs, undo_brackets, undo_words, undo_spelled):
            undo(tape)
        for kind, find in DETECT.items():
            for i, j in find(tape.text):
                if any(tape.new[i:j]) or tape.hi[j - 1] - tape.lo[i] != j - i:
                    s = (tape.lo[i], tape.hi[j - 1])
                    if _free(s, base[kind]) and (not out[kind] or out[kind][-1][1] <= s[0]):  # found from left to right
                        out[kind].append(s)
    return out


def _join(spans: dict[str, list[Span]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k in KINDS for a, b in sorted(spans[k]))


def scan(t: str) -> tuple[dict[str, list[Span]], dict[str, list[Span]]]:
    """(base spans, all spans)."""
    base = base_spans(t)
    more = disguised_spans(t, base)
    return base, {k: sorted(base[k] + more[k]) for k in KINDS}


def find(docs: DataFrame) -> DataFrame:
    """(doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_added). Counts are of base spans."""
    fields = "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_added long"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches):
            cols: list[list] = [[] for _ in range(7)]
            for t in texts(b):
                base, both = scan(t)
                row = [*(len(base[k]) for k in KINDS), hashlib.sha256(_join(base).encode()).hexdigest(), _join(both), sum(len(both[k]) - len(base[k]) for k in KINDS)]
                for c, v in zip(cols, row, strict=True):
                    c.append(v)
            types = [pa.int64()] * 4 + [pa.string()] * 2 + [pa.int64()]
            yield pa.RecordBatch.from_arrays([b.column(0).cast(pa.int64()), *(pa.array(c, t) for c, t in zip(cols, types, strict=True))], names=["doc_id", *(f"n_{k}" for k in KINDS), "base_sha256", "spans", "n_added"])

    return docs.select("doc_id", "text").mapInArrow(run, fields)


def mask(t: str) -> str:
    """Every span replaced by its kind in brackets; of overlapping spans the one that starts first, then the longer."""
    _, spans = scan(t)
    out, at = [], 0
    for a, b, k in sorted(((a, b, k) for k in KINDS for a, b in spans[k]), key=lambda s: (s[0], -s[1])):
        if a >= at:
            out += [t[at:a], f"[{k.upper()}]"]
        at = max(at, b)
    return "".join(out) + t[at:] if at else t


def redact(docs: DataFrame) -> DataFrame:
    """docs with every identifier in ``text`` masked; all columns kept, a null text stays null, n_chars follows the text."""
    schema, at = docs.schema, docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in sliced(batches):
            new = pa.array([None if t is None else mask(t) for t in b.column(at).to_pylist()], b.schema.field(at).type)
            yield pa.RecordBatch.from_arrays([new if i == at else c for i, c in enumerate(b.columns)], schema=b.schema)

    out = docs.mapInArrow(run, schema)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.length("text").cast(schema["n_chars"].dataType))
    return out
