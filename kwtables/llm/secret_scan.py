"""Secret scanning: fixed credential patterns plus sliding-window entropy per character class.

Candidate strings are maximal runs of one character class. A window moves over the run; character counts and
the sum of c*log2(c) are updated for the one character that leaves and the one that enters, so a run costs its
length whatever the window. What the allow-list explains is cut out of a run first (a matched stretch, or the letters and
digits around an allowed word), so that a harmless word beside a secret hides only itself. Windows at or above the class's
threshold are united into spans; spans that lack the class's mix of characters, or that lie inside a pattern's span or an
earlier class's, are suppressed. Offsets are code points, end exclusive.

Defined results: null and empty texts have no spans; texts of any length are scanned whole; repeated rows give
repeated results; other columns of the input are left alone.
"""

from __future__ import annotations

import math
import re
from bisect import bisect_right
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import ship

Span = tuple[str, int, int]

# The pattern kinds in their order, the names that announce a secret, and least lengths.
PATTERN_KINDS = ("assign", "access", "hex")
ASSIGN = re.compile(r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{32,}")
LEAST_VALUE, LEAST_ACCESS = 8, 16

#: Stretches that look random but are public by nature, and words that make the letters and digits around them harmless;
#: ``scan`` takes other lists as parameters.
ALLOWED = (
    r"(?<![0-9A-Za-z])[0-9A-Fa-f]{8}-(?:[0-9A-Fa-f]{4}-){3}[0-9A-Fa-f]{12}(?![0-9A-Za-z])",  # UUIDs
    r"(?<![0-9A-Za-z])(?i:sha(?:1|256|512)|md5)[-:=][0-9A-Za-z+/=]++",  # integrity digests
    r"(?<![0-9A-Za-z_/=+-])[0-9]++(?:[-_/=+]++[0-9]++)*+(?![0-9A-Za-z])",  # numbers, dates, rulers
)
ALLOWED_WORDS = ("example", "placeholder", "xxxx", "changeme", "abcdefghij", "qwertyuiop")
COMPONENT = re.compile("[0-9A-Za-z]*+")


@dataclass(frozen=True)
class CharClass:
    """A run of ``chars`` of ``window`` or more is measured; ``needs`` must all occur in a reported span."""

    kind: str
    chars: str
    window: int
    bits: float
    needs: tuple[str, ...]


CLASSES = (
    CharClass("entropy_hex", "0-9a-fA-F", 20, 3.0, ("[0-9]", "[a-fA-F]")),
    CharClass("entropy_base64", "A-Za-z0-9+/_=-", 24, 4.0, ("[0-9]", "[a-z]", "[A-Z]")),
)


def pattern_spans(text: str) -> list[Span]:
    """Spans of the fixed patterns by start, then kind."""
    out = [("assign", m.start(), m.end()) for m in ASSIGN.finditer(text) if m.end(1) - m.start(1) >= LEAST_VALUE]
    if "AKIA" in text:
        out += [("access", m.start(), m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= LEAST_ACCESS]
    out += [("hex", m.start(), m.end()) for m in HEX.finditer(text)]
    return sorted(out, key=lambda s: (s[1], PATTERN_KINDS.index(s[0])))


def dense_ranges(run: str, window: int, bits: float) -> list[tuple[int, int]]:
    """United ranges of the windows of ``run`` whose entropy reaches ``bits``."""
    weight = [0.0] + [c * math.log2(c) for c in range(1, window + 1)]
    counts: dict[str, int] = {}
    total, out = 0.0, []
    most = (math.log2(window) - bits) * window + 1e-9
    for i, c in enumerate(run):
        n = counts.get(c, 0)
        counts[c] = n + 1
        total += weight[n + 1] - weight[n]
        if i + 1 < window:
            continue
        start = i + 1 - window
        if total <= most:
            if out and start <= out[-1][1]:
                out[-1] = (out[-1][0], i + 1)
            else:
                out.append((start, i + 1))
        n = counts[run[start]]
        counts[run[start]] = n - 1
        total -= weight[n] - weight[n - 1]
    return out


def covered(spans: list[Span]) -> tuple[list[int], list[int]]:
    """(sorted starts, largest end up to each) of spans: one of them holds (a, b) if the largest end of those that start by a is b or more."""
    starts, ends = [], []
    for _, a, b in sorted(spans, key=lambda s: s[1]):
        starts.append(a)
        ends.append(max(b, ends[-1]) if ends else b)
    return starts, ends


class Scanner:
    def __init__(self, classes: tuple[CharClass, ...] = CLASSES, allowed: tuple[str, ...] = ALLOWED, words: tuple[str, ...] = ALLOWED_WORDS):
        self.classes = [(c, re.compile(f"[{c.chars}]{{{c.window},}}"), [re.compile(n).search for n in c.needs]) for c in classes]
        self.allowed = re.compile("|".join(f"(?:{a})" for a in allowed)) if allowed else None
        self.words = re.compile("|".join(map(re.escape, words)), re.IGNORECASE) if words else None
        self.order = {k: i for i, k in enumerate((*PATTERN_KINDS, *(c.kind for c in classes)))}

    def stretches(self, text: str, start: int, end: int) -> list[tuple[int, int]]:
        """What the allow-list leaves of a run, in order."""
        explained = [m.span() for m in self.allowed.finditer(text, start, end)] if self.allowed else []
        done = start
        for m in self.words.finditer(text, start, end) if self.words else ():
            if m.start() >= done:  # the component around a word, once
                a = m.start()
                while a > done and text[a - 1].isascii() and text[a - 1].isalnum():
                    a -= 1
                done = COMPONENT.match(text, m.end(), end).end()
                explained.append((a, done))
        out, at = [], start
        for a, b in sorted(explained):
            if a > at:
                out.append((at, a))
            at = max(at, b)
        return [*out, (at, end)] if at < end else out

    def scan(self, text: str) -> tuple[list[Span], list[Span]]:
        """(pattern spans, all spans)."""
        base = pattern_spans(text)
        found = list(base)
        for c, runs, needs in self.classes:
            starts, ends = covered(found)
            extra: list[Span] = []
            for m in runs.finditer(text):
                if not all(n(text, m.start(), m.end()) for n in needs):
                    continue
                for left, right in self.stretches(text, m.start(), m.end()):
                    if right - left < c.window:
                        continue
                    for a, b in dense_ranges(text[left:right], c.window, c.bits):
                        a, b = a + left, b + left
                        i = bisect_right(starts, a)
                        if all(n(text, a, b) for n in needs) and not (i and ends[i - 1] >= b):
                            extra.append((c.kind, a, b))
            found += extra
        return base, sorted(found, key=lambda s: (s[1], self.order[s[0]]))


def scan_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", classes: tuple[CharClass, ...] = CLASSES, allowed: tuple[str, ...] = ALLOWED, words: tuple[str, ...] = ALLOWED_WORDS) -> DataFrame:
    """``id_col, base, spans``: arrays of (kind, start, end) for each row, pattern spans alone and all spans."""
    ship(docs.sparkSession)
    span = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = Scanner(classes, allowed, words)
        named = lambda spans: [{"kind": k, "start": a, "end": b} for k, a, b in spans]
        for batch in batches:
            both = [scanner.scan(t.as_py() or "") for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([named(b) for b, _ in both], span), pa.array([named(s) for _, s in both], span)], names=[id_col, "base", "spans"])

    kind, spans = docs.schema[id_col].dataType.simpleString(), "array<struct<kind:string,start:bigint,end:bigint>>"
    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, base {spans}, spans {spans}")


def redact_documents(docs: DataFrame, text_col: str = "text", mask: str = "[secret]", classes: tuple[CharClass, ...] = CLASSES, allowed: tuple[str, ...] = ALLOWED, words: tuple[str, ...] = ALLOWED_WORDS) -> DataFrame:
    """``docs`` with every found span of ``text_col`` replaced by ``mask``; all columns and rows stay, null texts stay null."""
    ship(docs.sparkSession)
    schema, at = docs.schema, docs.columns.index(text_col)

    def clean(scanner: Scanner, text: str | None) -> str | None:
        if not text:
            return text
        out, end = [], 0
        for _, a, b in scanner.scan(text)[1]:
            if a >= end:
                out += [text[end:a], mask]
            end = max(end, b)
        return "".join([*out, text[end:]]) if out else text

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = Scanner(classes, allowed, words)
        for batch in batches:
            yield batch.set_column(at, batch.schema.field(at), pa.array([clean(scanner, t.as_py()) for t in batch.column(at)], batch.schema.field(at).type))

    return docs.mapInArrow(run, schema)
