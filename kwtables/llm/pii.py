"""Personal data by weak supervision: labelers vote on candidate spans, and a classifier learns from their agreement.

Candidates are the spans of four fixed patterns and looser ones: telephone numbers without a plus, spelled-out and
hexadecimal addresses, account numbers, national numbers, birth dates, street addresses and personal names. Seven labelers (pattern, checksum, gazetteer, cue words before, contrary words
before, shape, neighbours) vote personal, not personal or abstain. Expectation-maximisation estimates how reliable each
labeler is without any labels, from the counts of all vote patterns in the corpus. The posteriors then train a
logistic span classifier on features of the span and its context, again from counts. Both tables have a fixed number of
possible rows whatever the corpus, so nothing is sampled; the model that is sent to the workers is a few kilobytes. No
labeler and no feature knows whether a span is of a fixed pattern: features name its family (telephone, address, ...), so what
is learned on one kind serves the others of its family.

Spans of the fixed patterns are always reported; others only where the classifier finds them personal. Offsets are
code points, end exclusive. Defined results: null and empty texts have no spans; whole texts are searched; repeated rows
give repeated results; a corpus without candidates gives the prior model, which reports the patterns alone.
"""

from __future__ import annotations

import math
import re
from bisect import bisect_left
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ship
from .secret_scan import covered

Span = tuple[str, int, int]

# The pattern kinds in their order, and the patterns.
BASE_KINDS = ("email", "ip", "card", "phone")
DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
# The lookbehind only spares retries inside a run of digits, which fail wherever its start fails.
IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")

LOOSE_KINDS = ("phone_local", "email_spelled", "ip_hex", "iban", "national", "birth", "street", "name")
# Given names and titles, the gazetteer of the candidate names.
GIVEN_NAMES = "Anna Anne Antonio Carlos Carmen Charles Christian David Elena Elizabeth Emma Eva Francisco Franz Hans Isabel James Jane Jean Jennifer Jessica Johann John José Juan Julia Karl Klaus Laura Linda Lisa Louis Lucas Luis Manuel Marc Maria Marie Mark Martin Mary Michael Miguel Nicolas Patricia Paul Paula Pedro Peter Pierre Richard Robert Sarah Sophie Susan Susanne Thomas Ursula William Wolfgang".split()
TITLES = "Mr Mrs Ms Dr Prof Herr Frau Monsieur Madame Señor Señora".split()
CAPITALISED = r"[A-ZÄÖÜÉÈÀÁÍÓÚÑ][a-zäöüßéèêàáíóúñç]{1,24}"
LOOSE = {
    "phone_local": re.compile(r"(?<![\w+.-])(?:\([0-9]{2,4}\)|0[0-9]{1,4}|[0-9]{3})[\x20.-]?[0-9]{3,4}[\x20.-][0-9]{3,4}(?![\w-]|\.[0-9])"),
    "email_spelled": re.compile(r"(?<!\w)[A-Za-z0-9._+-]{1,64}\x20?[\[({]\x20?at\x20?[\])}]\x20?[A-Za-z0-9-]{1,63}(?:\x20?[\[({]\x20?dot\x20?[\])}]\x20?[A-Za-z]{2,24}|\.[A-Za-z]{2,24})(?!\w)", re.IGNORECASE | re.ASCII),
    "ip_hex": re.compile(r"(?<![\w:])(?:[0-9A-Fa-f]{1,4}:){7}[0-9A-Fa-f]{1,4}(?![\w:])"),
    "iban": re.compile(r"(?<!\w)[A-Z]{2}[0-9]{2}(?:\x20?[A-Z0-9]{4}){2,7}(?:\x20?[A-Z0-9]{1,3})?(?!\w)", re.ASCII),
    "national": re.compile(r"(?<![\w-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![\w-])", re.ASCII),
    "birth": re.compile(r"(?<![\w./-])(?:(?:19|20)[0-9]{2}-[01][0-9]-[0-3][0-9]|[0-3]?[0-9][./][01]?[0-9][./](?:19|20)[0-9]{2})(?![\w/-]|\.[0-9])", re.ASCII),
    "street": re.compile(rf"(?<!\w)(?:[0-9]{{1,5}}\x20(?:{CAPITALISED}\x20){{1,3}}(?:Street|St|Avenue|Ave|Road|Rd|Lane|Drive|Boulevard|Court|Square)|{CAPITALISED[:-6]}{{1,20}}(?:straße|strasse|weg|platz|gasse)\x20[0-9]{{1,4}}|[0-9]{{1,4}},?\x20(?:rue|avenue|boulevard)\x20(?:de\x20(?:la\x20)?)?{CAPITALISED}|(?:Calle|Avenida)\x20{CAPITALISED},?\x20[0-9]{{1,4}})(?!\w)"),
    "name": re.compile(rf"(?<!\w)(?:(?:{'|'.join(TITLES)})\.?\x20(?:{CAPITALISED}\x20)?|(?:{'|'.join(GIVEN_NAMES)})\x20(?:[A-Z]\.\x20)?){CAPITALISED}(?!\w)"),
}
KINDS = BASE_KINDS + LOOSE_KINDS
DIGIT, DIGIT_KINDS = re.compile("[0-9]").search, ("phone_local", "iban", "national", "birth", "street")
#: What a kind is about, whatever pattern found it.
FAMILIES = ("email", "ip", "card", "phone", "iban", "national", "birth", "street", "name")


def family(kind: str) -> str:
    return kind.split("_")[0]


# Gazetteers and cue words of the labelers.
ACCOUNT_COUNTRIES = frozenset("AT BE BG CH CY CZ DE DK EE ES FI FR GB GR HR HU IE IS IT LI LT LU LV MC MT NL NO PL PT RO SE SI SK SM".split())
TOP_DOMAINS = frozenset("com org net edu gov io co uk de fr es it nl ch at be eu us ca au jp cn in br ru pl se no fi dk pt ie nz info biz".split())
CARD_STARTS = ("34", "36", "37", "38", "4", "51", "52", "53", "54", "55", "6011", "62", "65")
COUNTRY_CODES = ("1", "7", "20", "27", "30", "31", "32", "33", "34", "39", "41", "43", "44", "45", "46", "47", "48", "49", "52", "55", "61", "81", "86", "91")
CUES = re.compile(r"(?i)\b(?:e-?mail|mail|contact|write|reach|tel|telephone|phone|mobile|cell|call|fax|whatsapp|card|visa|credit|payment|account|ip|host|login|address|user|client|iban|bank|ssn|social security|born|birth|birthday|dob|geboren|née?|nacid[oa]|lives?|resides?|wohnt|name|named|signed|dear|regards|sincerely)\b[^\n]{0,24}$")
CONTRARY = re.compile(r"(?i)\b(?:version|ver|isbn|issn|doi|figure|fig|table|section|chapter|page|order|invoice|item|part|sku|build|release|year|total|sum|price|id|no)\b[^\n]{0,12}$")
WINDOW = 40

LABELERS = ("pattern", "checksum", "gazetteer", "cue", "contrary", "shape", "neighbours")
YES, NO, ABSTAIN = 1, 0, -1
#: Reported look-alikes need this probability.
THRESHOLD = 0.5


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        total += d if i % 2 == 0 else (2 * d - 9 if d > 4 else 2 * d)
    return total % 10 == 0


def email_spans(text: str) -> list[Span]:
    """Leftmost non-overlapping addresses, found from their at-signs so that long runs without one cost nothing."""
    out, end, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > end and text[start - 1] in LOCAL:
            start -= 1
        if start < at and (m := DOMAIN.match(text, at + 1)):
            out.append(("email", start, m.end()))
            end = m.end()
        at = text.find("@", max(at + 1, end))
    return out


def pattern_spans(text: str) -> list[Span]:
    """Spans of the four patterns by start, then kind; each kind alone is leftmost and non-overlapping."""
    out = email_spans(text)
    for m in IP.finditer(text):
        if all(len(p) <= 3 and int(p) <= 255 for p in (q.lstrip("0") or "0" for q in m[0].split("."))):
            out.append(("ip", m.start(), m.end()))
    for m in CARD.finditer(text):
        if m.end() - m.start() >= 12:
            digits = m[0].replace(" ", "").replace("-", "")
            if 12 <= len(digits) <= 19 and luhn(digits):
                out.append(("card", m.start(), m.end()))
    if "+" in text:
        for m in PHONE.finditer(text):
            if 9 <= sum(c.isdigit() for c in m[0]) <= 15:
                out.append(("phone", m.start(), m.end()))
    return sorted(out, key=lambda s: (s[1], KINDS.index(s[0])))


def candidates(text: str) -> tuple[list[Span], list[Span]]:
    """(pattern spans, look-alikes outside them)."""
    base = pattern_spans(text)
    loose: list[Span] = []
    digits, brackets = DIGIT(text) is not None, any(c in text for c in "[({")
    for kind, pattern in LOOSE.items():
        # what a pattern cannot do without
        if kind == "email_spelled" and not brackets or kind == "ip_hex" and text.count(":") < 7 or kind in DIGIT_KINDS and not digits:
            continue
        starts, ends = covered([*base, *loose])
        for m in pattern.finditer(text):
            i = bisect_left(starts, m.end())  # spans that start before this one's end
            if not i or ends[i - 1] <= m.start():
                loose.append((kind, m.start(), m.end()))
    return base, loose


def mod_97(account: str) -> int:
    """Remainder of an account number's check digits."""
    moved = account[4:] + account[:4]
    return int("".join(str(int(c, 36)) for c in moved)) % 97


def votes(text: str, span: Span) -> tuple[int, ...]:
    """One vote of each labeler."""
    kind, a, b = span
    s, before, after = text[a:b], text[max(0, a - WINDOW) : a], text[b : b + 1]
    digits = "".join(c for c in s if c in "0123456789")
    root = family(kind)
    pattern, checksum, gazetteer, shape = ABSTAIN, ABSTAIN, ABSTAIN, ABSTAIN
    if root == "card":
        pattern = YES if re.fullmatch(r"[0-9]{12,19}|[0-9]{4}(?:[ -][0-9]{2,6})+", s) else NO
        checksum = YES if luhn(digits) else NO
        gazetteer = YES if digits.startswith(CARD_STARTS) else NO
        shape = YES if len(digits) in (15, 16) else NO
    elif root == "phone":
        pattern = YES if re.fullmatch(r"(?:\+[0-9]{1,3}[ .-]?)?(?:\([0-9]{2,4}\)|[0-9]{2,5})(?:[ .-]?[0-9]{2,4}){2,4}", s) else NO
        checksum = YES if 9 <= len(digits) <= 12 else NO
        gazetteer = YES if s[0] == "+" and digits.startswith(COUNTRY_CODES) else ABSTAIN
        shape = YES if re.search(r"[ ().-]", s) and len(set(digits)) > 3 else NO
    elif root == "email":
        pattern = YES if re.search(r"[^\W_]\W{0,2}(?:@|at)\W{0,2}[^\W_]", s, re.IGNORECASE) else NO
        gazetteer = YES if re.split(r"\W+", s.rstrip(")]}").lower())[-1] in TOP_DOMAINS else NO
        shape = YES if re.match(r"[A-Za-z]", s) else NO
    elif root == "ip":
        parts = s.split(".") if "." in s else s.split(":")
        pattern = YES if len(set(parts)) > 1 else NO
        checksum = YES if parts[0].strip("0") else NO
        gazetteer = NO if s in ("0.0.0.0", "127.0.0.1", "255.255.255.255") else ABSTAIN
        shape = YES if max(map(len, parts)) > 1 else NO
    elif root == "iban":
        plain = s.replace(" ", "")
        pattern = YES if 15 <= len(plain) <= 34 else NO
        checksum = YES if mod_97(plain) == 1 else NO
        gazetteer = YES if plain[:2] in ACCOUNT_COUNTRIES else NO
    elif root == "national":
        pattern = NO if s.startswith(("000", "666", "9")) or s[4:6] == "00" or s.endswith("0000") else YES
        shape = YES if len(set(digits)) > 3 else NO
    elif root == "birth":
        numbers = [int(x) for x in re.split(r"[./-]", s)]
        year, month = (numbers[0], numbers[1]) if numbers[0] > 31 else (numbers[2], numbers[1])
        pattern = YES if 1 <= month <= 12 else NO
        shape = YES if 1900 <= year <= 2015 else NO
    elif root == "street":
        pattern = YES if digits else NO
        gazetteer = YES if re.search(r"(?i)street|avenue|road|straße|strasse|rue|calle", s) else ABSTAIN
    else:
        first = re.split(r"[ .]+", s)[0]
        pattern = YES if first in TITLES else ABSTAIN
        gazetteer = YES if any(x in GIVEN_NAMES for x in s.split(" ")) else ABSTAIN
        shape = YES if len(s.split(" ")) > 1 else NO
    cue = YES if CUES.search(before) else ABSTAIN
    contrary = NO if CONTRARY.search(before) else ABSTAIN
    neighbours = NO if before[-1:].isalnum() or after.isalnum() or before[-1:] in tuple("$€£%") else YES
    return pattern, checksum, gazetteer, cue, contrary, shape, neighbours


def features(text: str, span: Span) -> tuple[int, ...]:
    """Small counts that describe a span and its context, each with a fixed number of values."""
    kind, a, b = span
    s = text[a:b]
    before = text[max(0, a - WINDOW) : a]
    digits = sum(c.isdigit() for c in s)
    marks = sum(not c.isalnum() for c in s)
    return (
        FAMILIES.index(family(kind)),
        min(5, int(math.log2(b - a))),
        min(3, digits * 4 // (b - a + 1)),
        min(3, marks),
        int(bool(CUES.search(before))),
        int(bool(CONTRARY.search(before))),
        int(before[-1:].isspace() or not before),
        int(text[b : b + 1].isspace() or b == len(text)),
    )


#: Values of each feature, in order.
WIDTHS = (len(FAMILIES), 6, 4, 4, 2, 2, 2, 2)


def one_hot(rows: np.ndarray) -> np.ndarray:
    """Feature rows as 0/1 columns, with a constant."""
    out = np.zeros((len(rows), sum(WIDTHS) + 1))
    out[:, -1] = 1
    at = 0
    for j, w in enumerate(WIDTHS):
        out[np.arange(len(rows)), at + np.clip(rows[:, j], 0, w - 1)] = 1
        at += w
    return out


def reliabilities(kinds: np.ndarray, cast: np.ndarray, weight: np.ndarray, rounds: int = 50, prior: float = 0.5) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(posterior of each row, table labeler x class x vote, share of personal spans by family), by expectation-maximisation.

    Every labeler has one table of vote probabilities given the class; smoothing counts keep a labeler that is better
    than chance at the start and rare votes away from zero.
    """
    n_lab = cast.shape[1]
    table = np.empty((n_lab, 2, 3))  # votes no, yes, abstain
    table[:, 1] = (0.15, 0.55, 0.30)
    table[:, 0] = (0.40, 0.30, 0.30)
    # words around a span are trusted more than its form at the start, and say nothing more often
    table[LABELERS.index("cue")] = ((0.02, 0.08, 0.90), (0.02, 0.60, 0.38))
    table[LABELERS.index("contrary")] = ((0.50, 0.02, 0.48), (0.04, 0.02, 0.94))
    start, share = table.copy(), np.full(len(FAMILIES), prior)
    column = np.where(cast == ABSTAIN, 2, cast)
    post = np.full(len(cast), prior)
    for _ in range(rounds):
        log = np.log(np.stack([1 - share[kinds], share[kinds]]))
        for j in range(n_lab):
            log = log + np.log(table[j][:, column[:, j]])
        post = 1 / (1 + np.exp(np.clip(log[0] - log[1], -50, 50)))
        w = np.stack([weight * (1 - post), weight * post])
        for j in range(n_lab):
            counts = np.stack([[w[c][column[:, j] == v].sum() for v in range(3)] for c in range(2)]) + 20 * start[j]
            table[j] = counts / counts.sum(axis=1, keepdims=True)
        for k in range(len(FAMILIES)):
            mine = kinds == k
            share[k] = (w[1][mine].sum() + 5 * prior) / (weight[mine].sum() + 5)
    return post, table, share


def fit_classifier(rows: np.ndarray, target: np.ndarray, weight: np.ndarray, ridge: float = 1.0, rounds: int = 25) -> np.ndarray:
    """Logistic weights by Newton steps on counted rows with soft targets."""
    x = one_hot(rows)
    beta = np.zeros(x.shape[1])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ beta, -30, 30)))
        grad = x.T @ (weight * (target - p)) - ridge * beta
        hess = (x * (weight * p * (1 - p) + 1e-9)[:, None]).T @ x + ridge * np.eye(len(beta))
        step = np.linalg.solve(hess, grad)
        beta += step
        if np.abs(step).max() < 1e-8:
            break
    return beta


def train(docs: DataFrame, text_col: str = "text") -> dict:
    """Labelers' reliabilities and the span classifier, from the counts of (kind, votes, features) over all documents."""
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            seen: Counter = Counter()
            for t in batch.column(0):
                if text := t.as_py():
                    for span in (s for part in candidates(text) for s in part):
                        seen[bytes(v + 1 for v in votes(text, span)) + bytes(features(text, span))] += 1
            yield pa.RecordBatch.from_arrays([pa.array(list(seen), pa.binary()), pa.array(list(seen.values()), pa.int64())], names=["signature", "n"])

    counted = docs.select(text_col).mapInArrow(run, "signature binary, n bigint").groupBy("signature").agg(F.sum("n").alias("n")).orderBy("signature").collect()
    if not counted:
        return {"beta": np.zeros(sum(WIDTHS) + 1).tolist(), "reliability": {}, "share": {}}
    raw = np.array([list(r["signature"]) for r in counted], dtype=np.int64)
    weight = np.array([r["n"] for r in counted], dtype=float)
    cast, rows = raw[:, : len(LABELERS)] - 1, raw[:, len(LABELERS) :]
    post, table, share = reliabilities(rows[:, 0], cast, weight)
    beta = fit_classifier(rows, post, weight)
    return {"beta": beta.tolist(), "reliability": {name: table[j].tolist() for j, name in enumerate(LABELERS)}, "share": dict(zip(FAMILIES, share.tolist(), strict=True))}


def find_spans(text: str, beta: np.ndarray, threshold: float = THRESHOLD) -> tuple[list[Span], list[Span]]:
    """(pattern spans, all spans) with look-alikes judged by the classifier."""
    base, loose = candidates(text)
    if loose:
        odds = one_hot(np.array([features(text, s) for s in loose])) @ beta
        loose = [s for s, z in zip(loose, odds, strict=True) if z > math.log(threshold / (1 - threshold))]
    return base, sorted([*base, *loose], key=lambda s: (s[1], KINDS.index(s[0])))


def find_personal_data(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", model: dict | None = None) -> DataFrame:
    """``id_col, base, spans``: arrays of (kind, start, end), pattern spans alone and all spans; trains on ``docs`` unless given a model."""
    ship(docs.sparkSession)
    weights = (model or train(docs, text_col))["beta"]
    span = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        beta = np.array(weights)
        named = lambda spans: [{"kind": k, "start": a, "end": b} for k, a, b in spans]
        for batch in batches:
            both = [find_spans(t.as_py() or "", beta) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([named(b) for b, _ in both], span), pa.array([named(s) for _, s in both], span)], names=[id_col, "base", "spans"])

    kind, spans = docs.schema[id_col].dataType.simpleString(), "array<struct<kind:string,start:bigint,end:bigint>>"
    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, base {spans}, spans {spans}")
