"""Language identification by nearest centroid: TF-IDF n-gram vectors against several clustered centroids per language.

A text's letters (lower-cased, everything else a break) give 1- to 3-grams of code points that are hashed into a fixed
number of cells; cell counts are dampened, weighted by inverse document frequency and normalised. Spherical k-means
splits each language's training vectors into a few centroids; a text takes the language of the nearest centroid by
cosine. Training also sets, for each language and number of distinct cells, the cosine below which a text is rejected: a third
of the least that held-out texts of at least that size reach on centroids learned without them, so that clean texts stay.
Texts of fewer than FEW_CELLS cells tell too little and go only at a cosine near zero.

Training reads about SAMPLE labelled texts of each language, those whose seeded hash of the id lies in that share of all ids,
whatever the partitioning; ids that repeat count once. With many languages the sample shrinks so that MOST_VECTORS fixed-size
vectors reach the driver. Languages are taken from the labels; more than MOST_LANGUAGES raise a ValueError.

Defined results: null texts and texts without a letter are ``und`` with score 0 and are rejected; whole texts are read,
in pieces of bounded size; ties go to the first language by name; repeated rows give repeated results; without any
labelled row every text is ``und``; other columns are never read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ship

CELL_BITS = 12
CELLS = 1 << CELL_BITS
SAMPLE = 400
CENTROIDS = 4
#: Languages that can be learned, and training vectors of all languages together (8 KB each on the driver).
MOST_LANGUAGES, MOST_VECTORS = 1_000, 25_600
NO_LANGUAGE = "und"
#: Rejected are texts below this share of the least held-out cosine.
REJECT_SHARE = 1 / 3
#: Below so many distinct cells a text is very short and is rejected only under this cosine; so is any without held-out texts.
FEW_CELLS, SHORT_COSINE = 64, 0.02
#: One in so many training texts is held out for the limits; under so many of a size, those of all languages, then of smaller sizes, count.
HOLD_EVERY, LEAST_HELD = 4, 20
PIECE = 1 << 20
_letters: list[np.ndarray] = []


def _letter_table() -> np.ndarray:
    """Whether each code point is a letter, once for each worker."""
    if not _letters:
        _letters.append(np.fromiter((chr(c).isalpha() for c in range(0x110000)), dtype=bool, count=0x110000))
    return _letters[0]


def cell_counts(text: str | None) -> np.ndarray | None:
    """Hashed 1- to 3-gram counts of a text's letters; None if it has none."""
    if not text:
        return None
    letters, out = _letter_table(), None
    low = text.lower()
    for at in range(0, len(low), PIECE):
        x = np.frombuffer(low[at : at + PIECE + 2].encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
        own = letters[x]
        if not own.any():
            continue
        x = np.where(own, x, 32).astype(np.uint32)
        keep = np.append(True, own[1:] | own[:-1])  # runs of other characters become one break
        x = x[keep]
        x = np.concatenate([[32] if x[0] != 32 else [], x, [32] if x[-1] != 32 else []]).astype(np.uint32)
        with np.errstate(over="ignore"):
            one = x * np.uint32(0x9E3779B1)
            two = (one[:-1] ^ (x[1:] * np.uint32(0x85EBCA77))) * np.uint32(0xC2B2AE3D)
            three = (two[:-1] ^ (x[2:] * np.uint32(0x27D4EB2F))) * np.uint32(0x165667B1)
        cells = np.concatenate([(g >> np.uint32(32 - CELL_BITS)) for g in (one[1:-1], two, three)])
        n = np.bincount(cells, minlength=CELLS)
        out = n if out is None else out + n
    return out


def weigh(counts: np.ndarray, idf: np.ndarray | None = None) -> np.ndarray:
    """Dampened, weighted, normalised vectors (rows)."""
    v = np.log1p(counts.astype(np.float32))
    if idf is not None:
        v *= idf
    return v / np.maximum(np.linalg.norm(v, axis=-1, keepdims=True), 1e-12)


def cluster(v: np.ndarray, k: int, rounds: int = 15) -> np.ndarray:
    """Spherical k-means from farthest-first starts; empty clusters vanish."""
    centre = v.mean(axis=0)
    centres = [v[int(np.argmax(v @ centre))]]
    while len(centres) < min(k, len(v)):
        nearest = np.max(v @ np.stack(centres).T, axis=1)
        centres.append(v[int(np.argmin(nearest))])
    c = np.stack(centres)
    for _ in range(rounds):
        mine = np.argmax(v @ c.T, axis=1)
        c = np.stack([v[mine == j].mean(axis=0) for j in range(len(c)) if (mine == j).any()])
        c /= np.maximum(np.linalg.norm(c, axis=1, keepdims=True), 1e-12)
    return c


def _bin(cells: np.ndarray | int) -> np.ndarray:
    """Size class of a text by its number of distinct cells: powers of two."""
    return np.log2(np.maximum(cells, 1)).astype(np.int64)


def held_cosines(mine: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(size classes, cosines) of one language's held-out vectors against centroids of the others; equal vectors count once."""
    new = np.append(True, (mine[1:] != mine[:-1]).any(axis=1)) if len(mine) else np.empty(0, dtype=bool)  # rows come sorted
    distinct = mine[new]
    held = np.arange(len(distinct)) % HOLD_EVERY == HOLD_EVERY - 1
    if not held.any():
        return np.empty(0, dtype=np.int64), np.empty(0)
    c = cluster(distinct[~held], k)
    return _bin((distinct[held] > 0).sum(axis=1)), np.max(distinct[held] @ c.T, axis=1)


def limits_of(held: list[tuple[np.ndarray, np.ndarray]]) -> list[list[float]]:
    """Least cosine that stays, for each language and size class."""
    bins, cosines = np.concatenate([b for b, _ in held]), np.concatenate([c for _, c in held])
    out = []
    for b, c in held:
        own = []
        for size in range(CELL_BITS + 1):
            found = c[b >= size]
            down = size
            while len(found) < LEAST_HELD and down >= 0:
                found = cosines[bins >= down]
                down -= 1
            short = 2 ** (size + 1) <= FEW_CELLS or not len(found)
            own.append(SHORT_COSINE if short else float(max(SHORT_COSINE, found.min() * REJECT_SHARE)))
        out.append(own)
    return out


def is_rejected(model: dict, language: int, cosine: float, counts: np.ndarray) -> bool:
    return bool(cosine < model["reject"][language][int(_bin(np.count_nonzero(counts)))])


def train(docs: DataFrame, where: Column | None = None, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", sample: int = SAMPLE, centroids: int = CENTROIDS, most_languages: int = MOST_LANGUAGES) -> dict:
    """Model from the labelled rows of ``docs`` that satisfy ``where``: a few hundred kilobytes of numbers."""
    ship(docs.sparkSession)
    # texts that can be learned from, and one key that samples the same rows in any partitioning
    labelled = docs.where(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull())
    if where is not None:
        labelled = labelled.where(where)
    key = F.xxhash64(F.col(id_col), F.lit("language"))
    # counts alone decide which keys are read, so no ranking gathers a language in one task
    counted = labelled.groupBy(F.col(lang_col).alias("lang")).agg(F.approx_count_distinct(key, 0.02).alias("ids")).orderBy("lang").limit(most_languages + 1).collect()
    if len(counted) > most_languages:
        raise ValueError(f"more than {most_languages} languages; most_languages sets how many can be learned")
    if not counted:
        return {"langs": [], "idf": None, "centroids": None, "owner": [], "reject": []}
    sample = min(sample, max(1, MOST_VECTORS // len(counted)))
    below = lambda n: min(2**63 - 1, int(sample / max(n, 1) * 2**64) - 2**63)
    shares = docs.sparkSession.createDataFrame([(r["lang"], below(r["ids"])) for r in counted], "lang_name string, most bigint")
    chosen = labelled.select(F.col(lang_col).alias("lang"), F.col(text_col).alias("text"), key.alias("key")).join(F.broadcast(shares), F.col("lang") == F.col("lang_name")).where(F.col("key") <= F.col("most"))
    texts = chosen.groupBy("lang", "key").agg(F.min("text").alias("text"))  # rows that repeat an id

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            langs, vectors = [], []
            for lang, t in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                n = cell_counts(t.as_py())
                if n is not None:
                    langs.append(lang)
                    vectors.append(np.log1p(n).astype(np.float16).tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(langs, pa.string()), pa.array(vectors, pa.binary())], names=["lang", "vector"])

    rows = texts.select("lang", "text").mapInArrow(run, "lang string, vector binary").orderBy("lang", "vector").collect()  # about sample rows of each language
    if not rows:
        return {"langs": [], "idf": None, "centroids": None, "owner": [], "reject": []}
    owner = np.array([r["lang"] for r in rows])
    x = np.empty((len(rows), CELLS), dtype=np.float32)
    for i, r in enumerate(rows):
        x[i] = np.frombuffer(r["vector"], dtype=np.float16)
    del rows
    langs = sorted(set(owner.tolist()))
    # mean over languages of the share of texts with a cell, so that a language with more rows weighs no more
    share = np.mean([(x[owner == lang] > 0).mean(axis=0) for lang in langs], axis=0)
    idf = (np.log((1 + len(x)) / (1 + share * len(x))) + 0.2).astype(np.float32)
    x *= idf  # in place: the driver holds one matrix; vectors come dampened already
    x /= np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)
    out, owners, held = [], [], []
    for i, lang in enumerate(langs):
        mine = x[owner == lang]
        c = cluster(mine, centroids)
        out.append(c)
        owners += [i] * len(c)
        held.append(held_cosines(mine, centroids))
    return {"langs": langs, "idf": idf.tobytes(), "centroids": np.concatenate(out).astype(np.float32).tobytes(), "owner": owners, "reject": limits_of(held)}


def predict(docs: DataFrame, model: dict, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id_col, lang_pred, score, rejected`` for each row; score is the nearest centroid's cosine."""
    ship(docs.sparkSession)
    cast = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = cast.value
        if m["langs"]:
            idf = np.frombuffer(m["idf"], dtype=np.float32)
            centres = np.frombuffer(m["centroids"], dtype=np.float32).reshape(-1, CELLS)
            owner = np.array(m["owner"])
        for batch in batches:
            langs, scores, rejected = [], [], []
            for t in batch.column(1):
                n = cell_counts(t.as_py()) if m["langs"] else None
                if n is None:
                    langs.append(NO_LANGUAGE)
                    scores.append(0.0)
                    rejected.append(True)
                    continue
                cosine = centres @ weigh(n, idf)
                i = int(np.argmax(cosine))
                langs.append(m["langs"][owner[i]])
                scores.append(round(float(min(1.0, max(0.0, cosine[i]))), 6))
                rejected.append(is_rejected(m, owner[i], cosine[i], n))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(langs, pa.string()), pa.array(scores, pa.float64()), pa.array(rejected, pa.bool_())], names=[id_col, "lang_pred", "score", "rejected"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, lang_pred string, score double, rejected boolean")


def keep_identified(docs: DataFrame, model: dict, text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` that are not rejected, with all their columns."""
    ship(docs.sparkSession)
    cast = docs.sparkSession.sparkContext.broadcast(model)
    at, schema = docs.columns.index(text_col), docs.schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = cast.value
        if not m["langs"]:
            return
        idf = np.frombuffer(m["idf"], dtype=np.float32)
        centres = np.frombuffer(m["centroids"], dtype=np.float32).reshape(-1, CELLS)
        for batch in batches:
            keep = []
            for t in batch.column(at):
                n = cell_counts(t.as_py())
                cosine = None if n is None else centres @ weigh(n, idf)
                keep.append(n is not None and not is_rejected(m, m["owner"][int(np.argmax(cosine))], cosine.max(), n))
            yield batch.filter(pa.array(keep, pa.bool_()))

    return docs.mapInArrow(run, schema)
