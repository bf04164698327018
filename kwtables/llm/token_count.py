"""Token counts without ids: the pieces of each distinct pre-token are counted once and joined to frequencies.

A block of rows is split into pre-tokens and counted into (document, pre-token, frequency); the distinct
pre-tokens of the block that are not yet known are each encoded once; the counts are joined to the frequencies
and summed by document. Blocks hold a fixed volume of text, so nothing is shuffled and memory follows the block and the
bounded table of known counts, never the corpus vocabulary. ``strategy="shuffle"`` does the same over the whole
corpus with joins (each distinct pre-token exactly once anywhere), at the price of a shuffle of all frequencies.

Defined results: null text counts as empty (0 bytes, 0 tokens); special-token strings count as the library
counts them by default, one each; repeated rows give repeated results.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bpe import ByteBpe, load
from .common import ship, trim

#: Characters of text in a block.
BLOCK_CHARS = 1 << 21
#: Counts that a worker remembers between blocks.
KNOWN_ENTRIES = 300_000
_known: dict[str, dict[str, int]] = {}


def frequencies(bpe: ByteBpe, text: str) -> tuple[Counter, int]:
    """Frequency of each pre-token, and the number of special tokens."""
    seen: Counter = Counter()
    special = 0
    for part, token in bpe.sections(text):
        if token is None:
            seen.update(bpe.split(part))
        else:
            special += 1
    return seen, special


def _weigh_block(bpe: ByteBpe, known: dict[str, int], block: list[tuple[Counter, int]]) -> list[int]:
    """Tokens of each document of a block: distinct pre-tokens are counted once, then joined to the frequencies."""
    fresh = list(set().union(*(seen for seen, _ in block)) - known.keys())
    if len(known) + len(fresh) > KNOWN_ENTRIES:
        known.clear()
        fresh = list(set().union(*(seen for seen, _ in block)))
    known.update(zip(fresh, bpe.piece_counts(fresh), strict=True))
    return [n + sum(known[p] * c for p, c in seen.items()) for seen, n in block]


def count_tokens(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", strategy: str = "block") -> DataFrame:
    """``id_col, n_bytes, n_tokens`` for each row."""
    ship(docs.sparkSession)
    if strategy == "shuffle":
        return _count_by_join(docs, path, id_col, text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = load(path)
        known = _known.setdefault(path, {})
        for batch in batches:
            totals: list[int] = []
            block: list[tuple[Counter, int]] = []
            held = 0
            for t in batch.column(1):
                text = t.as_py() or ""
                block.append(frequencies(bpe, text))
                held += len(text)
                if held >= BLOCK_CHARS:
                    totals += _weigh_block(bpe, known, block)
                    block, held = [], 0
            totals += _weigh_block(bpe, known, block)
            sizes = pc.binary_length(batch.column(1)).fill_null(0).cast(pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), sizes, pa.array(totals, pa.int64())], names=[id_col, "n_bytes", "n_tokens"])
        trim()

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, n_bytes bigint, n_tokens bigint")


def _count_by_join(docs: DataFrame, path: str, id_col: str, text_col: str) -> DataFrame:
    kind = docs.schema[id_col].dataType.simpleString()
    rows = docs.select(F.monotonically_increasing_id().alias("row_no"), F.col(id_col).alias("row_id"), F.col(text_col).alias("row_text"))

    def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = load(path)
        for batch in batches:
            for no, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                seen, n = frequencies(bpe, text.as_py() or "")
                items = [*((p, c) for p, c in seen.items()), *([(None, n)] if n else [])]
                yield pa.RecordBatch.from_arrays([pa.array([no] * len(items), pa.int64()), pa.array([p for p, _ in items], pa.string()), pa.array([c for _, c in items], pa.int64())], names=["row_no", "piece", "freq"])

    def weigh(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = load(path)
        for batch in batches:
            n = bpe.piece_counts(batch.column(0).to_pylist())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64())], names=["piece", "pieces"])

    parts = rows.select("row_no", "row_text").mapInArrow(split, "row_no bigint, piece string, freq bigint")
    weights = parts.where("piece IS NOT NULL").select("piece").distinct().mapInArrow(weigh, "piece string, pieces bigint")
    total = parts.join(weights, "piece", "left").groupBy("row_no").agg(F.sum(F.col("freq") * F.coalesce("pieces", F.lit(1))).alias("n_tokens"))
    size = F.coalesce(F.octet_length("row_text"), F.lit(0)).cast("bigint")
    out = rows.select("row_no", "row_id", size.alias("n_bytes")).join(total, "row_no", "left")
    return out.select(F.col("row_id").cast(kind).alias(id_col), "n_bytes", F.coalesce("n_tokens", F.lit(0)).cast("bigint").alias("n_tokens"))
