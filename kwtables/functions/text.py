"""Words of descriptions, with optional stemming and synonyms."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

ASCII_BREAKS = r"[^a-z0-9]+"
PROSE_BREAKS = r"[^\p{L}\p{N}]+"

#: Endings of the rule stemmer, tried in this order: pattern with the part that stays, and what follows it.
STEM_RULES = (
    (r"^([a-z]{2,}ss)es$", ""),
    (r"^([a-z]{2,})ies$", "y"),
    (r"^([a-z]{2,}[^s])s$", ""),
    (r"^([a-z]{3,})ing$", ""),
    (r"^([a-z]{3,})ed$", ""),
)


def tokenize(text: Column, prose: bool = False) -> Column:
    """Distinct lower-case words in order of first use; null and wordless texts give an empty array."""
    parts = F.split(F.lower(F.coalesce(text, F.lit(""))), PROSE_BREAKS if prose else ASCII_BREAKS)
    return F.array_distinct(F.array_remove(parts, ""))


def stem(word: Column) -> Column:
    """The first rule that applies, so that a word loses one ending at most."""
    out = word
    for pattern, replacement in reversed(STEM_RULES):
        out = F.when(F.regexp_like(word, F.lit(pattern)), F.concat(F.regexp_extract(word, pattern, 1), F.lit(replacement))).otherwise(out)
    return out


def normalise(df: DataFrame, word_col: str, synonyms: DataFrame | None = None, stemmed: bool = True) -> DataFrame:
    """``df`` with ``word_col`` replaced by its canonical form: a synonym's word, then its stem.

    ``synonyms(word, canonical)`` is joined by its word; the planner broadcasts it if it is small. Words and their
    variants thus share one posting list; queries go through the same function.
    """
    out = df
    if synonyms is not None:
        table = synonyms.select(F.lower("word").alias("_variant"), F.lower("canonical").alias("_canonical")).dropDuplicates(["_variant"])
        out = out.join(table, F.col(word_col) == F.col("_variant"), "left").withColumn(word_col, F.coalesce("_canonical", word_col)).drop("_variant", "_canonical")
    return out.withColumn(word_col, stem(F.col(word_col))) if stemmed else out


def similarity(words: Column) -> Column:
    """Jaccard similarity of one contained word with a word set."""
    return F.lit(1.0) / F.size(words)
