"""Scores of subtrees and their aggregation to scores of tree patterns."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Scores are compared by this many significant digits, so that the order of summation cannot reorder patterns.
DIGITS = 9


def order_key(score: str) -> Column:
    """A whole number that grows with ``score`` and is equal for scores equal in DIGITS significant digits.

    Decade and leading digits are put on one scale that is continuous where the decade changes.
    """
    s = F.col(score)
    decade = F.floor(F.log10(s))
    return F.when(s > 0, F.round((decade * 9 + s / F.pow(F.lit(10.0), decade)) * 10**DIGITS).cast("bigint")).otherwise(F.lit(-(10**18)).cast("bigint"))


@dataclass(frozen=True)
class Term:
    """One factor of the product: a path column summed over the words, raised to ``exponent``."""

    name: str
    column: str
    exponent: float


SIZE = Term("size", "len", -1.0)
IMPORTANCE = Term("importance", "pr", 1.0)
TEXT_MATCH = Term("text_match", "sim", 1.0)


@dataclass(frozen=True)
class ScoreSpec:
    """Factors of a tree's score and how trees add up to a pattern: ``sum``, ``avg``, ``max`` or ``count``."""

    terms: tuple[Term, ...] = field(default=(SIZE, IMPORTANCE, TEXT_MATCH))
    agg: str = "sum"

    def __post_init__(self) -> None:
        if self.agg not in ("sum", "avg", "max", "count"):
            raise ValueError(f"unknown aggregate {self.agg!r}")

    @property
    def columns(self) -> list[str]:
        return list(dict.fromkeys(t.column for t in self.terms))

    def tree_score(self) -> Column:
        """Product over the summed columns of one subtree."""
        out: Column | None = None
        for t in self.terms:
            c = F.col(t.column).cast("double")
            factor = c if t.exponent == 1 else F.lit(1.0) / c if t.exponent == -1 else F.pow(c, F.lit(t.exponent))
            out = factor if out is None else out * factor
        return F.lit(1.0) if out is None else out

    def pattern_score(self, scale: Column | None = None) -> Column:
        """Aggregate over a pattern's trees; ``scale`` corrects sums and counts of a sample."""
        s = F.col("tree_score")
        out = {"sum": F.sum(s), "avg": F.avg(s), "max": F.max(s), "count": F.count(s).cast("double")}[self.agg]
        return out * scale if scale is not None and self.agg in ("sum", "count") else out


def exponents(z1: float = -1.0, z2: float = 1.0, z3: float = 1.0, agg: str = "sum") -> ScoreSpec:
    """The three usual factors with the given exponents; a zero leaves its factor out."""
    chosen = [Term(t.name, t.column, z) for t, z in ((SIZE, z1), (IMPORTANCE, z2), (TEXT_MATCH, z3)) if z]
    return ScoreSpec(tuple(chosen), agg)
