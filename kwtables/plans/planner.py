"""Planning a keyword search: words are parsed, rewrite rules pick what to run, a lazy result comes back."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.scoring import ScoreSpec
from ..functions.text import normalise, tokenize
from ..operators import drafts, search
from ..operators.index import PathIndex
from ..operators.search import Query

METHODS = ("enumerate_then_group", "pattern_product", "root_expansion", "typed_topk", "individual_topk", "factorised", "draft_backward", "draft_backward_typed", "draft_path_groups", "draft_sampled")


@dataclass(frozen=True)
class SearchPlan:
    query: Query
    method: str
    k: int | None = 100
    lam: float = float("inf")
    rho: float = 1.0
    seed: int = 0
    check: bool | None = None
    notes: tuple[str, ...] = field(default=())


def parse_query(index: PathIndex, text: str, score: ScoreSpec | None = None, validity: str = "tree", synonyms: DataFrame | None = None, stemmed: bool = False) -> Query:
    """Words of ``text`` in order, as a set, through the same normalisation as the index (or the one given)."""
    spark = index.patterns.sparkSession
    synonyms, stemmed = synonyms if synonyms is not None else index.synonyms, stemmed or index.stemmed
    words = spark.range(1).select(F.posexplode(tokenize(F.lit(text))).alias("pos", "word"))
    if synonyms is not None or stemmed:
        words = normalise(words, "word", synonyms, stemmed)
    found = [r["word"] for r in words.orderBy("pos").collect()]  # a query's words
    return Query(tuple(found), score or ScoreSpec(), validity)


def plan(index: PathIndex, q: Query, method: str = "typed_topk", k: int | None = 100, lam: float = float("inf"), rho: float = 1.0, seed: int = 0, measure: bool = True) -> SearchPlan:
    """Rewrites: words by list size (rarest first joins least), no tree check where the schema proves it idle, and closed-form
    scores where they give the same result. Pattern ids of the result stay in the words' given order."""
    if method not in METHODS:
        raise ValueError(f"unknown method {method!r}")
    out = SearchPlan(q, method, k, lam, rho, seed)
    if not measure:
        return out
    if len(q.words) > 2:
        out = replace(out, query=replace(q, order=tuple(join_order(index, q))), notes=("rarest words first",))
    if q.validity == "tree" and not search.tree_check_needed(index):
        out = replace(out, check=False, notes=(*out.notes, "tree check left out"))
    if search.has_closed_form(q) and (q.validity == "product" or out.check is False) and method in ("root_expansion", "typed_topk") and rho >= 1.0:
        out = replace(out, method="factorised", notes=(*out.notes, "scores factorised"))
    return out


def join_order(index: PathIndex, q: Query) -> list[str]:
    """Words from the shortest posting list to the longest; a word's list is measured once for an index."""
    sizes = index.facts.setdefault("sizes", {})
    new = [w for w in q.words if w not in sizes]
    if new:
        found = {r["word"]: r["count"] for r in index.postings(new).groupBy("word").count().collect()}
        sizes.update((w, found.get(w, 0)) for w in new)
    return sorted(q.words, key=lambda w: (sizes[w], w))


def run(index: PathIndex, p: SearchPlan) -> DataFrame:
    q, g, d = p.query, index.graph, index.d
    if p.method == "enumerate_then_group":
        return search.enumerate_then_group(g, q, d, p.k)
    if p.method == "pattern_product":
        return search.pattern_product(index, q, p.k, check=p.check)
    if p.method == "root_expansion":
        return search.root_expansion(index, q, p.k, check=p.check)
    if p.method == "typed_topk":
        return search.typed_topk(index, q, p.k, p.lam, p.rho, p.seed, check=p.check)
    if p.method == "individual_topk":
        return search.individual_topk(index, q, p.k or 100)
    if p.method == "factorised":
        return search.factorised_scores(index, q, p.k)
    if p.method == "draft_backward":
        return drafts.draft_backward(g, q, d, p.k)
    if p.method == "draft_backward_typed":
        return drafts.draft_backward_typed(g, q, d, p.k or 100)
    if p.method == "draft_path_groups":
        return drafts.draft_path_groups(index, q, p.k)
    return drafts.draft_sampled(g, q, d, p.k or 100, p.lam if p.lam != float("inf") else 1e5, p.rho if p.rho < 1 else 0.1, p.seed)


def search_words(index: PathIndex, text: str, k: int | None = 100, method: str = "typed_topk", score: ScoreSpec | None = None, validity: str = "tree", **options) -> DataFrame:
    """Ranked tree patterns of height at most the index's d for the words of ``text``; ``k=None`` gives all."""
    return run(index, plan(index, parse_query(index, text, score, validity), method, k, **options))
