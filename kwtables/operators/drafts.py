"""Earlier variants of the methods: searches without the index, and the path-group search with early stop."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.graph import KnowledgeGraph
from .index import PathIndex
from .lineage import store
from .search import Query, backward_postings, enumerate_then_group, must_check, pattern_product, typed_topk


def online_index(graph: KnowledgeGraph, q: Query, d: int, nearest_match_only: bool) -> PathIndex:
    """Postings of one query's words, gathered by backward walks, in the place of a stored index."""
    postings, patterns = backward_postings(graph, q, d, nearest_match_only)
    # subtrees of a walked graph are always checked: to find the check idle, every edge would be read
    facts = {"check": True} if graph.parts is not None else {}
    return PathIndex(graph, d, paths=graph.nodes.limit(0), patterns=store(patterns), full=store(postings), facts=facts)


def draft_backward(graph: KnowledgeGraph, q: Query, d: int, k: int | None = 100, nearest_match_only: bool = True) -> DataFrame:
    """Backward search that stops at the nearest match, one grouping for all subtrees."""
    return enumerate_then_group(graph, q, d, k, nearest_match_only)


def draft_backward_typed(graph: KnowledgeGraph, q: Query, d: int, k: int = 100, nearest_match_only: bool = True) -> DataFrame:
    """The same with one grouping for each root type and k kept of each."""
    return typed_topk(online_index(graph, q, d, nearest_match_only), q, k)


def draft_sampled(graph: KnowledgeGraph, q: Query, d: int, k: int = 100, threshold: float = 1e5, rate: float = 0.1, seed: int = 0, nearest_match_only: bool = True) -> DataFrame:
    """Typed backward search that samples roots of heavy types and scores their leaders exactly."""
    return typed_topk(online_index(graph, q, d, nearest_match_only), q, k, threshold, rate, seed)


def draft_path_groups(index: PathIndex, q: Query, k: int | None = 100, nearest_match_only: bool = True) -> DataFrame:
    """Materialised path groups by root type, intersected list by list with empty prefixes dropped."""
    if not nearest_match_only:
        return pattern_product(index, q, k, prune="prefix")
    postings = index.postings(list(q.words))
    check = must_check(index, q, None)  # fewer paths can meet no more than all of them
    return pattern_product(replace(index, full=nearest_only(postings, index.graph), facts={}), q, k, prune="prefix", check=check)


def nearest_only(postings: DataFrame, graph: KnowledgeGraph) -> DataFrame:
    """Postings whose inner nodes (neither the root nor a matched end) do not hold the word."""
    from .index import schema_words, text_words

    types = F.broadcast(schema_words(graph.types, "type_id").select("word", "type_id"))
    held = text_words(graph).select("word", "node_id").unionByName(graph.nodes.select("node_id", "type_id").join(types, "type_id").select("word", "node_id")).distinct()
    held = held.join(F.broadcast(postings.select("word").distinct()), "word", "left_semi")
    numbered = postings.withColumn("posting", F.struct("pattern_id", "nodes", "attrs"))
    inner = numbered.where("len > 2").select("word", "posting", F.explode(F.slice("nodes", F.lit(2), F.col("len") - 2)).alias("node_id"))
    passing = inner.join(held, ["word", "node_id"], "left_semi").select("word", "posting").distinct()
    return numbered.join(passing, ["word", "posting"], "left_anti").select(postings.columns)
