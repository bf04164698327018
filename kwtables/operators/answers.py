"""Table answers: one row for each subtree of a pattern, one column for each node or matched edge of the pattern."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.scoring import order_key
from .index import PathIndex
from .search import Query, root_expansion


def answer_columns(index: PathIndex, pattern_ids: list[int], names: str = "qualified") -> list[tuple[str, int, int]]:
    """(name, word, place) of every column in order; edges that several words share give one column.

    The driver reads the pattern's own dictionary rows, one for each word. A column is named by its end's type, or by
    ``type.attribute.type`` for the edge that leads there; a matched edge is named without the type at its end.
    """
    rows = {r["pattern_id"]: r for r in index.patterns.where(F.col("pattern_id").isin(list(set(pattern_ids)))).collect()}
    types = {r["type_id"]: r["type_name"] for r in index.graph.types.collect()}
    attrs = {r["attr_id"]: r["attr_name"] for r in index.graph.attrs.collect()}
    out: list[tuple[str, int, int]] = []
    seen: set[tuple] = set()
    used: dict[str, int] = {}
    for word, pid in enumerate(pattern_ids, 1):
        labels = rows[pid]["labels"]
        for place in range(1, rows[pid]["len"] + 1):
            prefix = tuple(labels[: 2 * place - 1])
            if prefix in seen:
                continue
            if len(labels) >= 2 * place - 1:
                seen.add(prefix)
            end = types[labels[2 * place - 2]] if 2 * place - 1 <= len(labels) else None
            if place == 1:
                name = end
            else:
                source, attr = types[labels[2 * place - 4]], attrs[labels[2 * place - 3]]
                name = f"{source}.{attr}" + (f".{end}" if end is not None else "") if names == "qualified" else attr
            used[name] = used.get(name, 0) + 1
            out.append((name if used[name] == 1 else f"{name} ({used[name]})", word, place))
    return out


def answer_table(index: PathIndex, q: Query, pattern_ids: list[int], names: str = "qualified", with_ids: bool = False) -> DataFrame:
    """Rows of one pattern with the texts of their nodes, best subtree first by ``tree_score``, then by its nodes.

    Cells are joined with the texts by node and gathered again by the subtree's own nodes, so a task that runs again finds
    the same rows.
    """
    chosen = root_expansion(index, q, return_trees=True, pattern_ids=pattern_ids)
    columns = answer_columns(index, pattern_ids, names)
    # a pattern's subtree is known by the nodes of its paths; equal subtrees (from repeated edges) are counted and written out again
    key = F.flatten(F.array(*(F.col(f"nodes{w}") for w in range(1, len(q.words) + 1))))
    cells = chosen.select("tree_score", key.alias("nodes"), F.array(*(F.get(f"nodes{w}", F.lit(i - 1)) for _, w, i in columns)).alias("cells"))
    best_first = [order_key("tree_score").desc(), F.asc("nodes")]
    if with_ids:
        return cells.orderBy(*best_first).select("tree_score", *(F.col("cells")[i].alias(n) for i, (n, _, _) in enumerate(columns)))
    chosen_labels = index.patterns.where(F.col("pattern_id").isin(list(set(pattern_ids)))).select("labels").collect()  # a row for each word
    texts = index.graph.texts([r["labels"] for r in chosen_labels])
    once = cells.groupBy("nodes", "cells").agg(F.max("tree_score").alias("tree_score"), F.count(F.lit(1)).alias("times"))
    long = once.select("nodes", "tree_score", "times", F.posexplode("cells").alias("at", "node_id")).join(texts, "node_id", "left")
    wide = long.groupBy("nodes").agg(F.max("tree_score").alias("tree_score"), F.max("times").alias("times"), F.map_from_entries(F.collect_list(F.struct("at", "text"))).alias("by_place"))
    every = wide.withColumn("time", F.explode(F.sequence(F.lit(1), F.col("times")))).orderBy(*best_first)
    return every.select("tree_score", *(F.element_at("by_place", F.lit(i)).alias(n) for i, (n, _, _) in enumerate(columns)))


def answer_tables(index: PathIndex, q: Query, result: DataFrame, n: int) -> dict[int, DataFrame]:
    """Tables of the n best patterns by rank; n small rows reach the driver."""
    top = result.orderBy("rank").limit(n).select("rank", "pattern_ids").collect()
    return {r["rank"]: answer_table(index, q, r["pattern_ids"]) for r in top}


def sample_rows(trees: DataFrame, q: Query, n: int = 3) -> DataFrame:
    """``root_type, p1.., roots``: the roots of the n best subtrees of each pattern, a bounded list."""
    w = Window.partitionBy("root_type", *q.ids).orderBy(order_key("tree_score").desc(), "root")
    return trees.withColumn("place", F.row_number().over(w)).where(F.col("place") <= n).groupBy("root_type", *q.ids).agg(F.array_sort(F.collect_list("root")).alias("roots"))


def refine(answer: DataFrame, predicate: str | Column) -> DataFrame:
    """Rows of a table answer that satisfy a SQL predicate or column: comparisons, LIKE, patterns, null tests."""
    return answer.where(predicate)
