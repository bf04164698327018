"""Sizes of the path index from counts of paths: no path and no posting is formed, nothing of the graph is written.

Every node carries how many paths of each number of nodes end in it; a rule's edges hand these counts on, one aggregate for each
rule. Nodes of a table keyed by row (``NodePart.plain``) are its rows: none is looked up, so their keys are not made. Where the
rules lead back to a node's own part, lengths up to three are counted from both sides of the middle node, without the paths
that return to their root. ``countable`` says which graphs this holds for; others enumerate.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.graph import KINDS, ROW_PLACES, EdgePart, KnowledgeGraph, NodePart, keyed
from .walk import few

TOTAL = "decimal(38,0)"


def _order(nodes: list[NodePart], edges: list[EdgePart]) -> list[int] | None:
    """Places of the parts, sources before ends; None if rules lead back."""
    left, out = set(range(len(nodes))), []
    while left:
        free = sorted(i for i in left if not any(e.dst == i and e.src in left for e in edges))
        if not free:
            return None
        out += free
        left -= set(free)
    return out


def countable(graph: KnowledgeGraph, d: int) -> bool:
    if graph.parts is None or graph.ranks is not None:
        return False
    nodes, edges = graph.parts
    if any(p.unique and p.plain is None and p.source[1] != "literal" for p in nodes) or any(e.src == e.dst for e in edges):
        return False
    # rows without the key that their row keys are made of are no nodes while the places of keys suffice for them
    if any(p.unkeyed.limit(ROW_PLACES).count() >= ROW_PLACES for p in nodes if p.plain is not None):
        return False
    return _order(nodes, edges) is not None or d <= 3


def _ids(p: NodePart, *more: Column) -> DataFrame:
    """``id, m`` and sums of ``more``: how many rows are the node."""
    return p.rows.groupBy(F.col("node_id").alias("id")).agg(F.count(F.lit(1)).alias("m"), *more)


def _literal(e: EdgePart) -> bool:
    return e.dst_source[1] == "literal"


def _plain(e: EdgePart, nodes: list[NodePart]) -> DataFrame:
    """``src, dst`` of a rule without made keys: the end that is a row itself, or its literal, is left null."""
    if nodes[e.src].plain is None and nodes[e.dst].plain is None:
        return e.rows
    return e.plain


class Counts:
    """``node counts`` of an acyclic schema: ``of(part)`` has ``id, m, w, n1..nd``, or for rows (and their literals) text and counts."""

    def __init__(self, graph: KnowledgeGraph, d: int) -> None:
        self.graph, self.d = graph, d
        self.nodes, self.edges = graph.parts
        self.columns = [f"n{i}" for i in range(1, d + 1)]
        self.type_tokens = {r["type_id"]: r["tokens"] for r in graph.types.collect()}
        self.attr_tokens = {r["attr_id"]: r["tokens"] for r in graph.attrs.collect()}
        self.tables: dict[int, DataFrame] = {}
        for i in _order(self.nodes, self.edges):
            self.tables[i] = self._table(i)

    def _handed(self, e: EdgePart) -> DataFrame:
        """``id, n2..nd``: counts that an edge rule's sources hand to its ends."""
        shift = [F.col(f"n{k}").alias(f"n{k + 1}") for k in range(1, self.d)]
        if self.nodes[e.src].plain is not None:
            rows = _plain(e, self.nodes).where("dst IS NOT NULL").groupBy(F.col("dst").alias("id")).agg(F.count(F.lit(1)).alias("n2"))
            return rows.select("id", *(F.col("n2") if k == 1 else F.lit(0).cast("bigint").alias(f"n{k + 1}") for k in range(1, self.d)))
        return e.rows.join(self.tables[e.src].select(F.col("id").alias("src"), *shift), "src").select(F.col("dst").alias("id"), *self.columns[1:])

    def words(self, i: int, text: Column) -> Column:
        own = self.type_tokens[self.nodes[i].type_id]
        tokens = self.nodes[i].tokens(text)
        return F.array_distinct(F.concat(tokens, F.array(*map(F.lit, own)))) if own else tokens

    def _table(self, i: int) -> DataFrame:
        p = self.nodes[i]
        zero = F.lit(0).cast("bigint")
        if p.plain is not None:  # rows are ends of no edge, their literals of one each; texts grouped
            n = 2 if p.source[1] == "literal" else 1
            rows = p.plain.groupBy("text").agg(F.count(F.lit(1)).alias("m")) if n == 2 else p.plain.agg(F.count(F.lit(1)).alias("m")).withColumn("text", F.lit("0"))
            return rows.select("text", "m", *(F.col("m").alias(c) if int(c[1:]) <= n else zero.alias(c) for c in self.columns))
        size = F.size(self.words(i, F.col("text")))
        own = _ids(p, F.sum(size).alias("w"))
        into = [self._handed(e) for e in self.edges if e.dst == i] if self.d > 1 else []
        if not into:
            return own.select("id", "m", "w", F.col("m").alias("n1"), *(zero.alias(c) for c in self.columns[1:]))
        handed = reduce(DataFrame.unionByName, into).groupBy("id").agg(*(F.sum(c).alias(c) for c in self.columns[1:]))
        both = own.join(handed, "id", "left")
        return both.select("id", "m", "w", F.col("m").alias("n1"), *((F.coalesce(c, zero) * F.col("m")).alias(c) for c in self.columns[1:]))

    def attr_of(self, i: int) -> int | None:
        """The one attribute by which the part is reached."""
        held = {e.attr_id for e in self.edges if e.dst == i}
        return held.pop() if len(held) == 1 else None

    def lengths(self) -> DataFrame:
        """``part, n1.., p1.., w1..``: paths of each length that end in the part; the same with the tail's rows, and with their words."""
        parts = []
        for i, t in self.tables.items():
            m, w = ("m", "w") if "id" in t.columns else (F.lit(1), F.size(self.words(i, F.col("text"))))
            m, w = (F.col(x) if isinstance(x, str) else x for x in (m, w))
            total = lambda x, name: F.coalesce(F.sum(x.cast(TOTAL)), F.lit(0)).cast("bigint").alias(name)
            sums = [total(F.col(c) * f, f"{kind}{c[1:]}") for c in self.columns for kind, f in (("n", F.lit(1)), ("p", m), ("w", w))]
            parts.append(t.agg(*sums).select(F.lit(i).alias("part"), "*"))
        return reduce(DataFrame.unionByName, parts)


def acyclic(graph: KnowledgeGraph) -> bool:
    nodes, edges = graph.parts
    order = _order(nodes, edges)
    if order is None or any(nodes[e.dst].plain is not None and not _literal(e) for e in edges):
        return False
    return all(len({e.attr_id for e in edges if e.dst == i}) <= 1 for i in order)


def sizes_by_depth(graph: KnowledgeGraph, depths: list[int]) -> list[tuple[int, int, int, int, int]]:
    """(d, paths, postings, node cost, edge cost) of each depth: what ``PathIndex.cost`` counts."""
    c = Counts(graph, max(depths))
    rows = c.lengths().collect()
    out = []
    for d in depths:
        paths = postings = node = edge = 0
        for r in rows:
            attr = c.attr_of(r["part"])
            at_edge = len(c.attr_tokens[attr]) if attr is not None else 0
            for n in range(1, d + 1):
                paths += r[f"p{n}"]
                node += n * r[f"w{n}"]
                postings += r[f"w{n}"] + (r[f"n{n}"] * at_edge if n > 1 else 0)
                edge += n * r[f"n{n}"] * at_edge if n > 1 else 0
        out.append((d, paths, postings, node, edge))
    return out


def posting_sizes(graph: KnowledgeGraph, d: int) -> DataFrame:
    """``word, entries`` of all postings up to ``d`` nodes. Words that are whole numbers are grouped as numbers."""
    c = Counts(graph, d)
    whole = reduce(Column.__add__, map(F.col, c.columns))
    named, numbers = [], []
    schema: list[DataFrame] = []
    for i, t in c.tables.items():
        p, attr = c.nodes[i], c.attr_of(i)
        own = c.type_tokens[p.type_id]
        if attr is not None and d > 1:
            far = reduce(Column.__add__, map(F.col, c.columns[1:]))
            met = t.agg(F.sum(far).alias("n")).where("n > 0")
            schema.append(met.select(F.explode(F.array(*map(F.lit, c.attr_tokens[attr]))).alias("word"), "n"))
        if p.digits:
            numbers.append(p.plain_keys if p.plain is not None else t.select(F.abs(F.shiftright("id", KINDS.bit_length() - 1)).alias("number"), whole.alias("n")))
            if own:
                schema.append(t.agg(F.sum(whole).alias("n")).where("n > 0").select(F.explode(F.array(*map(F.lit, own))).alias("word"), "n"))
        elif "id" in t.columns:
            texts = p.rows.groupBy(F.col("node_id").alias("id")).agg(F.collect_set("text").alias("texts"))
            words = F.array_distinct(F.flatten(F.transform(F.when(F.size("texts") > 0, F.col("texts")).otherwise(F.array(F.lit(""))), lambda x: c.words(i, x))))
            named.append(t.join(texts, "id").select(F.explode(words).alias("word"), whole.alias("n")))
        else:
            named.append(t.select(F.explode(c.words(i, F.col("text"))).alias("word"), whole.alias("n")))
    few_words = reduce(DataFrame.unionByName, [x.select("word", F.col("n").cast("bigint").alias("n")) for x in named + schema]).groupBy("word").agg(F.sum("n").alias("n"))
    as_number = F.try_cast("word", "bigint") if hasattr(F, "try_cast") else F.expr("try_cast(word AS bigint)")
    plain = as_number.isNotNull() & (as_number.cast("string") == F.col("word"))
    split = few_words.select(F.when(plain, as_number).alias("number"), F.when(~F.coalesce(plain, F.lit(False)), F.col("word")).alias("word"), "n")
    counted = reduce(DataFrame.unionByName, [x.select("number", F.lit(None).cast("string").alias("word"), F.col("n").cast("bigint").alias("n")) for x in numbers] + [split]).groupBy("number", "word").agg(F.sum("n").alias("entries"))
    return counted.select(F.coalesce("word", F.col("number").cast("string")).alias("word"), "entries").where("entries > 0")


def paths_by_length(graph: KnowledgeGraph, d: int) -> list[tuple[int, int]]:
    """(len, paths) of all simple paths."""
    if acyclic(graph):
        rows = Counts(graph, d).lengths().collect()
        out = [(n, sum(r[f"n{n}"] for r in rows)) for n in range(1, d + 1)]
    else:
        out = _both_sides(graph)[:d]
    return [x for x in out if x[1]]


def _both_sides(graph: KnowledgeGraph) -> list[tuple[int, int]]:
    nodes, edges = graph.parts
    many = [None if p.plain is not None else _ids(p) for p in nodes]

    def weighed(rows: DataFrame, by: str, part: int, name: str) -> DataFrame:
        return rows.join(few(many[part].select(F.col("id").alias(by), F.col("m").alias(name))), by)

    total = lambda x: F.coalesce(F.sum(x.cast(TOTAL)), F.lit(0)).cast(TOTAL)
    one = (sum(p.rows.count() if p.plain is None else p.plain.count() for p in nodes))
    two, three = 0, 0
    for b, p in enumerate(nodes):
        into, out = [e for e in edges if e.dst == b], [e for e in edges if e.src == b]
        if not out:
            continue
        if p.plain is not None:
            two_b, three_b = _row_middle(graph, b, into, out, many)
            two, three = two + two_b, three + three_b
            continue
        zero = F.lit(0).cast("bigint")
        sides = []
        for e in into:
            rows = _plain(e, nodes)
            rows = rows.groupBy("dst").agg(F.count(F.lit(1)).alias("x")) if nodes[e.src].plain is not None else weighed(rows, "src", e.src, "x")
            sides.append(rows.select(F.col("dst").alias("id"), F.col("x").alias("i"), zero.alias("o")))
        for e in out:
            rows = _plain(e, nodes)
            if _literal(e):  # a node's literals of one attribute are one node
                rows = rows.groupBy("src").agg((F.count(F.lit(1)) * F.count(F.lit(1))).alias("x"))
            elif nodes[e.dst].plain is not None:
                rows = rows.groupBy("src").agg(F.count(F.lit(1)).alias("x"))
            else:
                rows = weighed(rows, "dst", e.dst, "x")
            sides.append(rows.select(F.col("src").alias("id"), zero.alias("i"), F.col("x").alias("o")))
        around = reduce(DataFrame.unionByName, sides).where("id IS NOT NULL").groupBy("id").agg(F.sum("i").alias("i"), F.sum("o").alias("o"))
        row = around.join(many[b], "id").agg(total(F.col("m") * F.col("o")).alias("two"), total((F.col("m") * F.col("o")).cast(TOTAL) * F.col("i")).alias("three")).first()
        two, three = two + int(row["two"]), three + int(row["three"])
        for e in into:
            for f in out:
                if e.src == f.dst:
                    three -= _closed(e, f, nodes, many, total)
    return [(1, one), (2, two), (3, three)]


def _closed(e: EdgePart, f: EdgePart, nodes: list[NodePart], many: list, total) -> int:
    """Paths from a node over ``e`` and back over ``f``."""
    if nodes[e.src].plain is not None:  # a row has one edge of a rule, and one back
        row = _plain(e, nodes).where("dst IS NOT NULL").groupBy(F.col("dst").alias("id")).agg(F.count(F.lit(1)).alias("n")).join(many[e.dst], "id").agg(total(F.col("n") * F.col("m")).alias("n")).first()
        return int(row["n"])
    there = e.rows.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"))
    if e.src_source == f.dst_source and e.dst_source == f.src_source:
        pairs = there.withColumn("back", F.col("n"))
    else:
        back = f.rows.groupBy(F.col("dst").alias("src"), F.col("src").alias("dst")).agg(F.count(F.lit(1)).alias("back"))
        pairs = there.join(back, ["src", "dst"])
    pairs = pairs.join(few(many[e.src].select(F.col("id").alias("src"), F.col("m").alias("a"))), "src").join(few(many[e.dst].select(F.col("id").alias("dst"), F.col("m").alias("b"))), "dst")
    return int(pairs.agg(total((F.col("n") * F.col("back") * F.col("a") * F.col("a")).cast(TOTAL) * F.col("b")).alias("n")).first()["n"])


def _row_middle(graph: KnowledgeGraph, b: int, into: list[EdgePart], out: list[EdgePart], many: list) -> tuple[int, int]:
    """(paths of two nodes from the rows, paths of three nodes over the rows that do not return)."""
    nodes = graph.parts[0]
    total = lambda x: F.coalesce(F.sum(x.cast(TOTAL)), F.lit(0)).cast(TOTAL)
    rows = graph.parts[0][b].plain
    one = F.lit(1).cast("bigint")
    back = {k for k, f in enumerate(out) for e in into if f.dst_source == e.src_source and f.src_source == e.dst_source}
    far = F.lit(0).cast("bigint")
    two = 0
    for k, f in enumerate(out):
        ends = f.plain_end
        if _literal(f):
            x = F.when(ends.isNotNull(), one).otherwise(F.lit(0))
            two += rows.where(ends.isNotNull()).count()
        elif k in back:
            row = rows.groupBy(ends.alias("id")).agg(F.count(F.lit(1)).alias("n")).join(many[f.dst], "id").agg(total(F.col("n") * F.col("m")).alias("n")).first()
            two += int(row["n"])
            continue
        else:
            rows = rows.withColumn(f"end{k}", ends).join(few(many[f.dst].select(F.col("id").alias(f"end{k}"), F.col("m").alias(f"x{k}"))), f"end{k}", "left")
            x = F.coalesce(f"x{k}", F.lit(0)).cast("bigint")
            two += int(rows.agg(total(F.coalesce(f"x{k}", F.lit(0))).alias("n")).first()["n"])
        far = far + x
    three = 0
    for e in into:
        row = rows.groupBy(e.plain_end.alias("id")).agg(F.sum(far).alias("n")).join(many[e.src], "id").agg(total(F.col("n") * F.col("m")).alias("n")).first()
        three += int(row["n"])
    return two, three
