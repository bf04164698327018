"""The path index: every simple path of up to d nodes, its pattern, and the words at its end.

``split`` keeps the words of types and attributes with the schema and joins them by pattern when a query asks (half of
all postings are such words, and a pattern implies them); ``full`` writes every posting out. Both give the same postings.
Two layouts serve the two search directions: by word, pattern, root and by root, word, pattern.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.patterns import path_length, path_pattern
from ..functions.text import normalise
from ..sources.graph import SCHEMA_ROWS, KnowledgeGraph
from .lineage import SALTS, store

POSTING_COLUMNS = ["word", "pattern_id", "root", "root_type", "nodes", "attrs", "len", "pr", "sim"]


def enumerate_paths(graph: KnowledgeGraph, d: int, roots: DataFrame | None = None) -> DataFrame:
    """``root, tail, nodes, attrs, labels, len, tail_pr, prev_pr`` of every simple path with 1..d nodes.

    Breadth-wise: each level joins the last one's tails with the edges, so a level is one shuffle; a hub's edges are
    one join key, which adaptive execution splits.
    """
    nodes = graph.ranked_nodes()
    seed = nodes if roots is None else nodes.join(roots.select(F.col("root").alias("node_id")).distinct(), "node_id", "left_semi")
    level = seed.select(F.col("node_id").alias("root"), F.col("node_id").alias("tail"), F.array("node_id").alias("nodes"), F.array().cast("array<int>").alias("attrs"), F.array("type_id").alias("labels"), F.lit(1).alias("len"), F.col("pr").alias("tail_pr"), F.lit(None).cast("double").alias("prev_pr"))
    out = level
    steps = graph.edges.join(nodes.select(F.col("node_id").alias("dst"), F.col("type_id").alias("dst_type"), F.col("pr").alias("dst_pr")), "dst").select("src", "attr_id", "dst", "dst_type", "dst_pr")
    for n in range(2, d + 1):
        level = level.join(steps, level["tail"] == steps["src"]).where(~F.array_contains("nodes", F.col("dst"))).select("root", F.col("dst").alias("tail"), F.concat("nodes", F.array("dst")).alias("nodes"), F.concat("attrs", F.array("attr_id")).alias("attrs"), F.concat("labels", F.array("attr_id", "dst_type")).alias("labels"), F.lit(n).alias("len"), F.col("dst_pr").alias("tail_pr"), F.col("tail_pr").alias("prev_pr"))
        out = out.unionByName(level)
    return out


def pattern_dictionary(paths: DataFrame, graph: KnowledgeGraph) -> DataFrame:
    """``pattern_id, labels, label, root_type, len, ends_on_edge`` of every path pattern, ids in order of the label text.

    The ids come from a sort of the distinct patterns alone: a table of the schema's size.
    """
    node = paths.select(path_pattern(F.col("labels"), False).alias("labels"), F.lit(False).alias("ends_on_edge")).distinct()
    edge = node.where(F.size("labels") > 1).select(path_pattern(F.col("labels"), True).alias("labels"), F.lit(True).alias("ends_on_edge")).distinct()
    every = node.unionByName(edge)
    names = F.broadcast(graph.types.agg(F.map_from_entries(F.collect_list(F.struct("type_id", "type_name"))).alias("type_names")))
    attr_names = F.broadcast(graph.attrs.agg(F.map_from_entries(F.collect_list(F.struct("attr_id", "attr_name"))).alias("attr_names")))
    text = F.array_join(F.transform("labels", lambda x, i: F.when(i % 2 == 0, F.element_at("type_names", x)).otherwise(F.element_at("attr_names", x))), ".")
    named = every.crossJoin(names).crossJoin(attr_names).select("labels", "ends_on_edge", text.alias("label"))
    ids = F.row_number().over(Window.orderBy("label", "ends_on_edge", "labels"))
    return named.select(ids.cast("int").alias("pattern_id"), "labels", "label", F.col("labels")[0].alias("root_type"), path_length(F.col("labels")).alias("len"), "ends_on_edge")


def text_words(graph: KnowledgeGraph) -> DataFrame:
    """``word, node_id, sim`` for words of descriptions."""
    return graph.nodes.select(F.explode("tokens").alias("word"), "node_id", (F.lit(1.0) / F.size("tokens")).alias("sim"))


def schema_words(table: DataFrame, ident: str) -> DataFrame:
    """``word, <ident>, sim`` for words of type or attribute names."""
    return table.select(F.explode("tokens").alias("word"), ident, (F.lit(1.0) / F.size("tokens")).alias("sim"))


@dataclass(frozen=True)
class PathIndex:
    """``paths(path columns, node_pattern, edge_pattern)`` with the graph's words; ``full`` holds all postings if materialised."""

    graph: KnowledgeGraph
    d: int
    paths: DataFrame
    patterns: DataFrame
    full: DataFrame | None = None
    build_seconds: float = 0.0
    #: How words were normalised; queries are normalised alike.
    synonyms: DataFrame | None = None
    stemmed: bool = False
    #: What the planner found out about the index, once.
    facts: dict = field(default_factory=dict, compare=False)

    # -- postings

    def _hits(self, words: list[str] | None, text: DataFrame, types: DataFrame, attrs: DataFrame) -> DataFrame:
        chosen: Column = F.col("word").isin(words) if words is not None else F.lit(True)
        by_type = self.graph.nodes.select("node_id", "type_id").join(F.broadcast(types.where(chosen)), "type_id").select("word", "node_id", "sim")
        node_hits = text.where(chosen).select("word", "node_id", "sim").unionByName(by_type).groupBy("word", "node_id").agg(F.max("sim").alias("sim"))
        p = self.paths
        on_node = p.join(node_hits, p["tail"] == node_hits["node_id"]).select("word", F.col("node_pattern").alias("pattern_id"), "root", F.col("labels")[0].alias("root_type"), "nodes", "attrs", "len", F.col("tail_pr").alias("pr"), "sim")
        edge_hits = F.broadcast(attrs.where(chosen))
        last = p.where("len > 1").withColumn("last_attr", F.try_element_at("attrs", F.lit(-1)))
        on_edge = last.join(edge_hits, last["last_attr"] == edge_hits["attr_id"]).select("word", F.col("edge_pattern").alias("pattern_id"), "root", F.col("labels")[0].alias("root_type"), "nodes", "attrs", "len", F.col("prev_pr").alias("pr"), "sim")
        return on_node.unionByName(on_edge)

    def postings(self, words: list[str] | None = None) -> DataFrame:
        """Postings of the given words (None: all), with the score terms of each."""
        if self.full is not None:
            return self.full if words is None else self.full.where(F.col("word").isin(words))
        return self._hits(words, text_words(self.graph), schema_words(self.graph.types, "type_id"), schema_words(self.graph.attrs, "attr_id"))

    def scan(self, words: list[str]) -> DataFrame:
        """Postings of the words of one query; roots of types that cannot reach all of them may be left out."""
        return self.postings(words)

    def list_sizes(self, words: list[str]) -> list[int]:
        """Numbers of postings of those of the words that have any."""
        return [r["count"] for r in self.postings(words).groupBy("word").count().collect()]

    def path_counts(self, words: list[str]) -> DataFrame | None:
        """``root_type, n0.., m``: numbers of roots with so many paths to each word, where they are found without postings."""
        return None

    # -- access by word and pattern, or by word and root

    def _of(self, word: str, pattern: int | None = None, root: int | None = None, root_type: int | None = None) -> DataFrame:
        out = self.postings([word])
        for name, value in (("pattern_id", pattern), ("root", root), ("root_type", root_type)):
            if value is not None:
                out = out.where(F.col(name) == value)
        return out

    def pattern_list(self, word: str, root: int | None = None, root_type: int | None = None) -> DataFrame:
        """Patterns of a word, or of a word under one root."""
        return self._of(word, root=root, root_type=root_type).select("pattern_id", "root_type").distinct()

    def roots(self, word: str, pattern: int | None = None, root_type: int | None = None) -> DataFrame:
        """Roots that reach a word, or reach it by one pattern."""
        return self._of(word, pattern, root_type=root_type).select("root", "root_type").distinct()

    def word_paths(self, word: str, pattern: int | None = None, root: int | None = None) -> DataFrame:
        """Paths to a word: by pattern and root, by root over all its patterns, or all."""
        return self._of(word, pattern, root)

    # -- sizes

    def vocabulary(self) -> DataFrame:
        """``word`` of every word that has a posting, without forming postings: each node is a path of its own, and an attribute
        is met if one of its edges is a path of two nodes."""
        g = self.graph
        typed = g.nodes.select("type_id").distinct().join(g.types, "type_id").select(F.explode("tokens").alias("word"))
        words = g.nodes.select(F.explode("tokens").alias("word")).unionByName(typed)
        if self.d > 1:
            ids = g.nodes.select("node_id")
            met = g.edges.where("src <> dst").join(ids.withColumnRenamed("node_id", "src"), "src", "left_semi").join(ids.withColumnRenamed("node_id", "dst"), "dst", "left_semi")
            words = words.unionByName(met.select("attr_id").distinct().join(g.attrs, "attr_id").select(F.explode("tokens").alias("word")))
        return words.distinct()

    def posting_sizes(self) -> DataFrame:
        """``word, entries``."""
        return self.postings().groupBy("word").agg(F.count(F.lit(1)).alias("entries"))

    def cost(self) -> DataFrame:
        """One row: paths, postings, the sum of length times words over node ends and over edge ends, seconds of building."""
        g = self.graph
        n_text = F.size(F.array_distinct(F.concat("tokens", "type_tokens")))
        ends = g.nodes.join(F.broadcast(g.types.select("type_id", F.col("tokens").alias("type_tokens"))), "type_id").select("node_id", n_text.alias("words"))
        at_node = self.paths.join(ends, self.paths["tail"] == ends["node_id"]).agg(F.count(F.lit(1)).alias("paths"), F.sum("words").alias("node_postings"), F.sum(F.col("len") * F.col("words")).alias("node_cost"))
        attr_size = F.broadcast(g.attrs.select(F.col("attr_id").alias("last_attr"), F.size("tokens").alias("words")))
        at_edge = self.paths.where("len > 1").withColumn("last_attr", F.try_element_at("attrs", F.lit(-1))).join(attr_size, "last_attr").agg(F.coalesce(F.sum("words"), F.lit(0)).alias("edge_postings"), F.coalesce(F.sum(F.col("len") * F.col("words")), F.lit(0)).alias("edge_cost"))
        return at_node.crossJoin(at_edge).select(F.lit(self.d).alias("d"), "paths", (F.col("node_postings") + F.col("edge_postings")).alias("postings"), "node_cost", "edge_cost", F.lit(self.build_seconds).alias("build_s"))

    def profile(self) -> DataFrame:
        """Paths by root type and length with subtotals."""
        named = self.patterns.join(F.broadcast(self.graph.types.select(F.col("type_id").alias("root_type"), F.col("type_name"))), "root_type")
        return self.paths.groupBy("node_pattern").agg(F.count(F.lit(1)).alias("n")).join(F.broadcast(named), F.col("node_pattern") == F.col("pattern_id")).rollup("type_name", "len").agg(F.sum("n").alias("paths"), F.countDistinct("pattern_id").alias("patterns"))

    # -- storage

    def write(self, path: str, layout: str = "pattern", buckets: int = 64) -> None:
        """All postings in one of the two sort orders, with the patterns and the graph beside them.

        ``pattern``: files by hash of word, sorted by word, pattern, root, so that a word's run is found from file
        statistics. ``root``: files by hash of root, sorted by root, word, pattern, so that joins on root read co-located runs.
        """
        if layout not in ("pattern", "root"):
            raise ValueError(f"unknown layout {layout!r}")
        keys = ["word", "pattern_id", "root"] if layout == "pattern" else ["root", "word", "pattern_id"]
        bucket = F.pmod(F.xxhash64(keys[0]), F.lit(buckets)).cast("int")
        rows = self.postings().withColumn("bucket", bucket).repartition("bucket", F.pmod(F.xxhash64("root"), F.lit(SALTS))).sortWithinPartitions("bucket", *keys)
        rows.write.mode("overwrite").partitionBy("bucket").parquet(f"{path}/postings_{layout}")
        self.patterns.write.mode("overwrite").parquet(f"{path}/patterns")
        self.paths.write.mode("overwrite").parquet(f"{path}/paths")
        for name in ("nodes", "edges", "types", "attrs"):
            getattr(self.graph, name).write.mode("overwrite").parquet(f"{path}/{name}")

    def save_bucketed(self, table: str, buckets: int = 64) -> None:
        """Postings as a table bucketed and sorted by root: joins on root need no shuffle."""
        self.postings().write.mode("overwrite").bucketBy(buckets, "root").sortBy("root", "word", "pattern_id").saveAsTable(table)

    @staticmethod
    def read(spark: SparkSession, path: str, d: int, layout: str = "pattern", buckets: int = 64) -> PathIndex:
        g = KnowledgeGraph(*(spark.read.parquet(f"{path}/{n}") for n in ("nodes", "edges", "types", "attrs")))
        return StoredIndex(g, d, spark.read.parquet(f"{path}/paths"), spark.read.parquet(f"{path}/patterns"), spark.read.parquet(f"{path}/postings_{layout}"), layout=layout, buckets=buckets)

    def register_views(self, prefix: str = "kg") -> None:
        for name, df in (("nodes", self.graph.nodes), ("edges", self.graph.edges), ("types", self.graph.types), ("attrs", self.graph.attrs), ("paths", self.paths), ("patterns", self.patterns), ("postings", self.postings())):
            df.createOrReplaceTempView(f"{prefix}_{name}")


@dataclass(frozen=True)
class StoredIndex(PathIndex):
    """An index read from files: words prune to their buckets, then to runs by statistics."""

    layout: str = "pattern"
    buckets: int = 64

    def postings(self, words: list[str] | None = None) -> DataFrame:
        out = self.full.select(*POSTING_COLUMNS) if words is None or self.layout != "pattern" else None
        if out is None:
            spark = self.full.sparkSession
            own = [r[0] for r in spark.createDataFrame([(w,) for w in words] or [("",)], "w string").select(F.pmod(F.xxhash64("w"), F.lit(self.buckets)).cast("int")).distinct().collect()]
            out = self.full.where(F.col("bucket").isin(own)).select(*POSTING_COLUMNS)
        return out if words is None else out.where(F.col("word").isin(words))


def normalised(graph: KnowledgeGraph, synonyms: DataFrame | None, stemmed: bool) -> KnowledgeGraph:
    """``graph`` with the words of entities, types and attributes in canonical form, so that variants share one posting list."""

    def mapped(table: DataFrame, ident: str) -> DataFrame:
        words = normalise(table.select(F.col(ident).alias("owner"), F.posexplode("tokens").alias("at", "word")), "word", synonyms, stemmed)
        first = words.groupBy("owner", "word").agg(F.min("at").alias("at"))
        own = first.groupBy("owner").agg(F.transform(F.array_sort(F.collect_list(F.struct("at", "word"))), lambda x: x["word"]).alias("canonical"))
        out = table.join(own, table[ident] == own["owner"], "left").withColumn("tokens", F.coalesce("canonical", F.array().cast("array<string>")))
        return out.select(table.columns)

    return replace_tables(graph, nodes=mapped(graph.nodes, "node_id"), types=mapped(graph.types, "type_id"), attrs=mapped(graph.attrs, "attr_id"))


def replace_tables(graph: KnowledgeGraph, **tables: DataFrame) -> KnowledgeGraph:
    return KnowledgeGraph(*(tables.get(n, getattr(graph, n)) for n in ("nodes", "edges", "types", "attrs", "ranks")))


def with_patterns(raw: DataFrame, patterns: DataFrame, hint: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """Enumerated paths with the ids of their patterns, ``node_pattern`` and ``edge_pattern``."""
    ids = patterns.select("labels", "pattern_id", "ends_on_edge")
    at_node = hint(ids.where(~F.col("ends_on_edge")).select("labels", F.col("pattern_id").alias("node_pattern")))
    at_edge = hint(ids.where("ends_on_edge").select(F.col("labels").alias("edge_labels"), F.col("pattern_id").alias("edge_pattern")))
    paths = raw.join(at_node, "labels")
    return paths.withColumn("edge_labels", path_pattern(F.col("labels"), True)).join(at_edge, "edge_labels", "left").drop("edge_labels")


def build_index(graph: KnowledgeGraph, d: int = 3, materialise: str = "split", stored: bool = True, synonyms: DataFrame | None = None, stemmed: bool = False, ranks: DataFrame | str | None = None) -> PathIndex:
    """Paths, patterns and (``full``) postings of ``graph`` up to ``d`` nodes.

    ``synonyms`` (word, canonical) and ``stemmed`` bring words into canonical form; a query that is parsed with the index is
    brought into the same form. ``ranks`` (node_id, pr, or "pagerank" to compute them) weighs nodes by importance; without
    it every node weighs 1, or what the graph brings.

    ``stored`` writes each once (paths by tail, postings by word, both sorted for pruning); otherwise everything stays lazy.
    """
    if materialise not in ("split", "full"):
        raise ValueError(f"unknown materialise {materialise!r}")
    began = time.time()
    if ranks is not None:
        from .rank import pagerank

        graph = graph.with_ranks(store(pagerank(graph)) if isinstance(ranks, str) else ranks)
    if synonyms is not None or stemmed:
        graph = normalised(graph, synonyms, stemmed)
        if stored:
            graph = graph.stored()
    raw = enumerate_paths(graph, d)
    if stored:
        raw = store(raw)
    patterns = pattern_dictionary(raw, graph)
    if stored:
        patterns = store(patterns)
    # the dictionary has the schema's size; it is broadcast only within a checked bound
    paths = with_patterns(raw, patterns, F.broadcast if not stored or patterns.count() <= SCHEMA_ROWS else (lambda x: x))
    index = PathIndex(graph, d, paths, patterns, synonyms=synonyms, stemmed=stemmed)
    if materialise == "full":
        full = index.postings()
        index = replace(index, full=store(full, by="word", salt="root", sort=["word", "pattern_id", "root"]) if stored else full)
    return replace(index, build_seconds=time.time() - began)
