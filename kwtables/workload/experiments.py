"""Experiments over any graph: cost of the index, times of the methods, sampling, single subtrees against patterns.

Each runs searches one after the other and returns its measurements as a small DataFrame; ``__main__`` runs them all.
"""

from __future__ import annotations

import argparse
import itertools
import json
import time
from collections.abc import Callable, Iterable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import measures
from ..operators import answers, search
from ..operators.index import PathIndex, build_index
from ..operators.search import Query
from ..sources.graph import KnowledgeGraph, build_graph, induced_subgraph
from . import query_sets

Method = Callable[[PathIndex, Query, int], DataFrame]

METHODS: dict[str, Method] = {
    "pattern_product": lambda ix, q, k: search.pattern_product(ix, q, k),
    "pattern_product_unpruned": lambda ix, q, k: search.pattern_product(ix, q, k, prune="none"),
    "root_expansion": lambda ix, q, k: search.root_expansion(ix, q, k),
    "typed_topk": lambda ix, q, k: search.typed_topk(ix, q, k),
    "baseline": lambda ix, q, k: search.enumerate_then_group(ix.graph, q, ix.d, k),
}


def query_of(words: str, validity: str = "tree") -> Query:
    return Query(tuple(words.split()), validity=validity)


def seconds(df: DataFrame) -> tuple[float, int]:
    began = time.time()
    rows = len(df.collect())  # k rows at most
    return time.time() - began, rows


def index_bytes(index: PathIndex) -> int:
    """Size of the stored postings (or paths), from file listings."""
    files = (index.full if index.full is not None else index.paths).inputFiles()
    if not files:
        return 0
    return index.patterns.sparkSession.read.format("binaryFile").load(files).select(F.sum("length")).first()[0] or 0


def index_cost(graph: KnowledgeGraph, depths: Iterable[int]) -> DataFrame:
    """Entries, predicted cost, seconds and bytes of the index for each d."""
    rows, spark = [], graph.nodes.sparkSession
    for d in depths:
        ix = build_index(graph, d, "full")
        c = ix.cost().first()
        rows.append((d, c["paths"], c["postings"], c["node_cost"] + c["edge_cost"], round(ix.build_seconds, 3), index_bytes(ix)))
    return spark.createDataFrame(rows, "d int, paths bigint, postings bigint, cost bigint, build_s double, bytes bigint")


def times(index: PathIndex, queries: Iterable[str], methods: Iterable[str] = tuple(METHODS), k: int = 100) -> DataFrame:
    """``d, query, m, n_patterns, n_trees, method, seconds`` for each query and method."""
    rows, spark = [], index.patterns.sparkSession
    for words in queries:
        q = query_of(words)
        n_patterns = search.count_patterns(index, q).first()[0]
        n_trees = search.subtree_counts(index, q, None).first()["n_trees"]
        for name in methods:
            s, _ = seconds(METHODS[name](index, q, k))
            rows.append((index.d, words, len(q.words), n_patterns, n_trees, name, s))
    return spark.createDataFrame(rows, "d int, query string, m int, n_patterns bigint, n_trees double, method string, seconds double")


def by_patterns(measured: DataFrame) -> DataFrame:
    """Least, geometric mean and greatest time by method and power of ten of the patterns."""
    return measures.time_report(measured.withColumn("group", measures.log_group(F.col("n_patterns"))), ["d", "method", "group"])


def by_subtrees(measured: DataFrame) -> DataFrame:
    return measures.time_report(measured.withColumn("group", measures.log_group(F.col("n_trees"))), ["d", "method", "group"])


def scaling(graph: KnowledgeGraph, queries: list[str], fractions: Iterable[float], by: str = "entity", d: int = 3, methods: Iterable[str] = ("pattern_product", "typed_topk")) -> DataFrame:
    """Mean seconds by method on induced parts of the graph."""
    rows, spark = [], graph.nodes.sparkSession
    for f in fractions:
        part = induced_subgraph(graph, f, 1, by).stored()
        ix = build_index(part, d, "full")
        n = part.nodes.count()
        for name in methods:
            rows.append((f, n, name, sum(seconds(METHODS[name](ix, query_of(w), 100))[0] for w in queries) / len(queries)))
    return spark.createDataFrame(rows, "fraction double, nodes bigint, method string, seconds double")


def varying_k(index: PathIndex, queries: list[str], ks: Iterable[int] = (10, 20, 50, 100), methods: Iterable[str] = ("pattern_product", "typed_topk")) -> DataFrame:
    rows = [(k, name, seconds(METHODS[name](index, query_of(w), k))[0]) for k in ks for name in methods for w in queries]
    return index.patterns.sparkSession.createDataFrame(rows, "k int, method string, seconds double").groupBy("k", "method").agg(F.avg("seconds").alias("seconds"))


def sampling(index: PathIndex, queries: list[str], lambdas: Iterable[float], rhos: Iterable[float], k: int = 100, seeds: Iterable[int] = (1,)) -> DataFrame:
    """Seconds, precision and speed-up over the pattern product for each threshold, rate and seed."""
    rows, spark = [], index.patterns.sparkSession
    for words in queries:
        q = query_of(words)
        base, _ = seconds(search.pattern_product(index, q, k))
        began = time.time()
        truth = {tuple(r["pattern_ids"]) for r in search.typed_topk(index, q, k).collect()}
        exact_s = time.time() - began
        for lam in lambdas:
            for rho, seed in itertools.product(rhos, seeds):
                began = time.time()
                found = {tuple(r["pattern_ids"]) for r in search.typed_topk(index, q, k, lam, rho, seed).collect()}
                s = time.time() - began
                rows.append((words, float(lam), rho, seed, s, exact_s, base, len(truth & found) / max(1, min(k, len(truth))), len(truth & found) / k))
    return spark.createDataFrame(rows, "query string, lam double, rho double, seed int, seconds double, exact_s double, product_s double, precision double, precision_of_k double").withColumn("speedup", F.col("product_s") / F.col("seconds"))


def over_seeds(sampled: DataFrame) -> DataFrame:
    """Means over the seeds of each query, threshold and rate."""
    return sampled.groupBy("query", "lam", "rho").agg(*(F.avg(c).alias(c) for c in ("seconds", "exact_s", "product_s", "precision", "speedup"))).orderBy("query", "lam", "rho")


def drawn_queries(index: PathIndex, per_m: int, most: int, mode: str = "rooted") -> list[str]:
    """Texts of ``per_m`` queries of each length 1..most."""
    return [r["words"] for r in query_sets.make_queries(index, per_m, most, mode).orderBy("m", "i").collect()]  # most * per_m rows


def single_against_patterns(index: PathIndex, queries: list[str], ks: Iterable[int] = (10, 50, 100)) -> DataFrame:
    """Mean coverage, novelty and share of single-tree patterns for each k."""
    out = None
    for words in queries:
        q = query_of(words)
        every = search.root_expansion(index, q)
        for k in ks:
            single, top = search.individual_topk(index, q, k), search.typed_topk(index, q, k)
            row = measures.coverage(single, top).crossJoin(measures.novelty(single, top)).crossJoin(measures.singular_share(single, every).select("share")).select(F.lit(k).alias("k"), "coverage", "novelty", "share")
            out = row if out is None else out.unionByName(row)
    return out.groupBy("k").agg(F.avg("coverage").alias("coverage"), F.avg("novelty").alias("novelty"), F.avg("share").alias("singular"))


def quality_by_depth(graph: KnowledgeGraph, depths: Iterable[int], judged: Iterable[tuple[str, str]] = query_sets.JUDGED) -> DataFrame:
    """Mean rank of the intended reading of judged queries, for each d."""
    rows, spark = [], graph.nodes.sparkSession
    for d in depths:
        ix = build_index(graph, d, "full")
        for words, label in judged:
            found = search.typed_topk(ix, query_of(words), 1000).where(F.col("label") == label).select("rank").first()
            rows.append((d, words, found[0] if found else None))
    return measures.mean_rank(spark.createDataFrame(rows, "d int, query string, position int"), ["d"])


def case_study(index: PathIndex, words: str = "large widget", k: int = 3) -> dict[str, list]:
    """The best single subtrees beside the best pattern's table."""
    q = query_of(words)
    top = search.typed_topk(index, q, 1).first()
    single = search.individual_topk(index, q, k)
    return {"pattern": [top["label"], top["n_trees"]], "rows": [list(r) for r in answers.answer_table(index, q, top["pattern_ids"]).limit(5).collect()], "single": [[r["tree_score"], r["root"]] for r in single.collect()]}


def main() -> None:
    parser = argparse.ArgumentParser(description=__doc__)
    parser.add_argument("--sf-dir", default="/root/testdata/sf0.01")
    parser.add_argument("--master", default="local[8]")
    parser.add_argument("--per-m", type=int, default=0, help="queries of each length 1..10 drawn for times by patterns and subtrees (0: the named ones)")
    parser.add_argument("--seeds", type=int, default=5, help="runs of each sampled search")
    args = parser.parse_args()
    spark = SparkSession.builder.master(args.master).config("spark.sql.shuffle.partitions", "16").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    show = lambda name, df: print(json.dumps({"experiment": name, "rows": [[round(x, 4) if isinstance(x, float) else x for x in r] for r in df.collect()], "columns": df.columns}), flush=True)
    forward = build_graph(spark, args.sf_dir, "forward").stored()
    many = build_graph(spark, args.sf_dir, "many_types").stored()
    show("index cost, forward", index_cost(forward, (2, 3, 4)))
    show("index cost, many types", index_cost(many, (2, 3)))
    f3, m3 = build_index(forward, 3, "full"), build_index(many, 3, "full")
    seeds = range(1, args.seeds + 1)
    if args.per_m:
        linked = build_graph(spark, args.sf_dir, "linked").stored()
        built = [build_index(many, 2, "full"), m3, build_index(linked, 2, "full"), build_index(linked, 3, "full")]
        measured = reduce(DataFrame.unionByName, [times(ix, drawn_queries(ix, args.per_m, 10)) for ix in built])
    else:
        measured = times(m3, query_sets.MANY).unionByName(times(f3, query_sets.NAMED[:8]))
    measured = spark.createDataFrame(measured.collect(), measured.schema)
    show("times by patterns", by_patterns(measured))
    show("times by subtrees", by_subtrees(measured))
    show("speed-up over the baseline", measures.speedup(measured, "baseline", ["d", "query"]).groupBy("method").agg(F.exp(F.avg(F.ln("speedup"))).alias("speedup")))
    show("share of entities", scaling(forward, ["large widget", "urgent automobile"], [i / 10 for i in range(1, 11)]))
    show("share of types", scaling(many, ["large widget"], (0.4, 0.7, 1.0), "type"))
    show("k", varying_k(m3, list(query_sets.MANY[:2]), range(10, 101, 10)))
    show("threshold", over_seeds(sampling(m3, [query_sets.MANY[3]], (0, 1e2, 1e3, 1e4), (0.01, 0.1), seeds=seeds)))
    show("rate", over_seeds(sampling(m3, [query_sets.MANY[3]], (1e3,), (0.05, 0.1, 0.2, 0.5, 1.0), seeds=seeds)))
    show("threshold, heavy", over_seeds(sampling(f3, list(query_sets.HEAVY), (0, 1e5, 1e7), (0.01, 0.1), seeds=seeds)))
    show("rate, heavy", over_seeds(sampling(f3, list(query_sets.HEAVY), (1e5,), (0.01, 0.05, 0.1, 0.2, 0.5), seeds=seeds)))
    show("single subtrees", single_against_patterns(m3, list(query_sets.MANY[:2])))
    show("mean rank", quality_by_depth(forward, (2, 3, 4)))
    print(json.dumps({"experiment": "case study", "result": case_study(f3)}), flush=True)
    spark.stop()


if __name__ == "__main__":
    main()
