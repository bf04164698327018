"""Headline timings on local[$BENCH_CPUS] at $BENCH_SF_DIR; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import tempfile
import time

os.environ.setdefault("PYSPARK_PYTHON", sys.executable)


def main() -> None:
    from pyspark.sql import SparkSession

    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    folder = tempfile.mkdtemp(prefix="bench")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", str(2 * int(cpus)))
        .config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "12g"))
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.local.dir", folder)
        .config("spark.checkpoint.dir", f"{folder}/shared")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")

    from kwtables.operators import search
    from kwtables.operators.index import build_index
    from kwtables.operators.rank import pagerank
    from kwtables.operators.search import Query
    from kwtables.plans import planner
    from kwtables.sources.graph import build_graph

    times: dict[str, float] = {}
    notes: dict[str, object] = {}

    def timed(name: str, work):
        began = time.time()
        out = work()
        times[name] = round(time.time() - began, 3)
        return out

    for profile in ("forward", "many_types"):
        graph = timed(f"graph_{profile}", lambda p=profile: build_graph(spark, sf_dir, p).stored())
        for d in (2, 3):
            index = timed(f"index_{profile}_d{d}", lambda g=graph, d=d: build_index(g, d, "full"))
            notes[f"postings_{profile}_d{d}"] = index.full.count()
        if profile == "forward":
            timed("rank_forward", lambda g=graph: pagerank(g).count())
            heavy = Query(("order", "status", "priority", "customer", "nation"))
            timed("planned_forward_heavy", lambda i=index: planner.run(i, planner.plan(i, heavy, k=100)).collect())
            four = Query(("order", "urgent", "automobile", "nation"))
        else:
            four = Query(("large", "widget", "urgent", "high"))
        words = " ".join(four.words)
        found = {}
        for method, work in (
            ("pattern_product", lambda i=index, q=four: search.pattern_product(i, q, 100)),
            ("pattern_product_unpruned", lambda i=index, q=four: search.pattern_product(i, q, 100, prune="none")),
            ("root_expansion", lambda i=index, q=four: search.root_expansion(i, q, 100)),
            ("typed_topk", lambda i=index, q=four: search.typed_topk(i, q, 100)),
            ("typed_topk_sampled", lambda i=index, q=four: search.typed_topk(i, q, 100, 1e4, 0.1, 1)),
            ("baseline", lambda g=graph, q=four: search.enumerate_then_group(g, q, 3, 100)),
        ):
            rows = timed(f"{method}_{profile}", lambda w=work: w().collect())
            found[method] = {r["label"]: r["n_trees"] for r in rows}
        exact = found["root_expansion"]
        notes[f"agree_{profile}"] = all(found[m] == exact for m in ("pattern_product", "pattern_product_unpruned", "typed_topk", "baseline"))
        notes[f"precision_{profile}"] = round(len(set(exact) & set(found["typed_topk_sampled"])) / max(1, len(exact)), 3)
        notes[f"query_{profile}"] = words

    try:
        from kwtables.llm.queries import queries as llm_queries
    except ImportError:
        llm_queries = dict
    for name, query in llm_queries().items():
        timed(name, lambda q=query: q(spark, sf_dir).write.format("noop").mode("overwrite").save())
    print(json.dumps({"metric": "total of headline queries", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": sf_dir.rstrip("/").split("sf")[-1], "notes": notes}), flush=True)
    spark.stop()


if __name__ == "__main__":
    main()
