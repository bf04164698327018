"""Measures of cost and accuracy, as small DataFrames."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def time_report(times: DataFrame, group: list[str], seconds: str = "seconds") -> DataFrame:
    """Least, geometric mean and greatest seconds of each group of queries."""
    return times.groupBy(*group).agg(F.count(F.lit(1)).alias("queries"), F.min(seconds).alias("min_s"), F.exp(F.avg(F.ln(F.greatest(F.col(seconds), F.lit(1e-9))))).alias("geomean_s"), F.max(seconds).alias("max_s"))


def log_group(count: Column) -> Column:
    """Group 10^i holds the values in [10^(i-1), 10^i); zero stays alone."""
    return F.when(count <= 0, F.lit(0)).otherwise(F.floor(F.log10(count.cast("double")) + F.lit(1e-12)).cast("int") + 1)


def precision_at_k(exact: DataFrame, approx: DataFrame, k: int) -> DataFrame:
    """``found, possible, precision, precision_of_k``: exact top patterns that the approximate answer holds."""
    truth = exact.where(F.col("rank") <= k).select("pattern_ids")
    found = truth.join(approx.where(F.col("rank") <= k).select("pattern_ids"), "pattern_ids", "left_semi").agg(F.count(F.lit(1)).alias("found"))
    total = truth.agg(F.count(F.lit(1)).alias("possible"))
    ratio = lambda n: F.when(n > 0, F.col("found") / n).otherwise(F.lit(1.0))
    return found.crossJoin(total).select("found", "possible", ratio(F.col("possible")).alias("precision"), (F.col("found") / F.lit(float(k))).alias("precision_of_k"))


def error_bound(s1: Column, s2: Column, rho: Column) -> Column:
    """Bound on the chance that a sample of rate ``rho`` swaps patterns of exact scores s1 > s2."""
    gap = (s1 - s2) / (s1 + s2)
    return F.exp(F.lit(-2.0) * gap * gap * rho * rho)


def pairwise_error(exact: DataFrame, runs: DataFrame, rho: float) -> DataFrame:
    """Observed share of runs that put the worse of two exact patterns first, beside the bound.

    ``exact(pattern_ids, score)`` and ``runs(seed, pattern_ids, score_est)`` hold a query's top patterns, so the pairs
    are those of a small table. A pattern that a run misses has estimate zero.
    """
    a, b = exact.select(F.col("pattern_ids").alias("p1"), F.col("score").alias("s1")), exact.select(F.col("pattern_ids").alias("p2"), F.col("score").alias("s2"))
    pairs = a.join(b, F.col("s1") > F.col("s2"))
    seeds = runs.select("seed").distinct()
    est = lambda p, s: runs.select("seed", F.col("pattern_ids").alias(p), F.col("score_est").alias(s))
    all_ = pairs.crossJoin(F.broadcast(seeds)).join(est("p1", "e1"), ["seed", "p1"], "left").join(est("p2", "e2"), ["seed", "p2"], "left").fillna(0.0, ["e1", "e2"])
    wrong = F.avg((F.col("e1") < F.col("e2")).cast("double")).alias("observed")
    return all_.groupBy("p1", "p2").agg(F.first("s1").alias("s1"), F.first("s2").alias("s2"), wrong).withColumn("bound", error_bound(F.col("s1"), F.col("s2"), F.lit(rho)))


def coverage(individual: DataFrame, patterns: DataFrame) -> DataFrame:
    """``covered, individual, coverage``: single top subtrees whose pattern is among the top patterns."""
    own = individual.select("pattern_ids")
    hit = own.join(patterns.select("pattern_ids").distinct(), "pattern_ids", "left_semi").agg(F.count(F.lit(1)).alias("covered"))
    return hit.crossJoin(own.agg(F.count(F.lit(1)).alias("individual"))).withColumn("coverage", F.when(F.col("individual") > 0, F.col("covered") / F.col("individual")).otherwise(F.lit(1.0)))


def novelty(individual: DataFrame, patterns: DataFrame) -> DataFrame:
    """``new, patterns, novelty``: top patterns none of whose subtrees is among the single top subtrees."""
    own = patterns.select("pattern_ids")
    new = own.join(individual.select("pattern_ids").distinct(), "pattern_ids", "left_anti").agg(F.count(F.lit(1)).alias("new"))
    return new.crossJoin(own.agg(F.count(F.lit(1)).alias("patterns"))).withColumn("novelty", F.when(F.col("patterns") > 0, F.col("new") / F.col("patterns")).otherwise(F.lit(0.0)))


def singular_share(individual: DataFrame, all_patterns: DataFrame) -> DataFrame:
    """``singular, individual, share``: single top subtrees that are the only one of their pattern."""
    own = individual.select("pattern_ids").join(all_patterns.select("pattern_ids", "n_trees"), "pattern_ids")
    return own.agg(F.sum((F.col("n_trees") == 1).cast("bigint")).alias("singular"), F.count(F.lit(1)).alias("individual")).withColumn("share", F.col("singular") / F.col("individual"))


def mean_rank(judged: DataFrame, group: list[str]) -> DataFrame:
    """Mean position of the best interpretation over judged queries (``position``; null if it was not found)."""
    return judged.groupBy(*group).agg(F.count("position").alias("found"), F.count(F.lit(1)).alias("queries"), F.avg("position").alias("mean_rank"))


def speedup(times: DataFrame, base: str, keys: list[str]) -> DataFrame:
    """Seconds of method ``base`` over those of every method, for each combination of ``keys``."""
    reference = times.where(F.col("method") == base).select(*keys, F.col("seconds").alias("base_s"))
    return times.join(reference, keys).withColumn("speedup", F.col("base_s") / F.col("seconds"))


def cost_model(n_trees: float, d: int, m: int, sizes: list[int], lam: float = float("inf"), rho: float = 1.0, types: int = 1, k: int = 100) -> dict[str, float]:
    """Operations that the running-time bounds predict for root expansion and for per-type search."""
    import math

    scanned = float(sum(sizes))
    exact = n_trees * d * m + scanned
    capped = min(lam * types, n_trees) if lam != float("inf") else n_trees
    sampled = (0.0 if lam == float("inf") else rho * n_trees * d * m) + capped * d * m + scanned + n_trees * math.log(max(k, 2))
    return {"root_expansion": exact, "typed_topk": sampled}


def score_gaps(ranked: DataFrame) -> DataFrame:
    """Each pattern's distance to the next one, its relative gap, quartile and running share of the total score."""
    by = Window.orderBy("rank")  # a query's top list, k rows
    nxt = F.lead("score").over(by)
    total = F.sum("score").over(Window.partitionBy(F.lit(1)))
    return ranked.select("rank", "score", (F.col("score") - nxt).alias("gap"), ((F.col("score") - nxt) / (F.col("score") + nxt)).alias("relative_gap"), F.ntile(4).over(by).alias("quartile"), (F.sum("score").over(by.rowsBetween(Window.unboundedPreceding, 0)) / total).alias("running_share"), F.dense_rank().over(Window.orderBy(F.desc("score"))).alias("dense"))
