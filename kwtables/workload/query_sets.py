"""Sets of keyword queries: named, random from the vocabulary, and with words of one root."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.patterns import root_sample
from ..operators.index import PathIndex
from ..operators.lineage import store

NAMED = ("automobile", "large widget", "urgent customer", "automobile customer region", "brand nation", "order urgent automobile nation", "large brand supplier", "nation building order urgent", "order priority", "asia africa", "order status priority customer nation", "large part brand order customer nation")
MANY = ("large widget", "urgent automobile widget", "order widget automobile", "large widget urgent high", "cold ring building urgent")
HEAVY = ("large part brand order customer nation", "order status priority customer nation", "part brand order customer supplier nation status")
#: Query and the label of its intended reading.
JUDGED = (
    ("large widget", "Part | Part"),
    ("urgent automobile", "Order.order priority.Text | Order.customer.Customer.market segment.Text"),
    ("customer nation", "Customer | Customer.nation"),
    ("brand widget", "Part.brand | Part"),
    ("supplier nation", "Supplier | Supplier.nation"),
    ("order priority", "Order | Order.order priority"),
    ("nation region", "Nation | Nation.region"),
    ("order customer", "Order | Order.customer.Customer"),
    ("line status", "Lineitem.line status | Lineitem.line status"),
    ("urgent customer", "Order.order priority.Text | Order.customer.Customer"),
)


#: Words that are looked at for each query, for each word it may have.
MARGIN = 8


def _with_tail(spots: DataFrame, seed: int) -> DataFrame:
    """``spots`` (m, i) with what follows the word in the text whose digest places it: made once for a query, not for each word."""
    return spots.withColumn("tail", F.concat(F.lit("|"), F.concat_ws("|", F.col("m").cast("string"), F.col("i").cast("string"), F.lit(str(seed)))))


def _place() -> Column:
    """What orders the words of query (m, i)."""
    return F.md5(F.concat("word", "tail").cast("binary"))


def _first_words(words: DataFrame, spots: DataFrame, most: int, seed: int) -> DataFrame:
    """``word, m, i, tail`` with the first ``m`` words of each spot among them: every word's place is computed, but only places below
    a bound are gathered; spots with too few words below it are given all words."""
    total = words.count()
    dealt = words.repartition(4 * words.sparkSession.sparkContext.defaultParallelism, "word").crossJoin(F.broadcast(_with_tail(spots, seed)))
    if total <= MARGIN * most:
        return dealt
    bound = f"{(MARGIN * most << 32) // total:08x}"
    near = store(dealt.where(_place() < bound))
    short = spots.join(near.groupBy("m", "i").agg(F.count(F.lit(1)).alias("n")), ["m", "i"], "left").where(F.coalesce("n", F.lit(0)) < F.col("m")).select("m", "i")
    return near if short.isEmpty() else near.join(F.broadcast(short), ["m", "i"], "left_anti").unionByName(dealt.join(F.broadcast(short), ["m", "i"], "left_semi").select(near.columns))


def make_queries(index: PathIndex, per_m: int = 50, most: int = 10, mode: str = "random", seed: int = 0, share: float = 1.0) -> DataFrame:
    """``m, i, words``: ``per_m`` queries of each length 1..most, the same for a seed anywhere.

    ``random`` orders the vocabulary (or a digest-chosen ``share`` of it) anew for each query and takes the first m words;
    ``rooted`` does so with the words of one root, so that an answer exists.
    """
    spark = index.patterns.sparkSession
    if mode == "random":
        words = store(index.vocabulary().where(root_sample(F.col("word"), seed, F.lit(share))))
        spots = spark.range(1, most + 1).select(F.col("id").cast("int").alias("m")).crossJoin(spark.range(per_m).select(F.col("id").cast("int").alias("i")))
        drawn = _first_words(words, spots, most, seed)
    elif mode == "rooted":
        held = index.postings().select("root", "word").distinct()
        rich = held.groupBy("root").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= most)
        digest = F.md5(F.concat_ws("|", F.col("root").cast("string"), F.lit(str(seed))).cast("binary"))
        chosen = rich.orderBy(digest, "root").limit(most * per_m)
        placed = chosen.select("root", (F.row_number().over(Window.orderBy(digest, "root")) - 1).alias("at"))
        drawn = _with_tail(held.join(F.broadcast(placed), "root").select("word", (F.floor(F.col("at") / per_m) + 1).cast("int").alias("m"), (F.col("at") % per_m).cast("int").alias("i")), seed)
    else:
        raise ValueError(f"unknown mode {mode!r}")
    first = drawn.withColumn("n", F.row_number().over(Window.partitionBy("m", "i").orderBy(_place(), "word"))).where(F.col("n") <= F.col("m"))
    return first.groupBy("m", "i").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("n", "word"))), lambda x: x["word"]), " ").alias("words"))
