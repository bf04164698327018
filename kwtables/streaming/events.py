"""Event streams beside the graph: word trends with watermarks, and new entities appended to an index."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..functions.text import tokenize
from ..operators.index import POSTING_COLUMNS, PathIndex, enumerate_paths, pattern_dictionary
from ..sources.graph import KnowledgeGraph

EVENT_TIME = "ts_utc"
LATENESS = "1 hour"


def read_events(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    """Events as a stream with a zoned time column; files hold times without a zone, which cannot carry a watermark."""
    schema = spark.read.parquet(path).schema
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)
    return with_event_time(stream)


def with_event_time(events: DataFrame) -> DataFrame:
    return events.withColumn(EVENT_TIME, F.col("ts").cast("timestamp"))


def windowed(kind: str, length: str, slide: str | None = None) -> Column:
    """A tumbling, sliding or session window over the event time."""
    if kind == "session":
        return F.session_window(EVENT_TIME, length)
    return F.window(EVENT_TIME, length, slide) if kind == "sliding" else F.window(EVENT_TIME, length)


def word_trend(events: DataFrame, words: list[str], kind: str = "tumbling", length: str = "1 day", slide: str | None = None, text: str = "event_type") -> DataFrame:
    """Hits of each word by window: batch and stream alike; late rows beyond the watermark are dropped in a stream."""
    timed = events.withWatermark(EVENT_TIME, LATENESS) if events.isStreaming else events
    hits = timed.select(EVENT_TIME, F.explode(tokenize(F.col(text))).alias("word")).where(F.col("word").isin(words))
    return hits.groupBy(windowed(kind, length, slide).alias("span"), "word").agg(F.count(F.lit(1)).alias("hits")).select(F.col("span.start").alias("start"), F.col("span.end").alias("end"), "word", "hits")


def without_repeats(events: DataFrame, key: str = "event_id") -> DataFrame:
    """Each event once: within the watermark in a stream, overall in a batch."""
    if events.isStreaming:
        return events.withWatermark(EVENT_TIME, LATENESS).dropDuplicatesWithinWatermark([key])
    return events.dropDuplicates([key])


def run_to_files(result: DataFrame, path: str, checkpoint: str) -> StreamingQuery:
    """All files there are, appended as Parquet, then the query ends."""
    return result.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).outputMode("append").trigger(availableNow=True).start()


def postings_of_new_entities(index: PathIndex, grown: KnowledgeGraph, new_nodes: DataFrame) -> DataFrame:
    """Postings that start at ``new_nodes(node_id)`` of the grown graph.

    An entity that nothing points to yet adds paths from itself only, so stored postings are appended to, never rewritten.
    """
    paths = enumerate_paths(grown, index.d, roots=new_nodes.select(F.col("node_id").alias("root")))
    return _postings(index, grown, paths)


def touched_roots(grown: KnowledgeGraph, new_edges: DataFrame, d: int) -> DataFrame:
    """Roots whose paths an edge between old entities can change: its source and whatever reaches it in d-2 more steps."""
    front = new_edges.select(F.col("src").alias("root")).distinct()
    out = front
    for _ in range(max(0, d - 2)):
        front = grown.edges.join(front.withColumnRenamed("root", "dst"), "dst", "left_semi").select(F.col("src").alias("root")).distinct()
        out = out.unionByName(front)
    return out.distinct()


def refreshed_postings(index: PathIndex, grown: KnowledgeGraph, new_edges: DataFrame) -> DataFrame:
    """All postings after ``new_edges``: those of touched roots computed anew, the rest kept."""
    roots = touched_roots(grown, new_edges, index.d)
    again = _postings(index, grown, enumerate_paths(grown, index.d, roots=roots))
    return index.postings().join(roots, "root", "left_anti").select(*POSTING_COLUMNS).unionByName(again)


def _postings(index: PathIndex, grown: KnowledgeGraph, paths: DataFrame) -> DataFrame:
    """Postings of some paths; patterns keep the ids they have, new ones follow."""
    fresh = pattern_dictionary(paths, grown).select("labels", "ends_on_edge", F.col("pattern_id").alias("fresh_id"))
    most = index.patterns.agg(F.coalesce(F.max("pattern_id"), F.lit(0)).alias("most"))
    known = index.patterns.select("labels", "ends_on_edge", "pattern_id")
    ids = fresh.join(F.broadcast(known), ["labels", "ends_on_edge"], "left").crossJoin(F.broadcast(most)).select("labels", "ends_on_edge", F.coalesce("pattern_id", F.col("most") + F.col("fresh_id")).alias("pattern_id"))
    at_node = F.broadcast(ids.where(~F.col("ends_on_edge")).select("labels", F.col("pattern_id").alias("node_pattern")))
    at_edge = F.broadcast(ids.where("ends_on_edge").select(F.col("labels").alias("edge_labels"), F.col("pattern_id").alias("edge_pattern")))
    named = paths.join(at_node, "labels").withColumn("edge_labels", F.slice("labels", F.lit(1), F.size("labels") - 1)).join(at_edge, "edge_labels", "left").drop("edge_labels")
    return PathIndex(grown, index.d, named, index.patterns).postings()


def append_batches(stream: DataFrame, to_graph, index: PathIndex, path: str, checkpoint: str) -> StreamingQuery:
    """Each micro-batch of new entities becomes a graph by ``to_graph(batch)``; its postings are appended at ``path``."""

    def add(batch: DataFrame, number: int) -> None:
        grown, new_nodes = to_graph(batch)
        postings_of_new_entities(index, grown, new_nodes).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return stream.writeStream.foreachBatch(add).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


