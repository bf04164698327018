"""Joining answers with a stream of events: the latest before, those around, and those within ranges."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

DAY = 86_400


def asof(left: DataFrame, right: DataFrame, key: str, left_time: str, right_time: str, columns: list[str]) -> DataFrame:
    """``left`` with the columns of the latest ``right`` row of the same key at or before its time (null: none).

    Both sides are laid in one sequence by key and time, and the last event is carried forward: one shuffle, no join. Left
    rows travel whole, so a task that runs again needs no row numbers. Ties take the event greatest by its columns; a null
    key or time has no event. A hot key is one window; ``around`` splits keys by time instead.
    """
    row, event = left.select(F.struct("*")).schema[0].dataType, right.select(F.struct(*columns)).schema[0].dataType
    marks = left.select(F.col(key).alias("key"), F.col(left_time).alias("at"), F.lit(1).alias("side"), F.struct("*").alias("row"), F.lit(None).cast(event).alias("event"))
    events = right.where(F.col(key).isNotNull() & F.col(right_time).isNotNull()).select(F.col(key).alias("key"), F.col(right_time).alias("at"), F.lit(0).alias("side"), F.lit(None).cast(row).alias("row"), F.struct(*columns).alias("event"))
    w = Window.partitionBy("key").orderBy("at", "side", "event").rowsBetween(Window.unboundedPreceding, 0)
    carried = marks.unionByName(events).withColumn("event", F.last("event", ignorenulls=True).over(w)).where("side = 1")
    return carried.select("row.*", *(F.col(f"event.{c}").alias(c) for c in columns))


def around(left: DataFrame, right: DataFrame, key: str, left_time: str, right_time: str, seconds: int) -> DataFrame:
    """Pairs of rows with one key whose times are at most ``seconds`` apart: an equality join on time buckets, then the bound.

    Each left row looks into the buckets that its window touches (two or three), so the join stays an equality join.
    """
    bucket = lambda c: F.floor(F.unix_seconds(c) / seconds)
    own = left.withColumn("bucket", F.explode(F.sequence(bucket(F.col(left_time)) - 1, bucket(F.col(left_time)) + 1)))
    other = right.withColumn("bucket", bucket(F.col(right_time))).withColumnRenamed(key, "other_key")
    gap = F.abs(F.unix_seconds(F.col(left_time)) - F.unix_seconds(F.col(right_time)))
    return own.join(other, (own[key] == other["other_key"]) & (own["bucket"] == other["bucket"])).where(gap <= seconds).drop(own["bucket"]).drop(other["bucket"]).drop("other_key")


def in_ranges(points: DataFrame, ranges: DataFrame, value: str, low: str, high: str, width: float) -> DataFrame:
    """Points with the ranges [low, high) that hold them; ranges are cut into buckets of ``width`` for an equality join."""
    cells = ranges.withColumn("cell", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    return points.withColumn("cell", F.floor(F.col(value) / width)).join(cells, "cell").where((F.col(value) >= F.col(low)) & (F.col(value) < F.col(high))).drop("cell")
