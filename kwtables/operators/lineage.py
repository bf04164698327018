"""Materialising intermediate tables where every executor can read them again."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_folder(spark: SparkSession) -> str:
    """The session's checkpoint folder; one of this machine only in local mode, where none is configured."""
    sc = spark.sparkContext
    if not sc.getCheckpointDir():
        named = sc.getConf().get("spark.checkpoint.dir")
        if not named and sc.master.split("[")[0] != "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="checkpoints"))
    return sc.getCheckpointDir()


#: Ways in which the rows of one key are dealt, so that a key with a large share of all rows is not one task.
SALTS = 64


def store(df: DataFrame, by: str | None = None, salt: str | None = None, sort: list[str] | None = None) -> DataFrame:
    """``df`` written as Parquet in the shared folder and read back: short plans, pruned columns, file statistics.

    Rows are dealt by ``by`` (a key's rows over SALTS places if ``salt`` names a second column) and sorted within files by
    ``sort``, so that equality filters skip row groups.
    """
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/tables/{uuid.uuid4().hex}"
    if by is not None:
        df = df.repartition(by, *([F.pmod(F.xxhash64(salt), F.lit(SALTS))] if salt else []))
    if sort:
        df = df.sortWithinPartitions(*sort)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def dealt(df: DataFrame, by: str, places: int, name: str) -> DataFrame:
    """``df`` written in ``places`` files by hash of ``by``, sorted by it: tables dealt alike are joined on it without a shuffle."""
    spark = df.sparkSession
    df.repartition(places, by).write.bucketBy(places, by).sortBy(by).option("path", _dealt_path(spark, name)).saveAsTable(name)
    return spark.table(name)


def _dealt_path(spark: SparkSession, name: str) -> str:
    return f"{shared_folder(spark)}/tables/{name}"


def drop_dealt(spark: SparkSession, name: str) -> None:
    """Takes a table that ``dealt`` wrote, and that nothing reads any more, from the disk."""
    spark.sql(f"DROP TABLE {name}")
    path = spark._jvm.org.apache.hadoop.fs.Path(_dealt_path(spark, name))
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


@contextmanager
def shuffles_dropped(spark: SparkSession) -> Iterator[None]:
    """Shuffle files are dropped as soon as the action that wrote them ends, for steps whose results are all written."""
    name = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(name, None)
    spark.conf.set(name, "true")
    try:
        yield
    finally:
        spark.conf.unset(name) if before is None else spark.conf.set(name, before)
