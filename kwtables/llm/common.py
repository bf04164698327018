"""Helpers shared by the training-data operators: code shipping, lineage cuts and checked broadcasts."""

from __future__ import annotations

import contextlib
import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows of an Arrow batch. Texts can be long, and a batch is held by the JVM and by the Python worker at once.
BATCH_ROWS = 1_000
_BATCH_SETTING, _BATCH_DEFAULT = "spark.sql.execution.arrow.maxRecordsPerBatch", "10000"

PACKAGE = Path(__file__).resolve().parent.parent
_shipped: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Send this package to the Python workers once per application, so that mapInArrow functions import it there.

    Sessions that leave the Arrow batch size at its default get batches of BATCH_ROWS.
    """
    sc = spark.sparkContext
    if spark.conf.get(_BATCH_SETTING, _BATCH_DEFAULT) == _BATCH_DEFAULT:
        spark.conf.set(_BATCH_SETTING, str(BATCH_ROWS))
    if sc.applicationId in _shipped:
        return
    _shipped.add(sc.applicationId)
    target = os.path.realpath(os.path.join(tempfile.mkdtemp(), f"{PACKAGE.name}.zip"))
    with zipfile.ZipFile(target, "w") as z:
        for p in sorted(PACKAGE.rglob("*.py")):
            z.write(p, str(Path(PACKAGE.name) / p.relative_to(PACKAGE)))
    sc.addPyFile(target)


def shared_folder(spark: SparkSession) -> str:
    """The folder that the driver and all executors share: spark.checkpoint.dir, else one of this machine in local mode only."""
    sc = spark.sparkContext
    if not sc.getCheckpointDir():
        named = sc.getConf().get("spark.checkpoint.dir")
        if not named and sc.master.split("[")[0] != "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="checkpoints"))
    return sc.getCheckpointDir()


def cut(df: DataFrame, eager: bool = True) -> DataFrame:
    """Materialise ``df`` in the cluster's shared checkpoint folder."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager)


def join_hot(rows: DataFrame, side: DataFrame, key: list[str], hot: DataFrame) -> DataFrame:
    """``rows`` left joined with ``side`` (one row a key): the keys of ``hot``, few by construction, are broadcast, the others shuffled."""
    if hot.isEmpty():
        return rows.join(side, key, "left")
    marked = rows.join(F.broadcast(hot.select(*key).withColumn("is_hot", F.lit(True))), key, "left")
    often = marked.where("is_hot").drop("is_hot").join(F.broadcast(side.join(F.broadcast(hot.select(*key)), key, "left_semi")), key, "left")
    return often.unionByName(marked.where("is_hot IS NULL").drop("is_hot").join(side, key, "left"))


def broadcast_if(df: DataFrame, size: int, limit: int) -> DataFrame:
    """Broadcast hint only for a measured ``size`` within ``limit``; beyond it the planner shuffles both sides."""
    return F.broadcast(df) if size <= limit else df


def fresh(df: DataFrame, stem: str) -> str:
    """A column name starting with ``stem`` that ``df`` does not hold yet."""
    taken, name = {c.lower() for c in df.columns}, stem
    while name.lower() in taken:
        name = f"{name}_"
    return name


def trim() -> None:
    """Hand memory that a finished partition no longer needs back to the system: idle workers count as the executor's."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)
