"""Scratch tables and files in the folder that the driver and all executors share."""

from __future__ import annotations

import atexit
import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_live: set[str] = set()


def shared_dir(spark: SparkSession) -> str:
    """The cluster's ``spark.checkpoint.dir``; where that is unset, a folder of our own.

    A local master has one machine, so a temporary folder is shared there; elsewhere the default file system is used, by its full URI.
    """
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if spark.sparkContext.master.split("[")[0] == "local":
        made = getattr(shared_dir, "made", None)
        if made is None or not os.path.isdir(made):
            made = shared_dir.made = tempfile.mkdtemp(prefix="wsig-shared-")
            atexit.register(_forget, made)
        return f"file://{made}"
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    at = jvm.org.apache.hadoop.fs.Path("wsig-scratch")
    return at.getFileSystem(conf).makeQualified(at).toString()


def _forget(path: str) -> None:
    import shutil

    shutil.rmtree(path, ignore_errors=True)


def new_path(spark: SparkSession, tag: str) -> str:
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    _live.add(path)
    return path


def drop(spark: SparkSession, *paths: str) -> None:
    """Deletes scratch paths through Hadoop's file system, whichever store they are in."""
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    for path in paths:
        at = jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(conf).delete(at, True)
        _live.discard(path)


def settle(df: DataFrame, tag: str) -> tuple[DataFrame, str]:
    """Writes a table to the shared folder and reads it again: the lineage ends there and lost executors lose nothing."""
    spark = df.sparkSession
    path = new_path(spark, tag)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path), path


def free(columns: list[str], *names: str) -> list[str]:
    """Names for columns of our own that no column of a table has, whatever its case."""
    taken, out = {c.lower() for c in columns}, []
    for name in names:
        while name in taken:
            name = "_" + name
        taken.add(name)
        out.append(name)
    return out


def slots(spark: SparkSession) -> int:
    """Shuffle partitions of the session, for repartitions that must not fall to one task."""
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


#: Arrow batches between the JVM and Python: no more rows, and about so many bytes.
BATCH_ROWS, BATCH_BYTES = 1000, 4 << 20


def small_batches(spark: SparkSession) -> None:
    """Lowers the session's Arrow batch sizes to ours where they are larger: a batch lies in the executor's direct memory and in its Python worker at once."""
    for name, most in (("maxRecordsPerBatch", BATCH_ROWS), ("maxBytesPerBatch", BATCH_BYTES)):
        key = f"spark.sql.execution.arrow.{name}"
        have = spark.conf.get(key, None)
        if have is None:
            continue
        size = int(have) if have.lstrip("-").isdigit() else None  # as a number of bytes with a unit: set by someone, left alone
        if size is not None and (size <= 0 or size > most):
            spark.conf.set(key, str(most))
