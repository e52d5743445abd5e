"""The shared folder for versions, checkpoints and scratch tables."""

from __future__ import annotations

import atexit
import os
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of a counted table that may go to every task whole; a larger one is shuffled.
SMALL_BYTES = 64 << 20
#: The same of a table that is hashed by its keys for a join: the driver makes that several times as large, in several copies.
HASHED_BYTES = 8 << 20


def shared_dir(spark: SparkSession) -> str:
    """The folder in ``spark.checkpoint.dir``; one of our own only where the session names none."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        own = tempfile.mkdtemp(prefix="gembed-shared-")
        atexit.register(shutil.rmtree, own, True)
        spark.sparkContext.setCheckpointDir(f"file://{own}")
        found = f"file://{own}"
    return found if found.startswith("file:") or "://" in found else f"file://{os.path.abspath(found)}"


def scratch(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark).rstrip('/')}/{name}-{uuid.uuid4().hex[:12]}"


def stored(df: DataFrame, name: str, *parts: str) -> DataFrame:
    """Written to the shared folder and read back: lineage ends here, and a lost executor loses nothing."""
    path = scratch(df.sparkSession, name)
    (df.write.partitionBy(*parts) if parts else df.write).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def key_bytes(df: DataFrame, key: str) -> tuple[int, int]:
    """Rows of a stored table, and the bytes of its keys."""
    row = df.agg(F.count(F.lit(1)).alias("n"), F.sum(F.octet_length(key)).alias("b")).first()
    return row["n"], row["b"] or 0


def is_small(n: int, keys: int, row: int = 0, most: int | None = None) -> bool:
    """Whether a table of so many rows, bytes of keys and further bytes a row may go to every task."""
    return keys + n * (48 + row) <= min(SMALL_BYTES, SMALL_BYTES if most is None else most)


def remove(spark: SparkSession, path: str) -> None:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def side_by_side(spark: SparkSession, settings, run) -> list:
    """``run`` of every setting, in their order; as many at a time as there are slots for tasks.

    A chain on one machine is a single task, so independent trainings leave no slot idle. Not for experiments that compare seconds with one training's own.
    """
    from concurrent.futures import ThreadPoolExecutor

    from pyspark import inheritable_thread_target

    settings = list(settings)
    with ThreadPoolExecutor(max(1, min(len(settings), spark.sparkContext.defaultParallelism))) as pool:
        return [f.result() for f in [pool.submit(inheritable_thread_target(spark)(run), x) for x in settings]]
