"""Shared folder, scratch tables and Arrow helpers used by the operators of this subpackage.

Every intermediate table goes to the folder named in ``spark.checkpoint.dir``: it is the only place
that the driver and all executors see, so a lost executor never takes the only copy with it.
"""

from __future__ import annotations

import atexit
import os
import shutil
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: White space of the contracts: space and U+0009 to U+000D; ``bytes.split()`` splits at the same six.
WS = r"[\x20\x09-\x0D]"


def shared_dir(spark: SparkSession) -> str:
    """The cluster's shared folder; sets one of its own only where the session names none (tests)."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        own = tempfile.mkdtemp(prefix="gembed-shared-")
        atexit.register(shutil.rmtree, own, True)
        spark.sparkContext.setCheckpointDir(f"file://{own}")
        found = f"file://{own}"
    return found if "://" in found or found.startswith("file:") else f"file://{os.path.abspath(found)}"


def scratch(spark: SparkSession, name: str) -> str:
    """A fresh folder name below the shared folder; never reused, so a retried call cannot mix files."""
    return f"{shared_dir(spark).rstrip('/')}/{name}-{uuid.uuid4().hex[:12]}"


def stored(df: DataFrame, name: str, *parts: str) -> DataFrame:
    """Writes a table to the shared folder and reads it back: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = scratch(spark, name)
    writer = df.write.partitionBy(*parts) if parts else df.write
    writer.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._gembed_path = path
    return out


def forget(df: DataFrame) -> None:
    """Deletes a table that ``stored`` wrote and nothing reads any more."""
    path = getattr(df, "_gembed_path", None)
    if path:
        remove(df.sparkSession, path)


def remove(spark: SparkSession, path: str) -> None:
    """Deletes a scratch folder through Hadoop's file system, wherever the shared folder lies."""
    jvm = spark._jvm
    at = jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def mapped(df: DataFrame, fn: Callable[[pa.RecordBatch], dict], schema: str, rows: int = 10_000, after: Callable[[], None] | None = None) -> DataFrame:
    """``mapInArrow`` for a function that turns at most ``rows`` rows of a batch into a dict of columns.

    ``after`` runs when a task has no more rows, to give back what the worker would else keep.
    """
    from pyspark.sql.types import StructType

    arrow = _arrow_schema(StructType.fromDDL(schema))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, rows):
                out = fn(batch.slice(lo, rows))
                yield pa.RecordBatch.from_arrays([_column(out[f.name], f.type) for f in arrow], schema=arrow)
        if after is not None:
            after()
        give_back()

    return df.mapInArrow(run, schema)


def give_back() -> None:
    """Returns memory that a Python worker has freed to the system; workers stay alive between stages."""
    import ctypes
    import gc

    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def _column(values, kind):
    return values if isinstance(values, pa.Array) and values.type == kind else pa.array(values, kind)


def _arrow_schema(struct) -> pa.Schema:
    from pyspark.sql.pandas.types import to_arrow_schema

    return to_arrow_schema(struct)


def file_system(uri: str):
    """pyarrow's file system for a folder of the shared store, and the path inside it."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri)


def id_and_text(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Only the two columns that an operator reads; null text counts as empty, other columns are pruned."""
    return docs.select(F.col(key).cast("long").alias("doc_id"), F.coalesce(F.col(text).cast("string"), F.lit("")).alias("text"))


class Generations:
    """A dict with a bound: when the young half is full it becomes the old half and the old one goes."""

    def __init__(self, make: Callable, bound: int):
        self.make, self.bound, self.young, self.old = make, bound, {}, {}

    def __call__(self, key):
        value = self.young.get(key)
        return self._add(key) if value is None else value

    def _add(self, key):
        value = self.old.get(key)
        if value is None:
            value = self.make(key)
        if len(self.young) >= self.bound:
            self.old, self.young = self.young, {}
        self.young[key] = value
        return value

    def many(self, keys: list) -> list:
        """The values of all keys, in order."""
        different = set(keys)
        missing = different.difference(self.young)
        if len(self.young) + len(missing) > self.bound and self.young:
            self.old, self.young = self.young, {}
            missing = different
        young, old, make = self.young, self.old, self.make
        for key in missing:
            value = old.get(key)
            young[key] = make(key) if value is None else value
        return [young[key] for key in keys]
