"""Operator 4: exact deduplication with stateful streaming.

Documents arrive as a stream of (digest, id, locator) records. A streaming aggregation keeps one state
entry per digest in RocksDB on disk, without expiry: the smallest id, where its content lies (file and
row id) and how many rows had the digest. Spark aggregates each micro-batch before its shuffle, so a
group that holds a third of all rows reaches a state partition as one record per task.

A digest that was hit twice or more proves nothing by itself: the full bytes of all its rows are
compared, again pre-aggregated (a task sends each different text of a digest once). Where one digest
holds different texts, its rows are grouped by the bytes instead.

Texts are equal when they are after every run of space and U+0009..U+000D became one space. Defined
results: null text counts as empty; of rows with equal text the smallest ``doc_id`` stays (null ids
last); of rows that repeat that id too, exactly one is ``kept``; an empty table gives an empty table;
other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import id_and_text, scratch, stored

#: Only runs that change are matched: those that start with another character than a space, or go on.
_RUNS = r"[\x09-\x0D][\x20\x09-\x0D]*|\x20[\x20\x09-\x0D]+"
ROCKSDB = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"
#: State on disk with a change log per batch; files are not preallocated (4 MB for each of many partitions).
SETTINGS = {
    "spark.sql.streaming.stateStore.providerClass": ROCKSDB,
    "spark.sql.streaming.stateStore.rocksdb.changelogCheckpointing.enabled": "true",
    "spark.sql.streaming.stateStore.rocksdb.allowFAllocate": "false",
}
#: Hit digests up to this number are broadcast (under 100 MB); more go by a shuffle join.
BROADCAST_DIGESTS = 500_000
_LAST_ID = (1 << 63) - 1


def normalised(text: Column) -> Column:
    return F.regexp_replace(F.coalesce(text, F.lit("")), _RUNS, " ")


def digest(text: Column) -> Column:
    return F.sha2(text, 256)


def ingest_log(docs: DataFrame, digest_of=digest) -> DataFrame:
    """One small record per row: digest, id, and the content's locator (file and row id)."""
    rows = id_and_text(docs).withColumn("norm", normalised(F.col("text")))
    return stored(rows.select("doc_id", digest_of(F.col("norm")).alias("digest"), F.monotonically_increasing_id().alias("row_id"), F.input_file_name().alias("file")), "dedup-log")


class DedupState:
    """The keyed state of one corpus; ``absorb`` may be called again when more log files have come."""

    def __init__(self, spark: SparkSession, root: str | None = None):
        self.spark, self.root = spark, root or scratch(spark, "dedup-state")
        self.updates = f"{self.root}/updates"

    def absorb(self, log: DataFrame, log_path: str, batches: int = 2) -> None:
        """Streams all new files of the log through the state and stops."""
        files = max(1, len(log.inputFiles()))
        spark, old = self.spark, {}
        for k, v in SETTINGS.items():
            old[k] = spark.conf.get(k, None)
            spark.conf.set(k, v)
        try:
            stream = spark.readStream.schema(log.schema).option("maxFilesPerTrigger", -(-files // batches)).parquet(log_path)
            state = stream.groupBy("digest").agg(F.min(F.struct(F.coalesce("doc_id", F.lit(_LAST_ID)).alias("doc_id"), "row_id", "file")).alias("first"), F.count(F.lit(1)).alias("n"))

            def keep(batch: DataFrame, number: int) -> None:
                batch.write.mode("overwrite").parquet(f"{self.updates}/batch={number}")

            run = state.writeStream.outputMode("update").foreachBatch(keep).option("checkpointLocation", f"{self.root}/checkpoint").trigger(availableNow=True).start()
            run.awaitTermination()
        finally:
            for k, v in old.items():
                spark.conf.unset(k) if v is None else spark.conf.set(k, v)

    def table(self) -> DataFrame:
        """digest, first (id, row id, file), n. Both only fall or grow, so the last update is min and max."""
        rows = self.spark.read.schema("digest string, first struct<doc_id: long, row_id: long, file: string>, n long").parquet(self.updates)
        return rows.groupBy("digest").agg(F.min("first").alias("first"), F.max("n").alias("n"))


def _collisions(docs: DataFrame, hits: DataFrame, digest_of) -> DataFrame:
    """Rows (digest, norm, doc_id) classes of digests under which different bytes were found."""
    texts = id_and_text(docs).select(normalised(F.col("text")).alias("norm")).withColumn("digest", digest_of(F.col("norm")))
    few = hits.count() <= BROADCAST_DIGESTS
    of_hits = texts.join(F.broadcast(hits) if few else hits, "digest", "left_semi")
    classes = of_hits.groupBy("digest", "norm").agg(F.count(F.lit(1)).alias("rows"))
    return classes.groupBy("digest").agg(F.count(F.lit(1)).alias("texts")).where("texts > 1").select("digest")


def dedup(docs: DataFrame, digest_of=digest, batches: int = 2) -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256 of every row."""
    spark = docs.sparkSession
    log = ingest_log(docs, digest_of)
    if not log.inputFiles():
        return spark.createDataFrame([], "doc_id long, keep_id long, group_size long, kept boolean, text_sha256 string")
    state = DedupState(spark)
    state.absorb(log, log.inputFiles()[0].rsplit("/", 1)[0], batches)
    firsts = stored(state.table(), "dedup-firsts")
    clashing = stored(_collisions(docs, firsts.where("n > 1").select("digest"), digest_of), "dedup-clashes")
    rows = log.join(firsts, "digest").select("doc_id", "digest", _known(F.col("first.doc_id")).alias("keep_id"), F.col("n").alias("group_size"), (F.col("row_id") == F.col("first.row_id")).alias("kept"))
    if clashing.isEmpty():
        return rows.select("doc_id", "keep_id", "group_size", "kept", F.col("digest").alias("text_sha256") if digest_of is digest else F.col("digest"))
    return _by_bytes(docs, rows, clashing, digest_of)


def _known(doc_id: Column) -> Column:
    return F.nullif(doc_id, F.lit(_LAST_ID))


def _by_bytes(docs: DataFrame, rows: DataFrame, clashing: DataFrame, digest_of) -> DataFrame:
    """The same, with rows of clashing digests grouped by their full text."""
    texts = id_and_text(docs).select("doc_id", F.monotonically_increasing_id().alias("row_id"), normalised(F.col("text")).alias("norm")).withColumn("digest", digest_of(F.col("norm"))).join(clashing, "digest", "left_semi")
    texts = stored(texts, "dedup-clashing-texts")
    first = texts.groupBy("norm").agg(F.min(F.struct(F.coalesce("doc_id", F.lit(_LAST_ID)).alias("doc_id"), "row_id")).alias("first"), F.count(F.lit(1)).alias("group_size"))
    apart = texts.join(first, "norm").select("doc_id", _known(F.col("first.doc_id")).alias("keep_id"), "group_size", (F.col("row_id") == F.col("first.row_id")).alias("kept"), digest(F.col("norm")).alias("text_sha256"))
    rest = rows.join(clashing, "digest", "left_anti").select("doc_id", "keep_id", "group_size", "kept", F.col("digest").alias("text_sha256"))
    return rest.unionByName(apart)


def keep_first(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` that stay, all columns unchanged.

    The list of those that go is broadcast while it is short; a longer one, and a table that repeats
    whole rows, goes by a shuffle join.
    """
    told = stored(dedup(docs).select(F.col("doc_id").alias("__gembed_id"), F.col("text_sha256").alias("__gembed_digest"), "kept").distinct(), "dedup-kept")
    kept, lost = told.where("kept").drop("kept"), told.where("not kept").drop("kept")
    rows = docs.withColumn("__gembed_own", digest(normalised(F.col("text").cast("string"))))
    same = lambda other: rows["doc_id"].cast("long").eqNullSafe(other["__gembed_id"]) & (rows["__gembed_own"] == other["__gembed_digest"])
    if lost.count() <= BROADCAST_DIGESTS and kept.intersect(lost).isEmpty():
        lost = F.broadcast(lost)
        return rows.join(lost, same(lost), "left_anti").drop("__gembed_own")
    return rows.join(kept, same(kept), "left_semi").dropDuplicates(["doc_id", "__gembed_own"]).drop("__gembed_own")
