"""Reading of the given tables and of triple lists, and the engine's sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Triples as text: head, relation and tail, separated by tabs.
TRIPLES = "head string, rel string, tail string"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def read_triples(spark: SparkSession, path: str) -> DataFrame:
    """A directory of tab-separated triples; lines with another number of fields are an error."""
    return spark.read.csv(path, sep="\t", schema=TRIPLES, mode="FAILFAST", quote="")


def write_triples(edges: DataFrame, path: str) -> None:
    """head, rel and tail as tab-separated text; tabs and line feeds inside keys become spaces."""
    clean = lambda c: F.regexp_replace(F.col(c).cast("string"), r"[\t\r\n]", " ")
    edges.select(F.concat_ws("\t", clean("head"), clean("rel"), clean("tail")).alias("value")).write.text(path)


def export_vectors(vectors: DataFrame, path: str) -> None:
    """key and vector per line, as embeddings are usually published."""
    vectors.select(F.concat_ws("\t", F.col("key"), F.array_join(F.transform("vec", lambda x: x.cast("string")), " ")).alias("value")).write.text(path)


def noop(df: DataFrame) -> None:
    """Runs a plan without keeping its rows (for measurements)."""
    df.write.format("noop").mode("overwrite").save()
