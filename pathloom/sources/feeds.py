"""Edge lists and change feeds: readers, and the partitioned edge store."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EDGES = "label string, src long, dst long"


def read_edges(spark: SparkSession, path: str, format: str = "parquet") -> DataFrame:
    """Edges (label, src, dst) as sets, rows with nulls dropped; label folders are pruned by filters."""
    rows = spark.read.schema(EDGES).option("header", True).format(format).load(path)
    return rows.where("label IS NOT NULL AND src IS NOT NULL AND dst IS NOT NULL").distinct()


def read_feed(spark: SparkSession, path: str, format: str = "json") -> DataFrame:
    return spark.read.schema(f"op string, {EDGES}").option("header", True).format(format).load(path).where("op IN ('+', '-')")


def write_edges(edges: DataFrame, path: str) -> None:
    """One folder for each label; a rerun replaces the labels that it holds and no others."""
    edges.repartition("label", F.pmod(F.xxhash64("src"), F.lit(16))).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("label").parquet(path)


def save_bucketed(edges: DataFrame, name: str, buckets: int = 16, by: str = "src", path: str | None = None) -> DataFrame:
    """A table bucketed by an end, so that compositions on it need no exchange; path: where it is kept, if not in the warehouse."""
    writer = edges.repartition(buckets, by).write.mode("overwrite").bucketBy(buckets, by).sortBy(by)
    (writer if path is None else writer.option("path", path)).saveAsTable(name)
    return edges.sparkSession.table(name)
