"""Sinks: segments, scores, vocabularies and merges as tables and files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def write_partitioned(df: DataFrame, path: str, *keys: str, files: int = 1) -> None:
    """Parquet folders by keys, `files` files at most in each: rows of a folder are dealt by their hash, so no folder is one task's work if files is over one."""
    part = F.pmod(F.xxhash64(*(c for c in df.columns if c not in keys)), F.lit(files)).alias("part")
    df.repartition(*keys, part).write.mode("overwrite").partitionBy(*keys).parquet(path)


def replace_partitions(df: DataFrame, path: str, *keys: str) -> None:
    """The folders that df has rows for are replaced, all others stay."""
    df.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy(*keys).parquet(path)


def write_bucketed(df: DataFrame, table: str, key: str, buckets: int) -> None:
    """A table whose rows are dealt and sorted by key, so that joins of two such tables need no exchange. Rows are dealt before, so a bucket is one file."""
    df.repartition(buckets, key).write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)


def write_orc(df: DataFrame, path: str) -> None:
    df.write.mode("overwrite").orc(path)


def write_merges(spark: SparkSession, merges: list[tuple[str, str]], path: str) -> None:
    """A list of merges, in its order, as JSON lines (rank, left, right)."""
    spark.createDataFrame([(k, a, b) for k, (a, b) in enumerate(merges)], "rank int, left string, right string").coalesce(1).write.mode("overwrite").json(path)


def read_merges(spark: SparkSession, path: str) -> list[tuple[str, str]]:
    """The merges of such a file; they are as many as the vocabulary's size, whatever the data."""
    rows = spark.read.schema("rank int, left string, right string").json(path)
    return [(r["left"], r["right"]) for r in rows.orderBy("rank").collect()]
