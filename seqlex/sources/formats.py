"""Text formats of sequences, intervals and matrices."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read_fasta(spark: SparkSession, path: str) -> DataFrame:
    """(name, seq) of a file of '>' records: records are cut by the reader itself, so no line order is needed across partitions."""
    records = spark.read.option("lineSep", ">").text(path).where(F.length(F.trim("value")) > 0)
    lines = F.split("value", "\n")
    return records.select(F.element_at(F.split(F.element_at(lines, 1), r"\s+"), 1).alias("name"), F.upper(F.regexp_replace(F.array_join(F.slice(lines, 2, F.size(lines)), ""), r"\s", "")).alias("seq"))


def read_intervals(spark: SparkSession, path: str) -> DataFrame:
    """(contig, start, end, category) of a tab-separated file; half-open coordinates."""
    return spark.read.option("sep", "\t").schema("contig string, start long, end long, category string").csv(path)


def read_matrices(spark: SparkSession, path: str) -> DataFrame:
    """(name, base, counts) of matrix records: a '>' line, then a line for each base with its counts in brackets."""
    records = spark.read.option("lineSep", ">").text(path).where(F.length(F.trim("value")) > 0)
    lines = F.split("value", "\n")
    rows = records.select(F.element_at(F.split(F.element_at(lines, 1), r"\s+"), 1).alias("name"), F.explode(F.slice(lines, 2, 4)).alias("line"))
    numbers = F.filter(F.split(F.regexp_replace("line", r"[^0-9.]+", " "), " "), lambda x: F.length(x) > 0)
    return rows.select("name", F.substring(F.trim("line"), 1, 1).alias("base"), F.transform(numbers, lambda x: x.cast("double")).alias("counts"))


def write_vocabulary(vocab: DataFrame, path: str) -> None:
    vocab.write.mode("overwrite").json(path)
