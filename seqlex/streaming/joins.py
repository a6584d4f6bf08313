"""Stateful streams: repeats dropped within the watermark, joins with the vocabulary and between streams, running results kept in a table."""

from __future__ import annotations

from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def timed(events: DataFrame, late: str = "10 minutes", column: str = "ts") -> DataFrame:
    """The events with their time as `at` and a watermark; rows later than that are dropped by the stateful steps behind it."""
    return events.withColumn("at", F.col(column).cast("timestamp")).withWatermark("at", late)


def distinct_within(events: DataFrame, *keys: str, late: str = "10 minutes") -> DataFrame:
    """The first row of each key within the watermark; the state of a key goes when the watermark passes it."""
    return timed(events, late).dropDuplicatesWithinWatermark(list(keys))


def with_vocabulary(tokens: DataFrame, vocabulary: DataFrame) -> DataFrame:
    """A stream of rows with `token` against the table (token_id, token); unknown tokens have a null id. The table is read again by each trigger."""
    return tokens.join(vocabulary.select("token", "token_id"), "token", "left")


def followed_by(first: DataFrame, then: DataFrame, key: str, within: str, late: str = "10 minutes") -> DataFrame:
    """(key, at, then_at) of two event streams: rows of `then` at most `within` after a row of `first` with its key. The state of both sides is bounded by the watermarks and the interval."""
    a = timed(first, late).select(F.col(key).alias("a_key"), "at")
    b = timed(then, late).select(F.col(key).alias("b_key"), F.col("at").alias("then_at"))
    near = F.expr(f"a_key = b_key AND then_at >= at AND then_at <= at + INTERVAL {within}")
    return a.join(b, near).select(F.col("a_key").alias(key), "at", "then_at")


def upsert(stream: DataFrame, path: str, key: str, checkpoint: str) -> str:
    """Keeps the newest row of each key of an update-mode stream as a table; returns the folder of its newest state. A trigger reads the folder of the one before and writes its own, so a
    repeated trigger gives the same rows."""
    spark = stream.sparkSession
    last = [None]

    def merge(batch: DataFrame, number: int) -> None:
        out = batch
        if number:
            try:
                before = spark.read.parquet(f"{path}/{number - 1}")
                out = before.join(batch.select(key), key, "left_anti").unionByName(batch)
            except AnalysisException as e:
                if "PATH_NOT_FOUND" not in str(e):
                    raise
        out.write.mode("overwrite").parquet(f"{path}/{number}")
        last[0] = f"{path}/{number}"

    q = stream.writeStream.foreachBatch(merge).outputMode("update").option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return last[0]
