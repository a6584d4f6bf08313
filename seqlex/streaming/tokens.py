"""Structured Streaming: the tokenizer is a stateless map per sequence, so the batch operator serves; windows over events carry watermarks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seqlex.operators.greedy import greedy_tokenize


def read_files(spark: SparkSession, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def stream_tokenize(sequences: DataFrame, words: list[str], **options) -> DataFrame:
    """(contig, seq) stream to (contig, n_bases, tokens)."""
    return greedy_tokenize(sequences, words, **options)


def token_counts(tokens: DataFrame) -> DataFrame:
    """Running counts of tokens (update mode)."""
    return tokens.select(F.explode("tokens").alias("t")).groupBy(F.col("t.token").alias("token")).agg(F.count(F.lit(1)).alias("n"))


def pack_stream(parts: DataFrame, length: int = 512) -> DataFrame:
    """(contig, seg_no, tokens) of a stream (contig, part_no, tokens array<string>): full segments as they fill. The state of a contig is its next
    segment number and less than one segment of tokens. The parts of a contig have to come in order over the triggers; within one they are sorted."""

    def fill(key, frames, state):
        import pandas as pd

        seg, rest = state.get if state.exists else (0, [])
        rest = list(rest)
        rows = sorted((int(n), list(t)) for f in frames for n, t in zip(f["part_no"], f["tokens"], strict=True))
        out = []
        for _, tokens in rows:
            rest += tokens
            while len(rest) >= length:
                out.append((key[0], seg, rest[:length]))
                rest, seg = rest[length:], seg + 1
        state.update((seg, rest))
        yield pd.DataFrame(out, columns=["contig", "seg_no", "tokens"])

    return parts.groupBy("contig").applyInPandasWithState(fill, "contig long, seg_no long, tokens array<string>", "seg_no long, rest array<string>", "append", "NoTimeout")


def windowed(events: DataFrame, width: str, *, slide: str | None = None, late: str = "10 minutes") -> DataFrame:
    """Counts and sums in tumbling or sliding windows. timestamp_ntz becomes a timestamp first, as a watermark needs one."""
    timed = events.withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", late)
    window = F.window("at", width, slide) if slide else F.window("at", width)
    return timed.groupBy(window.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 6).alias("total"))


def sessions(events: DataFrame, gap: str, *, late: str = "10 minutes") -> DataFrame:
    timed = events.withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", late)
    return timed.groupBy(F.session_window("at", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))


def run_available(stream: DataFrame, name: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """Runs the stream over what is there and gives its result as a table in memory (for tests and small results)."""
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return stream.sparkSession.table(name)
