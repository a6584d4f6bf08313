"""Interval algebra on half-open (key, start, end) rows."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from seqlex.functions.bases import bases
from seqlex.sources.tables import chunks


def merge(iv: DataFrame, key: str = "contig", start: str = "start", end: str = "end") -> DataFrame:
    """Union of overlapping or touching intervals: a row opens an island where it starts beyond all earlier ends."""
    order = Window.partitionBy(key).orderBy(start, end)
    seen = F.max(end).over(order.rowsBetween(Window.unboundedPreceding, -1))
    flagged = iv.select(key, start, end, F.when(F.col(start) <= seen, 0).otherwise(1).alias("opens"))
    named = flagged.withColumn("island", F.sum("opens").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    return named.groupBy(key, "island").agg(F.min(start).alias(start), F.max(end).alias(end), F.count(F.lit(1)).alias("n_members")).drop("island")


def merge_binned(iv: DataFrame, bin_size: int = 1 << 14) -> DataFrame:
    """merge() for contigs of any length: first within bins, so that the window over a contig sees one row for each covered stretch of a bin."""
    cut = iv.select("contig", "start", "end", F.explode(F.sequence(F.floor(F.col("start") / bin_size), F.floor((F.col("end") - 1) / bin_size))).alias("bin"))
    clipped = cut.select(F.struct("contig", "bin").alias("cell"), F.greatest("start", F.col("bin") * bin_size).alias("start"), F.least("end", (F.col("bin") + 1) * bin_size).alias("end"))
    return merge(merge(clipped, "cell").select("cell.contig", "start", "end")).drop("n_members")


def line_spans(df: DataFrame, least: int, length: int | None = None) -> DataFrame:
    """(contig, lang, spans array<(start, end, seq)>) of (contig, text, lang): the places and bases of the even lines of `least` bases or more, the first line being line 0. seq
    has the first `length` bases (none: all). Texts are cut one by one in the workers."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, batch.num_rows, 256):
                part, starts, ends, seqs, sizes = batch.slice(a, 256), [], [], [], []
                for text in part["text"].to_pylist():
                    lines = [] if text is None else bases(text, keep="\n").split("\n")
                    at = np.concatenate([[0], np.cumsum([len(x) for x in lines], dtype=np.int64)]).tolist()
                    own = [k for k in range(0, len(lines), 2) if len(lines[k]) >= least]
                    starts += [at[k] for k in own]
                    ends += [at[k + 1] for k in own]
                    seqs += [lines[k][:length] for k in own]
                    sizes.append(len(own))
                items = pa.StructArray.from_arrays([pa.array(starts, pa.int64()), pa.array(ends, pa.int64()), pa.array(seqs, pa.string())], ["start", "end", "seq"])
                spans = pa.ListArray.from_arrays(pa.array(np.cumsum([0, *sizes]), pa.int32()), items)
                yield pa.RecordBatch.from_arrays([part["contig"], part["lang"], spans], ["contig", "lang", "spans"])

    return df.select("contig", "text", "lang").mapInArrow(run, "contig long, lang string, spans array<struct<start:long,end:long,seq:string>>")


def complement(merged: DataFrame, bounds: DataFrame) -> DataFrame:
    """Gaps of merged intervals within (contig, length)."""
    marks = merged.select("contig", "start", "end").unionByName(bounds.select("contig", F.col("length").cast("long").alias("start"), F.col("length").cast("long").alias("end")))
    before = F.coalesce(F.lag("end").over(Window.partitionBy("contig").orderBy("start", "end")), F.lit(0))
    return marks.select("contig", before.cast("long").alias("start"), F.col("start").alias("end")).where("start < end")


def tile(iv: DataFrame, width: int = 300, keep_rest: bool = False) -> DataFrame:
    fits = iv.where(F.col("end") - F.col("start") >= (1 if keep_rest else width))
    last = F.col("end") - (1 if keep_rest else width)
    cut = fits.select("contig", F.col("end").alias("stop"), F.explode(F.sequence("start", last, F.lit(width).cast("long"))).alias("start"))
    return cut.select("contig", "start", F.least(F.col("start") + width, F.col("stop")).alias("end"))


def extract(iv: DataFrame, contigs: DataFrame, size: int = 1 << 16) -> DataFrame:
    """iv with the bases of each interval, by an equi join on contig and piece: a row never meets more of a contig than the pieces of `size` bases it lies in."""
    pieces = chunks(contigs.select("contig", "seq"), size, 0).select("contig", F.col("chunk_no").cast("long").alias("__piece"), "bases")
    last = F.greatest(F.col("start"), F.col("end") - 1)
    cut = iv.withColumn("__uid", F.monotonically_increasing_id()).withColumn("__piece", F.explode(F.sequence(F.floor(F.col("start") / size), F.floor(last / size))))
    at = F.greatest(F.lit(0), F.col("start") - F.col("__piece") * size)
    n = F.least(F.lit(size), F.col("end") - F.col("__piece") * size) - at
    met = cut.join(pieces, ["contig", "__piece"]).withColumn("__part", F.struct("__piece", F.substring("bases", (at + 1).cast("int"), n.cast("int")).alias("s")))
    one = F.floor(F.col("start") / size) == F.floor(last / size)
    alone = met.where(one).select(*iv.columns, F.col("__part.s").alias("seq"))
    joined = met.where(~one).groupBy("__uid", *iv.columns).agg(F.array_join(F.transform(F.array_sort(F.collect_list("__part")), lambda x: x["s"]), "").alias("seq"))
    return alone.unionByName(joined.drop("__uid"))


def overlap_pairs(a: DataFrame, b: DataFrame, bin_size: int = 512) -> DataFrame:
    """(contig, a_start, a_end, b_start, b_end, overlap) by an equi join on contig and bin; a pair is reported in its first common bin."""

    def binned(df: DataFrame, p: str) -> DataFrame:
        bins = F.explode(F.sequence(F.floor(F.col("start") / bin_size), F.floor((F.col("end") - 1) / bin_size)))
        return df.where("end > start").select("contig", F.col("start").alias(f"{p}_start"), F.col("end").alias(f"{p}_end"), bins.alias("bin"))

    pairs = binned(a, "a").join(binned(b, "b"), ["contig", "bin"]).where("a_start < b_end and b_start < a_end")
    pairs = pairs.where(F.floor(F.greatest("a_start", "b_start") / bin_size) == F.col("bin"))
    return pairs.select("contig", "a_start", "a_end", "b_start", "b_end", (F.least("a_end", "b_end") - F.greatest("a_start", "b_start")).alias("overlap"))


def nearest(a: DataFrame, b: DataFrame) -> DataFrame:
    """(contig, start, distance) of each row of a to the nearest start of b in its contig (null where there is none): two running looks over one sort."""
    both = a.select("contig", "start", F.lit(1).alias("is_a"), F.lit(None).cast("long").alias("at")).unionByName(b.select("contig", "start", F.lit(0).alias("is_a"), F.col("start").alias("at")))
    order = Window.partitionBy("contig").orderBy("start", "is_a")
    back = F.last("at", ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, 0))
    ahead = F.first("at", ignorenulls=True).over(order.rowsBetween(0, Window.unboundedFollowing))
    return both.select("contig", "start", "is_a", F.least(F.col("start") - back, ahead - F.col("start")).alias("distance")).where("is_a = 1").drop("is_a")


def covered(iv: DataFrame) -> DataFrame:
    """(regions, bases) of (contig, start, end)."""
    return merge_binned(iv).agg(F.count(F.lit(1)).alias("regions"), F.coalesce(F.sum(F.col("end") - F.col("start")), F.lit(0)).alias("bases"))
