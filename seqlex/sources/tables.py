"""The given tables, and the projections that stand in for genomes and annotations."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seqlex.functions.bases import first_bases, to_bases


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def checkpoint_dir(spark: SparkSession) -> str:
    """The folder that the session names for checkpoints. A temporary one serves only where it names none and all runs in one process (tests)."""
    sc = spark.sparkContext
    if not sc.getCheckpointDir():
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not (sc.master == "local" or sc.master.startswith("local[")):
            raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="seqlex-"))
    return sc.getCheckpointDir()


def settled(df: DataFrame) -> DataFrame:
    """Lineage cut by a checkpoint in the folder that the session names."""
    checkpoint_dir(df.sparkSession)
    return df.checkpoint()


def stored(df: DataFrame) -> DataFrame:
    """df written as compressed Parquet within the folder for checkpoints and read again, for what is read several times; a checkpoint takes a few times the space. It goes with the JVM."""
    spark = df.sparkSession
    path = f"{checkpoint_dir(spark).rstrip('/')}/seqlex-rows-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(where)
    return spark.read.schema(df.schema).parquet(path)


def spread(df: DataFrame) -> DataFrame:
    """A scan dealt to as many tasks as there are cores where it gives fewer (a file of one row group is one task); larger scans are left alone."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if df.rdd.getNumPartitions() < cores else df


def contigs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(contig, seq, lang): a document as a contig. Only three columns are read.

    The bases pass through a one-element explode: a projection alone would be inlined into the lambdas of later array functions and into
    filters pushed below them, and so be computed anew for each element."""
    docs = spread(table(spark, sf_dir, "documents").select("doc_id", "text", "lang"))
    return docs.select(F.col("doc_id").alias("contig"), F.explode(F.array(to_bases("text"))).alias("seq"), "lang")


def prefixes(spark: SparkSession, sf_dir: str, length: int = 300) -> DataFrame:
    """The first bases of contigs; only their letters are turned to bases. They are dealt out after the cut, so no whole text is shuffled."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    return spread(docs.select(F.col("doc_id").alias("contig"), F.explode(F.array(first_bases("text", length))).alias("seq"), "lang"))


def chunks(df: DataFrame, size: int, halo: int = 14) -> DataFrame:
    """(contig, chunk_no, start, n, bases): pieces of size bases with halo bases of the next piece; n is the contig's length."""
    n = F.length("seq")
    places = F.sequence(F.lit(0), F.greatest(F.lit(0), F.floor((n - 1) / size)).cast("int"))
    pieces = F.transform(places, lambda c: F.struct(c.alias("chunk_no"), (c * size).alias("start"), F.substring(F.col("seq"), c * size + 1, F.lit(size + halo)).alias("bases")))
    return df.select("contig", n.cast("int").alias("n"), F.inline(pieces)).select("contig", "chunk_no", "start", "n", "bases")


def slices(df: DataFrame, length: int, step: int) -> DataFrame:
    """Full windows of `length` bases every `step`."""
    n = F.length("seq")
    fits = df.where(n >= length)
    return fits.select("contig", "lang", F.posexplode(F.transform(F.sequence(F.lit(0), n - length, F.lit(step)), lambda s: F.substring(F.col("seq"), s + 1, F.lit(length)))).alias("slice_no", "seq"))
