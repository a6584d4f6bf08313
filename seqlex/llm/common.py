"""What the operators of this subpackage share: reading, spooling and text buffers."""

from __future__ import annotations

import ctypes
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text that a vectorised pass handles at a time; bounds the temporary arrays of a worker.
SLICE_BYTES = 1 << 20
#: Bytes of an Arrow batch on its way to a worker.
BATCH_BYTES = 4 << 20
#: Keys that a join takes out as the most frequent ones, and broadcasts, at most.
HOT = 1024
#: Folders written by spool() and not yet discarded.
spooled: list[str] = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share. A temporary one serves only where the session names none and all runs in one process (tests)."""
    sc = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not named:
        if not (sc.master == "local" or sc.master.startswith("local[")):
            raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="seqlex-"))
        named = sc.getCheckpointDir()
    return named


def spool(df: DataFrame, label: str) -> DataFrame:
    """df written as Parquet to the shared folder and read again: cuts the lineage, survives lost executors, goes with the JVM."""
    spark = df.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/seqlex-{label}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    jvm = spark._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(where)
    spooled.append(path)
    return spark.read.schema(df.schema).parquet(path)


def discard(spark: SparkSession, paths: list[str]) -> None:
    """Delete spooled folders that nothing reads any more."""
    for path in paths:
        where = spark._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
        if path in spooled:
            spooled.remove(path)


def fresh(columns: list[str], name: str) -> str:
    """name, or name with underscores before it where a column is called so (in whatever case)."""
    taken = {c.lower() for c in columns}
    while name.lower() in taken:
        name = f"_{name}"
    return name


def least_count(counts: DataFrame, column: str, bound: int) -> int:
    """The least count that at most bound rows have or exceed, by a histogram of the counts' binary logarithms in eighths."""
    n = F.col(column).cast("double")
    table = counts.where(n > 0).groupBy(F.floor(F.log2(n) * 8).cast("int").alias("k")).agg(F.count(F.lit(1)).alias("m"), F.min(column).alias("n")).collect()
    least, total = None, 0
    for r in sorted(table, key=lambda r: -r["k"]):
        if total + r["m"] > bound:
            break
        least, total = r["n"], total + r["m"]
    return least if least is not None else 2**63 - 1


def hot_keys(counts: DataFrame, on: list[str], n: str = "n") -> DataFrame:
    """The most frequent keys of counts (on, n), at most HOT of them, as rows of the plan."""
    rows = counts.where(F.col(n) >= least_count(counts, n, HOT)).select(*on).collect()
    return counts.sparkSession.createDataFrame(rows, counts.select(*on).schema)


def join_hot(left: DataFrame, right: DataFrame, on: list[str], hot: DataFrame, how: str = "inner") -> DataFrame:
    """left joined to right, which has a row for a key at most. Rows of left with a hot key (hot is bounded by HOT) meet a broadcast part of right and are
    not shuffled; the others meet by a shuffle, in which no key is frequent. The keys are not null."""
    here = F.broadcast(hot)
    often = left.join(here, on, "left_semi").join(F.broadcast(right.join(here, on, "left_semi")), on, how)
    return often.unionByName(left.join(here, on, "left_anti").join(right, on, how))


def split_by(df: DataFrame, key: Column, keys: DataFrame, name: str) -> tuple[DataFrame, DataFrame]:
    """(rows that may, rows that surely don't) have a key in keys' column `name`, without a shuffle of df. The keys are hashed into a bitmap of
    2**24 bits, of which at most 2**18 words are broadcast whatever the number of keys; an exact join of the first part must follow."""
    h = F.xxhash64(F.col(name))
    marks = keys.select(F.shiftrightunsigned(h, 46).alias("__word"), F.pmod(h, F.lit(64)).cast("int").alias("__bit")).groupBy("__word").agg(F.expr("bit_or(shiftleft(1L, __bit))").alias("__mask"))
    h = F.xxhash64(key)
    marked = df.withColumn("__word", F.shiftrightunsigned(h, 46)).withColumn("__bit", F.pmod(h, F.lit(64)).cast("int")).join(F.broadcast(marks), "__word", "left")
    maybe = F.expr("coalesce((shiftright(__mask, __bit) & 1L) = 1L, false)")
    return marked.where(maybe).select(*df.columns), marked.where(~maybe).select(*df.columns)


def id_crc(doc_id: str, modulus: int) -> Column:
    """crc32 of the id as text, modulo modulus; a null id counts as the empty text."""
    return F.crc32(F.coalesce(F.col(doc_id).cast("string"), F.lit("")).cast("binary")) % modulus


def utf8(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(offsets, bytes) of a string array, straight from the Arrow buffers; a null is an empty range."""
    if not len(column):
        return np.zeros(1, np.int64), np.zeros(0, np.uint8)
    column = column.cast(pa.large_string()) if column.type != pa.large_string() else column
    column = column.fill_null("") if column.null_count else column
    _, at, data = column.buffers()
    offsets = np.frombuffer(at, np.int64)[column.offset : column.offset + len(column) + 1]
    return offsets, np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)


def slices(offsets: np.ndarray, limit: int = SLICE_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges [a, b) of at most limit bytes each; a longer row stands alone."""
    a, n = 0, len(offsets) - 1
    while a < n:
        b = max(a + 1, int(np.searchsorted(offsets, offsets[a] + limit, "right")) - 1)
        yield a, min(b, n)
        a = min(b, n)


def give_back() -> None:
    """Memory that Arrow and the allocator hold but don't use goes back to the system. A worker lives on after its task and counts with its executor."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def bound_batches(spark: SparkSession) -> None:
    """Arrow batches of BATCH_BYTES at most from now on, unless the session has a lower bound. A batch stands in the executor's JVM (twice while its buffers grow) and in its
    Python worker at once, and by default it has 10,000 rows or 64 MB."""
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    now = spark.sparkContext._jvm.org.apache.spark.network.util.JavaUtils.byteStringAsBytes(spark.conf.get(key))
    if now <= 0 or now > BATCH_BYTES:
        spark.conf.set(key, str(BATCH_BYTES))


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (xor-shift and multiply), element by element."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))
