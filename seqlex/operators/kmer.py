"""Overlapping and disjoint k-mer tokenizers."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bases that a worker counts at once.
SLICE = 4_000_000

_code = np.full(256, 4, np.int64)
for _i, _b in enumerate(b"ACGT"):
    _code[_b] = _i


def kmers(seq: Column, k: int, stride: int, remainder: str = "onemer", n_policy: str = "keep", letters: Column | None = None) -> Column:
    """Array of tokens. With stride k the last n mod k bases become 1-mers (onemer), nothing (drop) or one short token (short).
    A k-mer with an N stays (keep), becomes the unknown token (unk) or its bases (onemer). With the bases at hand as an array, the cost is linear."""
    n = F.length(seq)
    piece = (lambda i: F.substring(seq, i + 1, F.lit(k))) if letters is None else (lambda i: F.concat(*[letters[i + j] for j in range(k)]))
    full = F.when(n >= k, F.transform(F.sequence(F.lit(0), n - k, F.lit(stride)), piece)).otherwise(F.array().cast("array<string>"))
    if n_policy == "unk":
        full = F.transform(full, lambda t: F.when(F.contains(t, F.lit("N")), "[UNK]").otherwise(t))
    elif n_policy == "onemer":
        full = F.flatten(F.transform(full, lambda t: F.when(F.contains(t, F.lit("N")), F.split(t, "")).otherwise(F.array(t))))
    if stride != k or remainder == "drop":
        return full
    rest = F.substring(seq, F.lit(1) + n - n % k, n % k)
    tail = F.split(rest, "") if remainder == "onemer" else F.array(rest)
    return F.concat(full, F.when(n % k > 0, tail).otherwise(F.array().cast("array<string>")))


def kmer_tokens(df: DataFrame, k: int, stride: int = 1, remainder: str = "onemer", n_policy: str = "keep") -> DataFrame:
    """A substring is linear in its place, so the bases are split once (through an explode, as in contigs()) and k-mers are read from the array."""
    split = df.select("*", F.explode(F.array(F.split("seq", ""))).alias("__letters"))
    return split.withColumn("tokens", kmers(F.col("seq"), k, stride, remainder, n_policy, F.col("__letters"))).drop("__letters")


class Cutter:
    """The tokens of kmer_tokens as numbers: codes to base five, and after them the bases of the remainder."""

    def __init__(self, k: int, stride: int = 1) -> None:
        self.k, self.stride = k, stride
        self.size = 5**k + (5 if stride == k > 1 else 0)

    def __call__(self, keys: np.ndarray, seqs: list[str]) -> tuple[np.ndarray, np.ndarray]:
        code, sizes = _code[np.frombuffer("".join(seqs).encode(), np.uint8)], np.array([len(s) for s in seqs], np.int64)
        of = np.repeat(np.arange(len(seqs)), sizes)
        place = np.arange(len(code)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
        ids = np.zeros(len(code), np.int64)
        for j in range(self.k):
            ids[: len(code) - j] = ids[: len(code) - j] * 5 + code[j:]
        keep = (sizes[of] - place >= self.k) & (place % self.stride == 0)
        if self.stride == self.k > 1:
            rest = place >= (sizes - sizes % self.k)[of]
            ids[rest] = 5**self.k + code[rest]
            keep |= rest
        return ids[keep], of[keep]


def kmer_vocab(spark: SparkSession, k: int) -> DataFrame:
    """All 4**k strings over A, C, G, T: each number of range(4**k) read to base four."""
    code = F.col("id")
    letters = [F.substring(F.lit("ACGT"), (F.floor(code / 4 ** (k - 1 - j)) % 4 + 1).cast("int"), F.lit(1)) for j in range(k)]
    return spark.range(4**k).select(F.concat(*letters).alias("token"))


def token_counts(df: DataFrame, *by: str) -> DataFrame:
    return df.select(*by, F.explode("tokens").alias("token")).groupBy(*by, "token").agg(F.count(F.lit(1)).alias("n"))


def kmer_counts(contigs: DataFrame, k: int, stride: int = 1, by: str | None = None) -> DataFrame:
    """(by, token, n) over whole contigs, with the tokens of kmer_tokens. Workers count packed codes (base five) of a slice at a time, in an array where 5**k is small and by
    sorting beyond, and hand on a row for each different token only."""
    kinds, dense = 5**k, 5**k <= 1 << 20

    def rows(group, codes: np.ndarray, n: np.ndarray, width: int) -> pa.RecordBatch:
        letters = np.frombuffer(b"ACGTN", np.uint8)[codes[:, None] // 5 ** np.arange(width - 1, -1, -1) % 5]
        tokens = pa.Array.from_buffers(pa.string(), len(codes), [None, pa.py_buffer(np.arange(0, width * len(codes) + 1, width, dtype=np.int32)), pa.py_buffer(np.ascontiguousarray(letters).tobytes())])
        return pa.RecordBatch.from_arrays([pa.array([group] * len(codes), pa.string()), tokens, pa.array(n, pa.int64())], ["by", "token", "n"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        totals: dict = {}
        ones: dict = {}
        for batch in batches:
            groups = batch["by"].to_pylist()
            for group in dict.fromkeys(groups):
                own = [s for s, g in zip(batch["seq"].to_pylist(), groups, strict=True) if g == group and s]
                a = 0
                while a < len(own):
                    b, size = a, 0
                    while b < len(own) and (b == a or size < SLICE):
                        size, b = size + len(own[b]), b + 1
                    code = _code[np.frombuffer("".join(own[a:b]).encode(), np.uint8)]
                    sizes = np.array([len(s) for s in own[a:b]])
                    place = np.arange(len(code)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
                    left = np.repeat(sizes, sizes) - place
                    packed = np.zeros(max(0, len(code) - k + 1), np.int64)
                    for j in range(k):
                        packed = packed * 5 + code[j : j + len(packed)]
                    packed = packed[((left >= k) & (place % stride == 0))[: len(packed)]]
                    if dense:
                        totals[group] = totals.get(group, 0) + np.bincount(packed, minlength=kinds)
                    else:
                        yield rows(group, *np.unique(packed, return_counts=True), k)
                    if stride == k and k > 1:
                        rest = code[place >= np.repeat(sizes - sizes % k, sizes)]
                        ones[group] = ones.get(group, 0) + np.bincount(rest, minlength=5)
                    a = b
        for found, width in ((totals, k), (ones, 1)):
            for group, n in found.items():
                yield rows(group, np.flatnonzero(n), n[n > 0], width)

    label = F.lit(None).cast("string") if by is None else F.col(by)
    counts = contigs.select(label.alias("by"), "seq").mapInArrow(run, "by string, token string, n long").groupBy("by", "token").agg(F.sum("n").alias("n"))
    return counts.drop("by") if by is None else counts.withColumnRenamed("by", by)
