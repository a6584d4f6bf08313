"""Beside the greedy scan: what every place offers, the scan as a recursive query, and the segmentation that covers most bases by motifs."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from seqlex.operators import greedy as G
from seqlex.sources.tables import settled


def position_best(df: DataFrame, words: list[str], *, pick: str = "random", seed: int = 7, min_len: int = 4, max_len: int = 12) -> DataFrame:
    """(contig, pos, len, kind): the offer of each place of (contig, seq), a word by the pick rule, else a 3-mer, else one base."""
    packed = df.sparkSession.sparkContext.broadcast(G.PackedDict(words, min_len, max_len))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for contig, seq in zip(batch["contig"].to_pylist(), batch["seq"].to_pylist(), strict=True):
                raw = (seq or "").encode()
                if not raw:
                    continue
                length, kind = G.offers(packed.value, raw, contig, 0, len(raw), pick, seed)
                key = pa.repeat(pa.scalar(contig, pa.int64()), len(raw))
                yield pa.RecordBatch.from_arrays([key, pa.array(np.arange(len(raw)), pa.int64()), pa.array(length, pa.int64()), pa.array(G.KINDS[kind], pa.string())], ["contig", "pos", "len", "kind"])

    return df.select("contig", "seq").mapInArrow(run, "contig long, pos long, len long, kind string")


def greedy_recursive(df: DataFrame, words: list[str], *, pick: str = "random", seed: int = 7, max_offset: int = 2, max_steps: int = 1000) -> DataFrame:
    """(contig, idx, pos, len, token, kind): the scan as a recursive query, a level for each step. For small inputs, as a reference; a contig of more than max_steps tokens is an error of Spark's."""
    spark = df.sparkSession
    offers = position_best(df, words, pick=pick, seed=seed)
    w = Window.partitionBy("contig").orderBy("pos")
    rivals = [F.struct(F.coalesce(F.lead("len", o).over(w), F.lit(0)).alias("size"), F.lit(-o).alias("back")) for o in range(max_offset + 1)]
    jump = offers.withColumn("best", F.array_max(F.array(*rivals))).select("contig", F.col("pos").alias("i"), (F.col("pos") - F.col("best.back")).alias("pos"), F.col("best.size").alias("len"))
    kinds = offers.select("contig", "pos", "kind")
    view = f"jump_{abs(hash((pick, seed, max_offset, id(df))))}"
    settled(jump.join(kinds, ["contig", "pos"]).select("*", (F.col("pos") + F.col("len")).alias("next"))).createOrReplaceTempView(view)
    walk = spark.sql(f"""WITH RECURSIVE walk(contig, i, idx) MAX RECURSION LEVEL {max_steps} AS (
        SELECT contig, i, 0 FROM {view} WHERE i = 0
        UNION ALL SELECT j.contig, j.next, w.idx + 1 FROM walk w JOIN {view} j ON w.contig = j.contig AND w.i = j.i)
        SELECT w.contig, w.idx, j.pos, j.len, j.kind FROM walk w JOIN {view} j ON w.contig = j.contig AND w.i = j.i""")
    cut = F.expr("substring(seq, cast(pos + 1 as int), cast(len as int))").alias("token")
    return walk.join(df.select("contig", "seq"), "contig").select("contig", "idx", "pos", "len", cut, "kind")


def best_cover(words: G.PackedDict, raw: bytes) -> tuple[list[int], np.ndarray, np.ndarray]:
    """(places, length, kind) of the segmentation with most bases under words; of those with the fewest tokens, and then with the longest token first."""
    n = len(raw)
    mask = words.matches(raw).tolist()
    c = np.concatenate([G._code[np.frombuffer(raw, np.uint8)] < 4, [False] * 2])
    clean = (c[:-2] & c[1:-1] & c[2:]).tolist()
    weight, value = n + 1, [0] * (n + words.max_len + 1)
    length, kind = [1] * n, [0] * n
    for i in range(n - 1, -1, -1):
        best, size, what = value[i + 1] - 1, 1, 0
        if clean[i] and value[i + 3] - 1 >= best:
            best, size, what = value[i + 3] - 1, 3, 1
        m = mask[i]
        while m:
            k = (m & -m).bit_length() - 1
            m &= m - 1
            gain = value[i + k] + k * weight - 1
            if gain >= best:
                best, size, what = gain, k, 2
        value[i], length[i], kind[i] = best, size, what
    at, places = 0, []
    while at < n:
        places.append(at)
        at += length[at]
    return places, np.array(length, np.int64), np.array(kind, np.int64)


def coverage_tokenize(df: DataFrame, words: list[str], *, min_len: int = 4, max_len: int = 12) -> DataFrame:
    """(contig, n_bases, tokens), and lang where there is one: an extension of the greedy scan, a dynamic programme over each sequence (about nine steps a base, memory in its length)."""
    more = ["lang"] if "lang" in df.columns else []
    packed = df.sparkSession.sparkContext.broadcast(G.PackedDict(words, min_len, max_len))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, batch.num_rows, 256):
                part, rows, sizes = batch.slice(a, 256), [], []
                for seq in part["seq"].to_pylist():
                    seq = seq or ""
                    raw = seq.encode()
                    places, length, kind = best_cover(packed.value, raw) if raw else ([], np.zeros(0, int), np.zeros(0, int))
                    rows.append(G._emit(seq, places, length, kind, 0, "drop", 0, len(raw)))
                    sizes.append(len(raw))
                yield pa.RecordBatch.from_arrays([part["contig"], pa.array(sizes, pa.int64()), G._arrays(rows), *(part[c] for c in more)], ["contig", "n_bases", "tokens", *more])

    return df.select("contig", "seq", *more).mapInArrow(run, f"contig long, n_bases long, tokens {G.TOKENS}" + "".join(f", {c} string" for c in more))
