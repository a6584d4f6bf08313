"""Training segments under an equal budget."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def to_ids(tokens: DataFrame, vocab: DataFrame, unknown: str = "[UNK]") -> DataFrame:
    """(contig, ids) of (contig, tokens: structs with a token): a hash lookup in Arrow; the vocabulary is small by nature."""
    rows = [(r["token"], r["token_id"]) for r in vocab.select("token", "token_id").collect()]
    shared = tokens.sparkSession.sparkContext.broadcast(rows)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, ids = pa.array([t for t, _ in shared.value]), pa.array([i for _, i in shared.value], pa.int32())
        miss = dict(shared.value)[unknown]
        for batch in batches:
            lists = batch["tokens"]
            at = np.asarray(lists.offsets)
            found = ids.take(pc.index_in(lists.flatten().field("token"), value_set=known)).fill_null(miss)
            yield pa.RecordBatch.from_arrays([batch["contig"], pa.ListArray.from_arrays(pa.array(at - at[0], pa.int32()), found)], ["contig", "ids"])

    return tokens.select("contig", "tokens").mapInArrow(run, "contig long, ids array<int>")


def pack_segments(df: DataFrame, length: int = 512, tail: str = "keep", key: str = "contig") -> DataFrame:
    """(key, seg_no, tokens, n_tokens): a contig's token array in pieces of `length`; the last one kept, dropped, or filled with [PAD]."""
    n = F.size("tokens")
    pieces = F.transform(F.sequence(F.lit(0), F.greatest(F.lit(0), F.ceil(n / length).cast("int") - 1)), lambda k: F.slice(F.col("tokens"), k * length + 1, length))
    cut = df.where(n > 0).select(key, F.posexplode(pieces).alias("seg_no", "tokens")).withColumn("n_tokens", F.size("tokens"))
    if tail == "drop":
        return cut.where(F.col("n_tokens") == length)
    return cut.withColumn("tokens", F.concat("tokens", F.array_repeat(F.lit("[PAD]"), F.lit(length) - F.col("n_tokens")))) if tail == "pad" else cut


def pack_chunks(tokens: DataFrame, length: int = 512) -> DataFrame:
    """(contig, seg_no, slot, ...) for token rows that carry (contig, chunk_no, token_offset, tokens): the running index needs only the chunks'
    counts, so no window runs over tokens."""
    rows = tokens.select("contig", "token_offset", F.posexplode("tokens").alias("k", "t"))
    at = F.col("token_offset") + F.col("k")
    return rows.select("contig", F.floor(at / length).alias("seg_no"), (at % length).alias("slot"), "t.*")


def n_share(tokens: Column, rule: str = "all") -> Column:
    has = {"all": lambda t: (F.length(F.replace(t, F.lit("N"), F.lit(""))) == 0), "any": lambda t: F.contains(t, F.lit("N"))}
    if rule == "bases":
        text = F.array_join(tokens, "")
        return (F.length(text) - F.length(F.replace(text, F.lit("N"), F.lit("")))) / F.length(text)
    return F.size(F.filter(tokens, has[rule])) / F.size(tokens)


def drop_n_segments(segments: DataFrame, max_share: float = 0.5, rule: str = "all") -> DataFrame:
    return segments.withColumn("n_share", n_share(F.col("tokens"), rule)).where(F.col("n_share") <= max_share)


def masked(key: Column, prob: float, seed: int) -> Column:
    """Keyed Bernoulli draw by md5."""
    h = F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}|"), key)), 1, 8), 16, 10).cast("long")
    return h < int(prob * 2**32)


def mask_segments(segments: DataFrame, prob: float = 0.15, seed: int = 1) -> DataFrame:
    """(contig, seg_no, slot, token, input, selected): selected tokens become [MASK]."""
    rows = segments.select("contig", "seg_no", F.posexplode("tokens").alias("slot", "token"))
    rows = rows.withColumn("selected", masked(F.concat_ws("|", "contig", "seg_no", "slot"), prob, seed))
    return rows.withColumn("input", F.when(F.col("selected"), "[MASK]").otherwise(F.col("token")))


def training_budget(sizes: DataFrame, *, layers: int = 12, hidden: int = 768, ffn: int = 3072, max_len: int = 512, batch: int = 96, steps: int = 200_000) -> DataFrame:
    """(vocab_size, params, tokens, flops, bases_seen, epochs) of rows (vocab_size, corpus_bases, corpus_tokens): encoder weights, biases and norms, tied output with its transform, two
    segment types; the bases under the budget's tokens, at the tokenizer's bases a token, and how often they go through the corpus (null for a corpus without bases)."""
    vocab_size = F.col("vocab_size")
    embed = (vocab_size + max_len + 2) * hidden + 2 * hidden
    layer = 4 * (hidden * hidden + hidden) + 2 * hidden + hidden * ffn + ffn + ffn * hidden + hidden + 2 * hidden
    head = hidden * hidden + hidden + 2 * hidden + vocab_size
    params, tokens = embed + layers * layer + head, batch * max_len * steps
    seen = F.lit(float(tokens)) * F.col("corpus_bases") / F.nullif(F.col("corpus_tokens"), F.lit(0))
    sized = sizes.select("vocab_size", params.cast("long").alias("params"), F.lit(tokens).cast("long").alias("tokens"), seen.alias("bases_seen"), "corpus_bases")
    flops, epochs = F.lit(6.0) * F.col("params") * F.col("tokens"), F.col("bases_seen") / F.nullif(F.col("corpus_bases"), F.lit(0))
    return sized.select("vocab_size", "params", "tokens", flops.alias("flops"), "bases_seen", epochs.alias("epochs"))


def make_batches(segments: DataFrame, batch: int = 96, seed: int = 1) -> DataFrame:
    """(contig, seg_no, batch_no, slot): order by hash. The hash's first two digits deal segments to 256 groups, each filling its own batches, so no
    task sorts all segments."""
    h = F.md5(F.concat(F.lit(f"{seed}|"), F.concat_ws("|", "contig", "seg_no")))
    dealt = segments.select("contig", "seg_no", h.alias("h")).withColumn("group", F.substring("h", 1, 2))
    nth = F.row_number().over(Window.partitionBy("group").orderBy("h", "contig", "seg_no")) - 1
    return dealt.withColumn("nth", nth).select("contig", "seg_no", F.concat_ws("-", "group", F.floor(F.col("nth") / batch)).alias("batch_no"), (F.col("nth") % batch).alias("slot"))


def truncate_pad(ids: Column, max_len: int, pad: int) -> tuple[Column, Column]:
    cut = F.slice(ids, 1, max_len)
    missing = F.lit(max_len) - F.size(cut)
    return F.concat(cut, F.array_repeat(F.lit(pad), missing)), F.concat(F.array_repeat(F.lit(1), F.size(cut)), F.array_repeat(F.lit(0), missing))
