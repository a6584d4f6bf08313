"""Functions of this library in SQL text."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from seqlex.functions.bases import BASES, LETTERS
from seqlex.operators.greedy import PackedDict, offers, walk, winners


def register(spark: SparkSession, words: list[str] | None = None) -> None:
    """to_bases, revcomp, n_share and kmers as SQL functions that Catalyst inlines; motif_tokens as an Arrow UDF over the given words."""
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION to_bases(t STRING) RETURNS STRING RETURN regexp_replace(translate(regexp_replace(t, '[ \\t\\r\\n]', ''), '{LETTERS + LETTERS.upper()}', '{BASES * 2}'), '[^ACGT]', 'N')")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION revcomp(s STRING) RETURNS STRING RETURN reverse(translate(s, 'ACGT', 'TGCA'))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION n_share(s STRING) RETURNS DOUBLE RETURN CASE WHEN length(s) > 0 THEN (length(s) - length(replace(s, 'N', ''))) / length(s) ELSE 0 END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION kmers(s STRING, k INT) RETURNS ARRAY<STRING> RETURN CASE WHEN length(s) >= k THEN transform(sequence(1, length(s) - k + 1), i -> substring(s, i, k)) ELSE array() END")
    if words is not None:
        packed = PackedDict(words)

        @F.arrow_udf("array<string>")
        def motif_tokens(seqs: pa.Array) -> pa.Array:
            out = []
            for s in seqs.to_pylist():
                raw = (s or "").encode()
                if not raw:
                    out.append([])
                    continue
                length, _ = offers(packed, raw, 0, 0, len(raw), "longest", 0)
                places, _ = walk(length, winners(length, 2), 0, len(raw))
                out.append([s[p : p + int(length[p])] for p in places])
            return pa.array(out, pa.list_(pa.string()))

        spark.udf.register("motif_tokens", motif_tokens)
