"""Aggregate and table functions of this library for SQL text."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

from seqlex.operators.greedy import KINDS, PackedDict, offers, walk, winners


@F.pandas_udf(DoubleType())
def entropy_bits(tokens: pd.Series) -> float:
    """Shannon entropy of a group's tokens. A group is held whole: where one may be large, count its tokens first and take the entropy of the counts (`usage_entropy`)."""
    share = tokens.dropna().value_counts(normalize=True).to_numpy()
    return float(-(share * np.log2(share)).sum()) if len(share) else 0.0


@F.pandas_udf(DoubleType())
def mcc_of(y: pd.Series, yhat: pd.Series) -> float:
    """Correlation of two 0/1 columns, 0 where a margin is empty; rows with a null take no part."""
    known = y.notna() & yhat.notna()
    a, b = y[known].to_numpy(float), yhat[known].to_numpy(float)
    n, tp = len(a), float((a * b).sum())
    below = a.sum() * (n - a.sum()) * b.sum() * (n - b.sum())
    return float((tp * n - a.sum() * b.sum()) / np.sqrt(below)) if below > 0 else 0.0


def token_table(words: list[str], seed: int = 7, pick: str = "longest"):
    """A table function: the tokens of a sequence as rows (pos, len, token, kind)."""
    packed = PackedDict(words)

    @F.udtf(returnType="pos int, len int, token string, kind string")
    class Tokens:
        def eval(self, seq: str):
            raw = (seq or "").encode()
            if raw:
                length, kind = offers(packed, raw, 0, 0, len(raw), pick, seed)
                for p in walk(length, winners(length, 2), 0, len(raw))[0]:
                    yield p, int(length[p]), seq[p : p + int(length[p])], str(KINDS[kind[p]])

    return Tokens


def register_aggregates(spark: SparkSession, words: list[str] | None = None) -> None:
    """entropy_bits and mcc_of as aggregates; motif_rows(seq), for a LATERAL join, over the given words."""
    spark.udf.register("entropy_bits", entropy_bits)
    spark.udf.register("mcc_of", mcc_of)
    if words is not None:
        spark.udtf.register("motif_rows", token_table(words))
