"""Mixing sources to target weights: iterative proportional fitting, then sampling by calibrated probabilities.

Token totals are gathered for every (source, language, topic) cell. Raking scales the cells until the source, language and topic
marginals all meet their targets, each an array of shares or, by default, the present shares raised to a power and normalised.
A document's probability is its cell's raked weight over its present one, times one rate, at most 1; the rate is solved so
that the expected tokens are `keep` of the total. A hash of the id then decides, so a retry decides alike.

The cell table is small next to the documents, yet not bounded: up to `DRIVER_CELLS` cells (counted first) are raked in numpy on
the driver, more by the same sweeps as aggregations of a distributed table, under the same rule: the sweeps end when no marginal was further than
`TOLERANCE` from its target, or after `SWEEPS` (targets that the cells can't meet together never come that near). `achieved` reports what the marginals are after
probabilities were cut at 1 and documents drawn.

Documents has no topic, so the query takes the text's form for one (`form_topic`); the operator takes any column.

Defined results: a null source, language or topic is a category of its own; a text without a token (null, empty, white space) weighs nothing, has probability 1
and is kept. Rows repeated with one id are kept or left together; rows without an id
are decided by their text. All columns of the input return unchanged beside the added ones, whose names begin with `prefix`.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import discard, spool, spooled

DRIVER_CELLS, SWEEPS, TOLERANCE = 200_000, 500, 1e-10
DIMENSIONS = ("source", "lang", "topic")
POWERS = {"source": 0.5, "lang": 0.7, "topic": 0.8}


def token_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def form_topic(text: Column, tokens: Column) -> Column:
    """marked (a symbol to each 100 characters or more), short (under 50 tokens), long (1000 or more) or prose. A null or empty text is short."""
    symbols = F.length(text) - F.length(F.translate(text, "#*$%&|<>", ""))
    return F.when((symbols > 0) & (symbols * 100 >= F.length(text)), "marked").when(tokens < 50, "short").when(tokens >= 1000, "long").otherwise("prose")


def targets(cells: list[np.ndarray], tokens: np.ndarray, powers: dict[str, float]) -> list[np.ndarray]:
    out = []
    for code, name in zip(cells, DIMENSIONS, strict=True):
        share = np.bincount(code, tokens) / max(tokens.sum(), 1)
        share = np.where(share > 0, share, 0) ** powers[name] * (share > 0)
        out.append(share / max(share.sum(), 1e-300))
    return out


def rake(codes: list[np.ndarray], tokens: np.ndarray, goals: list[np.ndarray]) -> np.ndarray:
    """Cell shares that meet the goals (shares of each category of each dimension), nearest to tokens in relative entropy."""
    weight = tokens / max(tokens.sum(), 1)
    for _ in range(SWEEPS):
        worst = 0.0
        for code, goal in zip(codes, goals, strict=True):
            now = np.bincount(code, weight, len(goal))
            factor = np.divide(goal, now, out=np.ones_like(goal), where=now > 0)
            worst = max(worst, float(np.abs(now - goal)[now > 0].max(initial=0)))
            weight = weight * factor[code]
        if worst < TOLERANCE:
            break
    return weight


def rate(tokens: np.ndarray, weight: np.ndarray, keep: float) -> float:
    """The r of which sum(min(tokens, r * weight)) is keep * sum(tokens): cells fill up in order of tokens / weight."""
    has = (tokens > 0) & (weight > 0)
    t, w = tokens[has].astype(float), weight[has]
    if not len(t):
        return 0.0
    full = np.sort(t / w)
    order = np.argsort(t / w, kind="stable")
    done, open_ = np.concatenate([[0], np.cumsum(t[order])]), np.concatenate([np.cumsum(w[order][::-1])[::-1], [0]])
    goal = keep * t.sum()
    at = done[:-1] + full * open_[:-1]
    k = min(int(np.searchsorted(at, goal)), len(t) - 1)
    return float(min((goal - done[k]) / open_[k], full[-1]))


def cell_probabilities(spark: SparkSession, cells: DataFrame, keep: float, powers: dict[str, float]) -> DataFrame:
    """(source, lang, topic, share, probability) for cells (source, lang, topic, tokens)."""
    cells = spool(cells, "cells")
    if cells.limit(DRIVER_CELLS + 1).count() > DRIVER_CELLS:
        return _distributed(cells, keep, powers)
    pdf = cells.toPandas().sort_values(list(DIMENSIONS), na_position="first").reset_index(drop=True)
    codes = [pdf[c].astype(object).where(pdf[c].notna(), None).map(lambda x: ("", "") if x is None else ("s", x)).astype("category").cat.codes.to_numpy().astype(np.int64) for c in DIMENSIONS]
    tokens = pdf["tokens"].to_numpy(np.float64)
    weight = rake(codes, tokens, targets(codes, tokens, powers)) if len(pdf) else tokens
    r = rate(tokens, weight, keep)
    p = np.minimum(1.0, np.divide(r * weight, tokens, out=np.ones_like(tokens), where=tokens > 0))
    rows = [(*(None if x is None or x != x else x for x in row), float(w), float(q)) for row, w, q in zip(pdf[list(DIMENSIONS)].itertuples(index=False), weight, p, strict=True)]
    # At most DRIVER_CELLS rows, as counted above: small enough to broadcast, so the documents are not shuffled.
    return F.broadcast(spark.createDataFrame(rows, "source string, lang string, topic string, share double, probability double"))


def _distributed(cells: DataFrame, keep: float, powers: dict[str, float]) -> DataFrame:
    """The same sweeps over a cell table of any size; each dimension's marginals are an aggregation, joined back. Cut from its lineage by a spool at each sweep."""
    total = cells.agg(F.sum("tokens")).first()[0] or 1
    now = cells.withColumn("share", F.col("tokens") / F.lit(float(total)))
    goals = {}
    for c in DIMENSIONS:
        raw = now.groupBy(F.col(c).alias("g")).agg(F.sum("share").alias("s")).withColumn("s", F.when(F.col("s") > 0, F.pow("s", F.lit(powers[c]))).otherwise(0.0))
        goals[c] = spool(raw.crossJoin(F.broadcast(raw.agg(F.sum("s").alias("all")))).select("g", (F.col("s") / F.col("all")).alias("goal")), "goals")
    spark = cells.sparkSession
    for _ in range(SWEEPS):
        before, worst = len(spooled), 0.0
        for c in DIMENSIONS:
            have = now.groupBy(F.col(c).alias("g")).agg(F.sum("share").alias("have")).withColumnRenamed("g", "g2")
            factor = spool(goals[c].join(have, F.col("g").eqNullSafe(F.col("g2"))).select("g", "have", "goal", F.when(F.col("have") > 0, F.col("goal") / F.col("have")).otherwise(1.0).alias("factor")), "factors")
            worst = max(worst, factor.where("have > 0").agg(F.max(F.abs(F.col("have") - F.col("goal")))).first()[0] or 0.0)
            now = now.join(factor.select("g", "factor"), F.col(c).eqNullSafe(F.col("g"))).withColumn("share", F.col("share") * F.col("factor")).drop("g", "factor")
        now = spool(now, "raked")
        discard(spark, spooled[before:-1])
        if worst < TOLERANCE:
            break
    low, high = 0.0, float(now.agg(F.max(F.when(F.col("share") > 0, F.col("tokens") / F.col("share")))).first()[0] or 0)
    for _ in range(50):
        mid = (low + high) / 2
        got = now.agg(F.sum(F.least(F.col("tokens").cast("double"), mid * F.col("share")))).first()[0] or 0
        low, high = (mid, high) if got < keep * total else (low, mid)
    return now.select(*DIMENSIONS, "share", F.least(F.lit(1.0), F.when(F.col("tokens") > 0, high * F.col("share") / F.col("tokens")).otherwise(1.0)).alias("probability"))


def mix_to_targets(docs: DataFrame, *, keep: float = 0.5, powers: dict[str, float] = POWERS, seed: int = 4, topic: Column | None = None, prefix: str = "__") -> DataFrame:
    """docs with tokens, topic, share, probability and kept, all after the prefix."""
    text, p = F.col("text"), prefix
    marked = docs.withColumn(f"{p}tokens", token_count(text))
    marked = marked.withColumn(f"{p}topic", form_topic(text, F.col(f"{p}tokens")) if topic is None else topic)
    cells = marked.groupBy(F.col("source").cast("string").alias("source"), F.col("lang").cast("string").alias("lang"), F.col(f"{p}topic").alias("topic")).agg(F.sum(f"{p}tokens").alias("tokens"))
    found = cell_probabilities(docs.sparkSession, cells, keep, powers).withColumnsRenamed({"source": f"{p}s", "lang": f"{p}l", "topic": f"{p}t", "share": f"{p}share", "probability": f"{p}probability"})
    joined = marked.join(found, F.col("source").eqNullSafe(F.col(f"{p}s")) & F.col("lang").eqNullSafe(F.col(f"{p}l")) & F.col(f"{p}topic").eqNullSafe(F.col(f"{p}t")), "left").drop(f"{p}s", f"{p}l", f"{p}t")
    joined = joined.withColumn(f"{p}probability", F.when(F.col(f"{p}tokens") > 0, F.col(f"{p}probability")).otherwise(1.0))
    h = F.xxhash64(F.lit(seed), F.coalesce(F.col("doc_id").cast("string"), text, F.lit("")))
    uniform = F.shiftrightunsigned(h, 11) / F.lit(float(2**53))
    return joined.withColumn(f"{p}kept", uniform < F.col(f"{p}probability"))


def achieved(mixed: DataFrame, powers: dict[str, float] = POWERS) -> DataFrame:
    """(dimension, category, present, target, expected, drawn): token shares of mix_to_targets' result before, as aimed at, after probabilities were cut at 1, and as drawn."""
    out = None
    for name in DIMENSIONS:
        col = F.col("__topic") if name == "topic" else F.col(name).cast("string")
        t = F.col("__tokens").cast("double")
        sums = mixed.groupBy(F.lit(name).alias("dimension"), col.alias("category")).agg(F.sum(t).alias("present"), F.sum(t * F.col("__probability")).alias("expected"), F.sum(F.when(F.col("__kept"), t).otherwise(0.0)).alias("drawn"))
        sums = sums.withColumn("target", F.when(F.col("present") > 0, F.pow("present", F.lit(powers[name]))).otherwise(0.0))
        out = sums if out is None else out.unionByName(sums)
    total = out.groupBy("dimension").agg(*[F.sum(c).alias(f"all_{c}") for c in ("present", "target", "expected", "drawn")])
    share = lambda c: F.when(F.col(f"all_{c}") > 0, F.round(F.col(c) / F.col(f"all_{c}"), 9)).otherwise(0.0).alias(c)
    return out.join(F.broadcast(total), "dimension").select("dimension", "category", *[share(c) for c in ("present", "target", "expected", "drawn")])
