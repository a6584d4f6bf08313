"""Scores, a relational naive Bayes, and token attribution."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from seqlex.functions.bases import mcc


def confusion(pred: DataFrame, *by: str) -> DataFrame:
    """(by, tp, tn, fp, fn) of rows (y, yhat)."""
    n = lambda y, h: F.count_if((F.col("y") == y) & (F.col("yhat") == h))
    return pred.groupBy(*by).agg(n(1, 1).alias("tp"), n(0, 0).alias("tn"), n(0, 1).alias("fp"), n(1, 0).alias("fn"))


def scores(pred: DataFrame, *by: str) -> DataFrame:
    c = confusion(pred, *by)
    m = F.round(mcc(F.col("tp"), F.col("tn"), F.col("fp"), F.col("fn")), 6)
    return c.withColumn("mcc", m).withColumn("accuracy", F.round((F.col("tp") + F.col("tn")) / (F.col("tp") + F.col("tn") + F.col("fp") + F.col("fn")), 6))


def mcc_multiclass(pred: DataFrame, y: str = "y", yhat: str = "yhat") -> DataFrame:
    """The generalised correlation from class margins and the trace; equals the binary one for two classes."""
    cells = pred.groupBy(F.col(y).alias("y"), F.col(yhat).alias("h")).agg(F.count(F.lit(1)).cast("double").alias("n"))
    true, said = cells.groupBy("y").agg(F.sum("n").alias("t")), cells.groupBy("h").agg(F.sum("n").alias("p"))
    margins = true.join(said, F.col("y") == F.col("h"), "full").select(F.coalesce("t", F.lit(0.0)).alias("t"), F.coalesce("p", F.lit(0.0)).alias("p"))
    m = margins.agg(F.sum(F.col("t") * F.col("p")).alias("tp"), F.sum(F.col("t") * F.col("t")).alias("tt"), F.sum(F.col("p") * F.col("p")).alias("pp"), F.sum("t").alias("s"))
    c = cells.agg(F.coalesce(F.sum(F.when(F.col("y") == F.col("h"), F.col("n"))), F.lit(0.0)).alias("c"))
    s2 = F.col("s") * F.col("s")
    below = (s2 - F.col("pp")) * (s2 - F.col("tt"))
    return m.crossJoin(c).select(F.round(F.when(below > 0, (F.col("c") * F.col("s") - F.col("tp")) / F.sqrt(below)).otherwise(0.0), 6).alias("mcc"))


def mean_std(results: DataFrame, *by: str, value: str = "value", ddof: int = 1) -> DataFrame:
    std = F.stddev_samp(value) if ddof else F.stddev_pop(value)
    return results.groupBy(*by).agg(F.round(F.avg(value), 6).alias("mean"), F.round(std, 6).alias("std"), F.count(F.lit(1)).alias("n"))


def places(means: DataFrame, *by: str) -> DataFrame:
    """means with `place`: 1 for the highest mean of each group, 2 for the second; equal means share a place."""
    return means.withColumn("place", F.dense_rank().over(Window.partitionBy(*by).orderBy(F.desc("mean"))))


def profile(rows: DataFrame) -> DataFrame:
    """(id, token, n) of rows (id, token)."""
    return rows.groupBy("id", "token").agg(F.count(F.lit(1)).alias("n"))


def nb_train(counts: DataFrame, labels: DataFrame) -> tuple[DataFrame, DataFrame]:
    """((token, y, w), (y, prior)): log of smoothed token shares and class shares; labels are (id, y) of the training rows."""
    joined = counts.join(labels, "id")
    by_class = joined.groupBy("y").agg(F.sum("n").alias("all"))
    tokens = joined.select("token").distinct()
    v = tokens.agg(F.count(F.lit(1)).alias("v"))
    grid = tokens.crossJoin(F.broadcast(by_class.crossJoin(v)))  # tokens x classes: the model itself
    seen = joined.groupBy("token", "y").agg(F.sum("n").alias("n"))
    w = grid.join(seen, ["token", "y"], "left").select("token", "y", F.ln((F.coalesce("n", F.lit(0)) + 1.0) / (F.col("all") + F.col("v"))).alias("w"))
    total = labels.agg(F.count(F.lit(1)).alias("rows"))
    prior = labels.groupBy("y").agg(F.count(F.lit(1)).alias("n")).crossJoin(total).select("y", F.ln(F.col("n") / F.col("rows")).alias("prior"))
    return w, prior


def nb_predict(counts: DataFrame, w: DataFrame, prior: DataFrame) -> DataFrame:
    """(id, yhat, score): the best class, ties (to nine places) to the smaller one."""
    s = counts.join(w, "token").groupBy("id", "y").agg(F.sum(F.col("n") * F.col("w")).alias("s")).join(F.broadcast(prior), "y")
    s = s.select("id", "y", F.round(F.col("s") + F.col("prior"), 6).alias("score"))
    nth = F.row_number().over(Window.partitionBy("id").orderBy(F.desc("score"), "y"))
    return s.withColumn("nth", nth).where("nth = 1").select("id", F.col("y").alias("yhat"), "score")


def attribution(counts: DataFrame, w: DataFrame, prior: DataFrame, yes, no) -> DataFrame:
    """(id, token, score): integrated gradients of the logistic of the class margin from the empty profile. The margin is linear in the counts, so the path
    integral has a closed form: n w (sigma(z) - sigma(z0)) / (z - z0)."""
    diff = w.groupBy("token").agg(F.sum(F.when(F.col("y") == yes, F.col("w")).when(F.col("y") == no, -F.col("w"))).alias("d"))
    z0 = prior.agg(F.sum(F.when(F.col("y") == yes, F.col("prior")).when(F.col("y") == no, -F.col("prior"))).alias("z0"))
    parts = counts.join(diff, "token").withColumn("part", F.col("n") * F.col("d"))
    rise = F.sum("part").over(Window.partitionBy("id"))
    sig = lambda x: 1 / (1 + F.exp(-F.greatest(F.lit(-700.0), x)))
    out = parts.withColumn("rise", rise).crossJoin(F.broadcast(z0))
    slope = F.when(F.abs(F.col("rise")) > 1e-9, (sig(F.col("z0") + F.col("rise")) - sig(F.col("z0"))) / F.col("rise")).otherwise(sig(F.col("z0")) * (1 - sig(F.col("z0"))))
    return out.select("id", "token", (F.col("part") * slope).alias("score"), "rise", "z0")
