"""Weight matrices to consensus strings, and the dictionary built from them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from seqlex.functions.bases import revcomp

# Special tokens and one-letter tokens of every vocabulary.
SPECIALS = ("[PAD]", "[UNK]", "[CLS]", "[SEP]", "[MASK]")
ONE = ("A", "C", "G", "T", "N")
MATRICES = 879


def matrices(embeddings: DataFrame) -> DataFrame:
    """(motif_id, width, family, rows): rows are the four probabilities of each position; squares of positive parts, 0.25 where all are zero."""
    width = (F.lit(5) + F.col("vec_id") % 12).cast("int")

    def row(p: Column) -> Column:
        w = [F.greatest(F.element_at("embedding", (p * 4 + j + 1).cast("int")).cast("double"), F.lit(0.0)) for j in range(4)]
        w = [x * x for x in w]
        total = w[0] + w[1] + w[2] + w[3]
        return F.array(*[F.when(total > 0, x / total).otherwise(F.lit(0.25)) for x in w])

    return embeddings.where(F.col("vec_id") < MATRICES).select(F.col("vec_id").alias("motif_id"), width.alias("width"), F.col("label").alias("family"), F.transform(F.sequence(F.lit(0), width - 1), row).alias("rows"))


def normalise(counts: DataFrame) -> DataFrame:
    """(motif_id, pos, a, c, g, t) counts to probabilities."""
    total = F.col("a") + F.col("c") + F.col("g") + F.col("t")
    return counts.select("motif_id", "pos", *[F.when(total > 0, F.col(b) / total).otherwise(F.lit(0.25)).alias(b) for b in "acgt"])


def marked(rows: Column, threshold: float) -> Column:
    """One letter a position: upper case where the largest probability reaches the threshold, else lower case (a wildcard)."""

    def letter(r: Column) -> Column:
        top = F.array_max(r)
        at = F.array_position(r, top).cast("int")
        return F.substring(F.when(top >= threshold, F.lit("ACGT")).otherwise(F.lit("acgt")), at, F.lit(1))

    return F.array_join(F.transform(rows, letter), "")


def consensus(m: DataFrame, *, threshold: float = 0.5, max_width: int = 12, interior: str = "argmax") -> DataFrame:
    """(motif_id, family, seq): wildcard ends trimmed; wildcards inside take their likeliest base, or with interior='reject' drop the motif."""
    kept = m.where(F.col("width") <= max_width).withColumn("seq", F.regexp_replace(marked(F.col("rows"), threshold), "^[acgt]+|[acgt]+$", ""))
    kept = kept.where(F.length("seq") > 0)
    if interior == "reject":
        kept = kept.where(~F.col("seq").rlike("[acgt]"))
    return kept.select("motif_id", "family", F.upper("seq").alias("seq"))


def both_strands(c: DataFrame) -> DataFrame:
    """(seq, n_sources): strings and reverse complements, each once."""
    return c.select("motif_id", "seq").unionByName(c.select("motif_id", revcomp("seq").alias("seq"))).groupBy("seq").agg(F.countDistinct("motif_id").alias("n_sources"))


def build_vocab(spark: SparkSession, motifs: DataFrame) -> DataFrame:
    """(token_id, token, kind, len): specials, 1-mers, 3-mers, motifs, numbered in this order and by token. At most a few thousand rows."""
    fixed = [(t, 0, "special") for t in SPECIALS] + [(t, 1, "one") for t in ONE] + [(a + b + c, 2, "three") for a in "ACGT" for b in "ACGT" for c in "ACGT"]
    rows = spark.createDataFrame(fixed, "token string, rank int, kind string").unionByName(motifs.select(F.col("seq").alias("token"), F.lit(3).alias("rank"), F.lit("motif").alias("kind")))
    first = rows.groupBy("token").agg(F.min(F.struct("rank", "kind")).alias("k"))
    order = Window.orderBy("k.rank", "token")
    return first.select((F.row_number().over(order) - 1).alias("token_id"), "token", F.col("k.kind").alias("kind"), F.length("token").alias("len"))


def information(m: DataFrame) -> DataFrame:
    """(motif_id, bits): two bits a position less its entropy."""
    bits = F.aggregate("rows", F.lit(0.0), lambda acc, r: acc + 2.0 + F.aggregate(r, F.lit(0.0), lambda s, p: s + F.when(p > 0, p * F.log2(p)).otherwise(0.0)))
    return m.select("motif_id", bits.alias("bits"))


def sweep(m: DataFrame, thresholds: list[float], max_width: int = 12) -> DataFrame:
    """(threshold, motifs, mean_len, wildcard_share) for each threshold, in one pass over the matrices."""
    thin = m.where(F.col("width") <= max_width)
    each = [F.struct(F.lit(t).alias("threshold"), marked(F.col("rows"), t).alias("m")) for t in thresholds]
    long = thin.select("motif_id", F.explode(F.array(*each)).alias("x")).select("x.*")
    seq = F.regexp_replace("m", "^[acgt]+|[acgt]+$", "")
    return long.groupBy("threshold").agg(
        F.count_if(F.length(seq) > 0).alias("motifs"),
        F.round(F.avg(F.when(F.length(seq) > 0, F.length(seq))), 6).alias("mean_len"),
        F.round(F.sum(F.length(F.regexp_replace("m", "[A-Z]", ""))) / F.sum(F.length("m")), 6).alias("wildcard_share"),
    )
