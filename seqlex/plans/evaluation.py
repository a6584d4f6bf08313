"""Scores, splits, naive Bayes, attribution."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from seqlex.functions import bases as B
from seqlex.functions.bases import keyed_fold
from seqlex.operators import greedy as G
from seqlex.operators import kmer as K
from seqlex.operators import models as M
from seqlex.operators import pwm as V
from seqlex.sources import tables as T

from . import sql as S
from .registry import query
from .sequence import words

FOLD = "('0x' || substr(md5('{}|' || {}), 1, 8))::BIGINT % 10"
TOK = "list_concat(list_transform(range(0, greatest(0, length(seq) - 5), 6), lambda i: substr(seq, i + 1, 6)), list_transform(range(length(seq) - length(seq) % 6, length(seq)), lambda i: substr(seq, i + 1, 1)))"
NB = f"""{S.PREFIXES}, f AS (SELECT contig AS id, lang AS y, {FOLD.format('nb', 'contig')} AS fold, {TOK} AS tokens FROM prefixes),
c AS (SELECT id, token, count(*) AS n FROM (SELECT id, unnest(tokens) AS token FROM f) GROUP BY 1, 2), tr AS (SELECT id, y FROM f WHERE fold <> 0),
j AS (SELECT c.*, y FROM c JOIN tr USING (id)), cl AS (SELECT y, sum(n) AS total FROM j GROUP BY y), tk AS (SELECT DISTINCT token FROM j),
w AS (SELECT tk.token, cl.y, ln((coalesce(s.n, 0) + 1.0) / (cl.total + (SELECT count(*) FROM tk))) AS w FROM tk, cl LEFT JOIN (SELECT token, y, sum(n) AS n FROM j GROUP BY 1, 2) s ON s.token = tk.token AND s.y = cl.y),
pr AS (SELECT y, ln(count(*) / (SELECT count(*) FROM tr)) AS prior FROM tr GROUP BY y),
sc AS (SELECT id, y, round(sum(n * w) + any_value(prior), 6) AS score FROM c JOIN f USING (id, y) RIGHT JOIN (SELECT 1) ON false GROUP BY 1, 2),
p AS (SELECT id, y AS yhat, score FROM (SELECT id, y, score, row_number() OVER (PARTITION BY id ORDER BY score DESC, y) AS nth FROM (SELECT c.id, w.y, round(sum(c.n * w.w) + any_value(pr.prior), 6) AS score FROM c JOIN f ON c.id = f.id AND f.fold = 0 JOIN w ON c.token = w.token JOIN pr ON pr.y = w.y GROUP BY 1, 2)) WHERE nth = 1)"""
NB = "\n".join(line for line in NB.split("\n") if not line.startswith("sc AS"))


def profiles(spark, d) -> tuple[DataFrame, DataFrame]:
    """(counts (id, token, n), rows (id, y, fold)) of disjoint 6-mers of 300-base prefixes by language."""
    p = T.prefixes(spark, d)
    f = K.kmer_tokens(p, 6, 6).select(F.col("contig").alias("id"), F.col("lang").alias("y"), keyed_fold("nb", F.col("contig")).alias("fold"), "tokens")
    return M.profile(f.select("id", F.explode("tokens").alias("token"))), f.select("id", "y", "fold")


def predictions(spark, d) -> DataFrame:
    counts, rows = profiles(spark, d)
    w, prior = M.nb_train(counts, rows.where("fold <> 0").select("id", "y"))
    test = rows.where("fold = 0")
    return M.nb_predict(counts.join(test.select("id"), "id", "left_semi"), w, prior).join(test.select("id", "y"), "id")


@query("nb_sql", f"WITH {NB} SELECT p.id, yhat, score, f.y FROM p JOIN f USING (id)")
def nb_sql(spark, d):
    return predictions(spark, d)


@query("mcc_multiclass", f"WITH {NB}, q AS (SELECT f.y, yhat FROM p JOIN f USING (id)), t AS (SELECT y, count(*)::DOUBLE AS t FROM q GROUP BY y), h AS (SELECT yhat, count(*)::DOUBLE AS p FROM q GROUP BY yhat), m AS (SELECT sum(coalesce(t, 0) * coalesce(p, 0)) AS tp, sum(coalesce(t, 0) * coalesce(t, 0)) AS tt, sum(coalesce(p, 0) * coalesce(p, 0)) AS pp, sum(coalesce(t, 0)) AS s FROM t FULL JOIN h ON t.y = h.yhat), hit AS (SELECT (count(*) FILTER (y = yhat))::DOUBLE AS c FROM q) SELECT round(CASE WHEN (s * s - pp) * (s * s - tt) > 0 THEN (c * s - tp) / sqrt((s * s - pp) * (s * s - tt)) ELSE 0 END, 6) AS mcc FROM m, hit")
def mcc_multiclass(spark, d):
    return M.mcc_multiclass(predictions(spark, d))


# A prediction table that SQL can rebuild: order priority told from the customer's balance.
PRED = "pred AS (SELECT o_orderstatus AS task, (o_totalprice > 200000)::INT AS y, (c_acctbal > 4000)::INT AS yhat FROM orders JOIN customer ON o_custkey = c_custkey)"


def pred(spark, d) -> DataFrame:
    o, c = T.table(spark, d, "orders"), T.table(spark, d, "customer")
    return o.join(c, o["o_custkey"] == c["c_custkey"]).select(F.col("o_orderstatus").alias("task"), (F.col("o_totalprice") > 200000).cast("int").alias("y"), (F.col("c_acctbal") > 4000).cast("int").alias("yhat"))


CONF = f"{PRED}, conf AS (SELECT task, count(*) FILTER (y = 1 AND yhat = 1) AS tp, count(*) FILTER (y = 0 AND yhat = 0) AS tn, count(*) FILTER (y = 0 AND yhat = 1) AS fp, count(*) FILTER (y = 1 AND yhat = 0) AS fn FROM pred GROUP BY task)"
MCC = "CASE WHEN (tp + fp)::DOUBLE * (tp + fn) * (tn + fp) * (tn + fn) > 0 THEN (tp::DOUBLE * tn - fp::DOUBLE * fn) / sqrt((tp + fp)::DOUBLE * (tp + fn) * (tn + fp) * (tn + fn)) ELSE 0 END"


@query("confusion", f"WITH {CONF} SELECT * FROM conf")
def confusion(spark, d):
    return M.confusion(pred(spark, d), "task")


@query("mcc", f"WITH {CONF} SELECT task, round({MCC}, 6) AS mcc FROM conf")
def mcc(spark, d):
    return M.scores(pred(spark, d), "task").select("task", "mcc")


@query("accuracy", f"WITH {PRED} SELECT task, round(avg((y = yhat)::INT), 6) AS accuracy FROM pred GROUP BY task")
def accuracy(spark, d):
    return M.scores(pred(spark, d), "task").select("task", "accuracy")


@query("suite_mean_std", f"WITH {CONF} SELECT round(avg(m), 6) AS mean, round(stddev_samp(m), 6) AS std, count(*) AS n FROM (SELECT round({MCC}, 6) AS m FROM conf)")
def suite_mean_std(spark, d):
    return M.mean_std(M.scores(pred(spark, d), "task"), value="mcc")


@query("seed_stability", "SELECT l_returnflag, round(avg(l_discount), 6) AS mean, round(stddev_samp(l_discount), 6) AS std, count(*) AS n FROM lineitem GROUP BY 1")
def seed_stability(spark, d):
    return M.mean_std(T.table(spark, d, "lineitem"), "l_returnflag", value="l_discount")


@query("split_keyed", f"SELECT doc_id, {FOLD.format('quality', 'doc_id')} AS fold FROM labels")
def split_keyed(spark, d):
    return T.table(spark, d, "labels").select("doc_id", keyed_fold("quality", F.col("doc_id")).alias("fold"))


@query("class_balance", "SELECT quality, toxic, count(*) AS n FROM labels GROUP BY CUBE (quality, toxic)")
def class_balance(spark, d):
    return T.table(spark, d, "labels").cube("quality", "toxic").agg(F.count(F.lit(1)).alias("n"))


@query("majority_baseline", "WITH m AS (SELECT quality AS yhat FROM labels GROUP BY quality ORDER BY count(*) DESC, quality LIMIT 1) SELECT yhat, round(avg((quality = yhat)::INT), 6) AS accuracy, 0.0::DOUBLE AS mcc FROM labels, m GROUP BY yhat")
def majority_baseline(spark, d):
    rows = T.table(spark, d, "labels")
    top = rows.groupBy(F.col("quality").alias("yhat")).agg(F.count(F.lit(1)).alias("k")).orderBy(F.desc("k"), "yhat").limit(1).select("yhat")
    p = rows.select(F.col("quality").alias("y")).crossJoin(F.broadcast(top))
    return M.scores(p, "yhat").select("yhat", "accuracy", "mcc")


@query("token_profile", f"WITH {NB} SELECT id, token, n FROM c")
def token_profile(spark, d):
    return profiles(spark, d)[0]


@query("length_breakdown", f"WITH {NB}, b AS (SELECT p.id, yhat, f.y, CASE WHEN length(x.seq) <= 100 THEN 'to_100' WHEN length(x.seq) <= 500 THEN 'to_500' ELSE 'over_500' END AS bucket FROM p JOIN f USING (id) JOIN contigs x ON x.contig = p.id) SELECT bucket, count(*) AS n, round(avg((y = yhat)::INT), 6) AS accuracy FROM b GROUP BY bucket")
def length_breakdown(spark, d):
    """Accuracy of the language task by the length of the sequence."""
    n = F.length("seq")
    size = T.contigs(spark, d).select(F.col("contig").alias("id"), F.when(n <= 100, "to_100").when(n <= 500, "to_500").otherwise("over_500").alias("bucket"))
    return predictions(spark, d).join(size, "id").groupBy("bucket").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg((F.col("y") == F.col("yhat")).cast("int")), 6).alias("accuracy"))


def nearest_centroid(spark, d) -> DataFrame:
    """(label, yhat, n): vectors to the nearest class mean, squared distances to six places, ties to the smaller class."""
    v = T.table(spark, d, "embeddings").select("vec_id", "label", F.posexplode("embedding").alias("k", "x")).withColumn("x", F.col("x").cast("double"))
    mean = v.groupBy(F.col("label").alias("c"), "k").agg(F.avg("x").alias("m"))
    dist = v.join(F.broadcast(mean), "k").groupBy("vec_id", "label", "c").agg(F.round(F.sum((F.col("x") - F.col("m")) * (F.col("x") - F.col("m"))), 6).alias("d"))
    return dist.withColumn("nth", F.row_number().over(Window.partitionBy("vec_id").orderBy("d", "c"))).where("nth = 1").groupBy("label", F.col("c").alias("yhat")).agg(F.count(F.lit(1)).alias("n"))


query("zero_shot_centroid", "WITH v AS (SELECT vec_id, label, generate_subscripts(embedding, 1) AS k, unnest(embedding)::DOUBLE AS x FROM embeddings), m AS (SELECT label AS c, k, avg(x) AS m FROM v GROUP BY 1, 2), q AS (SELECT vec_id, label, c, round(sum((x - m) * (x - m)), 6) AS d FROM v JOIN m USING (k) GROUP BY 1, 2, 3) SELECT label, c AS yhat, count(*) AS n FROM (SELECT *, row_number() OVER (PARTITION BY vec_id ORDER BY d, c) AS nth FROM q) WHERE nth = 1 GROUP BY 1, 2")(nearest_centroid)


@query("zero_shot")
def zero_shot(spark, d):
    """k-means on unsupervised 3-mer profiles: purity over languages and silhouette."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.evaluation import ClusteringEvaluator
    from pyspark.ml.feature import CountVectorizer, Normalizer

    p = K.kmer_tokens(T.prefixes(spark, d), 3).where(F.size("tokens") > 0)
    x = Normalizer(inputCol="c", outputCol="features", p=1.0).transform(CountVectorizer(inputCol="tokens", outputCol="c", vocabSize=128).fit(p).transform(p))
    out = KMeans(k=4, seed=1).fit(x).transform(x)
    cells = out.groupBy("prediction", "lang").agg(F.count(F.lit(1)).alias("n"))
    purity = cells.groupBy("prediction").agg(F.max("n").alias("top"), F.sum("n").alias("all")).agg(F.round(F.sum("top") / F.sum("all"), 4).alias("purity"))
    return purity.crossJoin(rand_index(cells, "prediction", "lang")).withColumn("silhouette", F.lit(round(ClusteringEvaluator().evaluate(out), 4)))


def rand_index(cells: DataFrame, a: str, b: str) -> DataFrame:
    """(ari): the adjusted Rand index of two partitions from the counts n of their cells."""
    two = lambda c: F.col(c).cast("double") * (F.col(c) - 1) / 2
    sums = [cells.groupBy(x).agg(F.sum("n").alias("m")).agg(F.sum(two("m")).alias(f"s{i}")) for i, x in enumerate((a, b))]
    all_ = cells.agg(F.sum(two("n")).alias("both"), F.sum("n").alias("n")).withColumn("pairs", two("n"))
    x = all_.crossJoin(sums[0]).crossJoin(sums[1])
    expected, top = F.col("s0") * F.col("s1") / F.col("pairs"), (F.col("s0") + F.col("s1")) / 2
    return x.select(F.round(F.when(top > expected, (F.col("both") - expected) / (top - expected)).otherwise(1.0), 4).alias("ari"))


@query("proxy_classifier")
def proxy_classifier(spark, d):
    """(tokenizer, n, accuracy, mcc): logistic regression on normalised token counts with one feature budget for all tokenizers, tried on fold 0."""
    from functools import reduce

    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import HashingTF, Normalizer, StringIndexer

    p = T.prefixes(spark, d).where(F.length("seq") >= 30)
    cuts = {"kmer3": K.kmer_tokens(p, 3), "kmer6d": K.kmer_tokens(p, 6, 6), "motif_random": dictionary_tokens(spark, d, p)}
    out = []
    for name, rows in cuts.items():
        rows = rows.withColumn("fold", keyed_fold("nb", F.col("contig")))
        x = Normalizer(inputCol="c", outputCol="features", p=1.0).transform(HashingTF(inputCol="tokens", outputCol="c", numFeatures=4096).transform(rows))
        x = StringIndexer(inputCol="lang", outputCol="label", stringOrderType="alphabetAsc", handleInvalid="skip").fit(x).transform(x)
        said = LogisticRegression(maxIter=30, regParam=1e-4).fit(x.where("fold <> 0")).transform(x.where("fold = 0")).select(F.col("label").alias("y"), F.col("prediction").alias("yhat"))
        score = said.agg(F.count(F.lit(1)).alias("n"), F.round(F.avg((F.col("y") == F.col("yhat")).cast("int")), 6).alias("accuracy"))
        out.append(score.crossJoin(M.mcc_multiclass(said)).select(F.lit(name).alias("tokenizer"), "*"))
    return reduce(DataFrame.unionByName, out)


def dictionary_tokens(spark, d, rows: DataFrame) -> DataFrame:
    """(contig, lang, tokens array<string>) by the random pick."""
    t = G.greedy_tokenize(rows, words(spark, d), seed=7)
    return t.select("contig", "lang", F.transform("tokens", lambda x: x["token"]).alias("tokens"))


CLASSES = ("en", "de", "fr")


def class_attributions(spark, d) -> DataFrame:
    """(y, token, kind, mean_score, n): mean attribution of dictionary tokens toward each of three classes, over the test sequences of that class, from a margin of the class against the
    other two."""
    from functools import reduce

    three = T.prefixes(spark, d).where(F.col("lang").isin(*CLASSES))
    t = dictionary_tokens(spark, d, three).withColumn("fold", keyed_fold("nb", F.col("contig")))
    counts, out = M.profile(t.select(F.col("contig").alias("id"), F.explode("tokens").alias("token"))), []
    for c in CLASSES:
        rows = t.select(F.col("contig").alias("id"), F.when(F.col("lang") == c, "yes").otherwise("no").alias("y"), "fold")
        w, prior = M.nb_train(counts, rows.where("fold <> 0").select("id", "y"))
        own = rows.where("fold = 0 and y = 'yes'").select("id")
        a = M.attribution(counts.join(own, "id", "left_semi"), w, prior, "yes", "no")
        out.append(a.groupBy("token").agg(F.round(F.avg("score"), 6).alias("mean_score"), F.count(F.lit(1)).alias("n")).select(F.lit(c).alias("y"), "token", "mean_score", "n"))
    kind = F.when(F.length("token") > 3, "motif").when(F.length("token") == 3, "three").otherwise("one")
    return reduce(DataFrame.unionByName, out).withColumn("kind", kind)


@query("attribution_by_kind")
def attribution_by_kind(spark, d):
    """Motif tokens against 3-mers and single bases: mean, median and upper decile of the mean attributions of each class."""
    q = lambda p: F.round(F.percentile("mean_score", F.lit(p)), 6)
    return class_attributions(spark, d).groupBy("y", "kind").agg(F.count(F.lit(1)).alias("tokens"), F.round(F.avg("mean_score"), 6).alias("mean"), q(0.5).alias("median"), q(0.9).alias("p90"))


def top_motifs(spark, d, n: int = 200) -> DataFrame:
    nth = F.row_number().over(Window.partitionBy("y").orderBy(F.desc("mean_score"), "token"))
    return class_attributions(spark, d).where("kind = 'motif'").withColumn("nth", nth).where(F.col("nth") <= n)


@query("top_overlap_venn")
def top_overlap_venn(spark, d):
    """(cell, n): motif tokens among the 200 highest of one class only, of two, or of all three."""
    cells = top_motifs(spark, d).groupBy("token").agg(F.array_join(F.array_sort(F.collect_set("y")), "+").alias("cell"))
    return cells.groupBy("cell").agg(F.count(F.lit(1)).alias("n"))


@query("token_to_family")
def token_to_family(spark, d):
    """(family, en, de, fr): mean attribution of the 200 highest motif tokens of each class by the matrix family they come from; a token of several families counts in each."""
    c = V.consensus(V.matrices(T.table(spark, d, "embeddings")))
    both = c.select("family", F.col("seq").alias("token")).unionByName(c.select("family", B.revcomp("seq").alias("token"))).distinct()
    met = top_motifs(spark, d).join(F.broadcast(both), "token")
    return met.groupBy("family").pivot("y", list(CLASSES)).agg(F.round(F.avg("mean_score"), 6))


def attributions(spark, d) -> DataFrame:
    counts, rows = profiles(spark, d)
    two = rows.where("y in ('en', 'de')")
    w, prior = M.nb_train(counts, two.where("fold <> 0").select("id", "y"))
    test = two.where("fold = 0")
    return M.attribution(counts.join(test.select("id"), "id", "left_semi"), w, prior, "en", "de").join(test.select("id", "y"), "id")


@query("integrated_gradients")
def integrated_gradients(spark, d):
    """Completeness: the parts of a sequence sum to the rise of the output; gap is the largest difference."""
    a = attributions(spark, d)
    sig = lambda x: 1 / (1 + F.exp(-x))
    per = a.groupBy("id").agg(F.sum("score").alias("s"), F.max("rise").alias("rise"), F.max("z0").alias("z0"))
    return per.agg(F.count(F.lit(1)).alias("n"), F.round(F.max(F.abs(F.col("s") - (sig(F.col("z0") + F.col("rise")) - sig(F.col("z0"))))), 9).alias("gap"))


@query("token_attribution_mean")
def token_attribution_mean(spark, d):
    toward = F.when(F.col("y") == "en", F.col("score")).otherwise(-F.col("score"))
    return attributions(spark, d).groupBy("y", "token").agg(F.round(F.avg(toward), 6).alias("mean_score"), F.count(F.lit(1)).alias("n"))


@query("top200_tokens")
def top200_tokens(spark, d):
    m = token_attribution_mean(spark, d)
    return m.withColumn("nth", F.row_number().over(Window.partitionBy("y").orderBy(F.desc("mean_score"), "token"))).where("nth <= 200")


@query("motif_enrichment", f"WITH {NB}, k AS (SELECT y, token, sum(n) AS n FROM c JOIN f USING (id) GROUP BY 1, 2), a AS (SELECT y, sum(n) AS total FROM k GROUP BY y), g AS (SELECT token, sum(n) AS all_n FROM k GROUP BY token) SELECT y, token, round(ln(((k.n + 0.5) / (total - k.n + 0.5)) / ((all_n - k.n + 0.5) / ((SELECT sum(n) FROM k) - total - (all_n - k.n) + 0.5))), 6) AS log_odds FROM k JOIN a USING (y) JOIN g USING (token)")
def motif_enrichment(spark, d):
    counts, rows = profiles(spark, d)
    k = counts.join(rows, "id").groupBy("y", "token").agg(F.sum("n").alias("n"))
    by_y, by_t, all_ = k.groupBy("y").agg(F.sum("n").alias("total")), k.groupBy("token").agg(F.sum("n").alias("all_n")), k.agg(F.sum("n").alias("s"))
    x = k.join(F.broadcast(by_y), "y").join(by_t, "token").crossJoin(F.broadcast(all_))
    rest = F.col("all_n") - F.col("n")
    odds = ((F.col("n") + 0.5) / (F.col("total") - F.col("n") + 0.5)) / ((rest + 0.5) / (F.col("s") - F.col("total") - rest + 0.5))
    return x.select("y", "token", F.round(F.ln(odds), 6).alias("log_odds"))
