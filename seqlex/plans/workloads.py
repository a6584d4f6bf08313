"""The experiments on the given tables: every tokenizer on stand-in tasks, one row for each (suite, task, tokenizer)."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seqlex.functions.bases import keyed_fold, page_text, to_bases
from seqlex.operators import bayes as NB
from seqlex.operators import bpe as P
from seqlex.operators import greedy as G
from seqlex.operators import intervals as R
from seqlex.operators import kmer as K
from seqlex.operators import models as M
from seqlex.operators import segments as SEG
from seqlex.sources import tables as T

from . import evaluation as E
from .intervals import balanced, elements, shuffled
from .registry import query
from .sequence import words
from .vocabularies import corpora

#: BPE is trained to this size once a corpus; the smaller vocabularies are its first merges.
LARGEST = 4096


def merges_of(spark: SparkSession, d: str, corpus: str, learnt: dict) -> list[P.Merge]:
    """learnt keeps the merges of the corpora trained so far."""
    if corpus not in learnt:
        learnt[corpus] = P.train_bpe(corpora(spark, d)[corpus], LARGEST, 20)
    return learnt[corpus]


def tokenised(spark: SparkSession, d: str, rows: DataFrame, name: str, learnt: dict | None = None) -> DataFrame:
    """(contig, tokens array<string>) of rows (contig, seq) by the tokenizer called name."""
    if name.startswith("motif_"):
        t = G.greedy_tokenize(rows, words(spark, d), pick=name.split("_")[1], seed=int(name.split("_")[2]) if name.count("_") > 1 else 7)
        return t.select("contig", F.transform("tokens", lambda x: x["token"]).alias("tokens"))
    if name.startswith("bpe_"):
        _, corpus, size = name.split("_")
        return P.apply_bpe(rows, merges_of(spark, d, corpus, {} if learnt is None else learnt)[: int(size) - P.SPECIAL_AND_ALPHABET])
    return K.kmer_tokens(rows, *KMERS[name]).select("contig", "tokens")


KMERS = {"kmer3": (3, 1), "kmer6": (6, 1), "kmer6d": (6, 6)}


def cutter(spark: SparkSession, d: str, name: str):
    """The tokenizer called name, which is no BPE, for bayes: the tokens of tokenised() as numbers."""
    if name.startswith("motif_"):
        return G.Cutter(words(spark, d), pick=name.split("_")[1], seed=int(name.split("_")[2]) if name.count("_") > 1 else 7)
    return K.Cutter(*KMERS[name])


def cutters(spark: SparkSession, d: str, tokenizers: tuple[str, ...], learnt: dict):
    """(names of tokenizers, their cutter): vocabularies of one corpus are cut together."""
    groups: dict[str, list[str]] = {}
    for name in tokenizers:
        groups.setdefault(name.rpartition("_")[0] if name.startswith("bpe_") else name, []).append(name)
    for group, names in groups.items():
        if group.startswith("bpe_"):
            names = sorted(names, key=lambda x: int(x.rpartition("_")[2]))
            yield names, P.Cutter(merges_of(spark, d, group.removeprefix("bpe_"), learnt), [int(x.rpartition("_")[2]) for x in names])
        else:
            yield names, cutter(spark, d, group)


def evaluate(spark: SparkSession, d: str, data: DataFrame, tokenizers: tuple[str, ...], suite: str) -> DataFrame:
    """data: (contig, seq, marks array<(task, label 0/1, fold)>), the fold null unless the task sets it; a mark without a label takes no part. Naive Bayes on token counts with the same
    folds for every tokenizer; the MCC of the held-out fold 0. data is read once, and stored, where there are several tokenizers; nothing of it is shuffled."""
    hashed = lambda m: keyed_fold("w", F.concat_ws("|", m["task"], F.col("contig").cast("string"), m["label"].cast("string")))
    mark = lambda m: F.struct(
        F.xxhash64(m["task"], F.col("contig"), F.col("seq"), m["label"]).alias("id"),
        F.concat_ws("|", m["task"], m["label"].cast("string")).alias("y"),
        (F.coalesce(m["fold"].cast("long"), hashed(m)) == 0).alias("test"),
    )
    labelled = F.filter("marks", lambda m: m["task"].isNotNull() & m["label"].isNotNull())
    rows = data.where("seq IS NOT NULL").select(F.xxhash64("seq").alias("key"), "seq", F.transform(labelled, mark).alias("marks"))
    rows = T.stored(rows) if len(tokenizers) > 1 else rows
    out, learnt = [], {}
    for names, cut in cutters(spark, d, tokenizers, learnt):
        for name, tried in zip(names, NB.tried_each(rows, cut), strict=True):
            scored = M.scores(tried.select("task", "y", "yhat"), "task")
            out.append(scored.select(F.lit(suite).alias("suite"), "task", F.lit(name).alias("tokenizer"), "mcc", "accuracy"))
    return reduce(DataFrame.unionByName, out)


def marks(named) -> F.Column:
    """An array of marks of (task, label) or (task, label, fold); a null task is none."""
    one = lambda task, label, fold=F.lit(None): F.struct((F.lit(task) if isinstance(task, str) else task).alias("task"), label.cast("int").alias("label"), fold.cast("int").alias("fold"))
    return F.array(*[one(*x) for x in named]).alias("marks")


def by_length(rows: DataFrame, lengths, named) -> DataFrame:
    """(contig, seq, marks) of rows (contig, seq) in one scan: the first n bases of each length n, with the marks named(n)."""
    return rows.select("contig", F.inline(F.array(*[F.struct(F.substring("seq", 1, n).alias("seq"), marks(named(n))) for n in lengths])))


def language_tasks(spark, d, *lengths: int, langs: tuple[str, ...] = ("en", "de", "fr")) -> DataFrame:
    p = T.prefixes(spark, d, max(lengths)).where(F.length("seq") >= 30)
    return by_length(p, lengths, lambda n: [(f"lang_{x}_{n}", F.col("lang") == x) for x in langs])


def labelled(spark, d, length: int) -> DataFrame:
    """(contig, seq, lang, quality, toxic): only the first bases of a document meet the labels."""
    return T.prefixes(spark, d, length).where(F.length("seq") >= 30).join(T.table(spark, d, "labels").withColumnRenamed("doc_id", "contig"), "contig")


def label_tasks(spark, d, *lengths: int, names: tuple[str, ...] = ("quality", "toxic")) -> DataFrame:
    return by_length(labelled(spark, d, max(lengths)), lengths, lambda n: [(f"{x}_{n}", F.col(x)) for x in names])


def together(*sets: DataFrame) -> DataFrame:
    """Sets of rows (contig, seq, marks) as one, a row for each contig and its first bases, so that these are cut once for the marks of all sets."""
    return reduce(DataFrame.unionByName, sets).groupBy("contig", "seq").agg(F.flatten(F.collect_list("marks")).alias("marks"))


@query("w08_length_effect")
def w08(spark, d):
    return reduce(DataFrame.unionByName, [evaluate(spark, d, language_tasks(spark, d, n), ("kmer3", "motif_random"), f"S1_{n}") for n in (70, 300, 1000)])


def texts(spark, d, name: str, key: str, text, length: int, **more) -> DataFrame:
    """(contig, seq, more): first bases of another table's texts."""
    rows = T.table(spark, d, name).select(F.col(key).alias("contig"), F.explode(F.array(to_bases(text))).alias("seq"), *(c.alias(n) for n, c in more.items()))
    return rows.select("contig", F.substring("seq", 1, length).alias("seq"), *more).where(F.length("seq") >= 30)


def versus(task: str, yes: DataFrame, no: DataFrame) -> DataFrame:
    """One task from two sets; the negatives' keys are made negative, so that keys of two tables don't meet."""
    return yes.select("contig", "seq", marks([(task, F.lit(1))])).unionByName(no.select((-F.col("contig") - 1).alias("contig"), "seq", marks([(task, F.lit(0))])))


def one_of(rows: DataFrame, column: str, *values: str) -> DataFrame:
    """A task for each value: rows with it against the others."""
    return rows.where(F.col(column).isNotNull()).select("contig", "seq", marks([(f"{column}_{x}", F.col(column) == x) for x in values]))


@query("w02_lengths")
def w02(spark, d):
    data = label_tasks(spark, d, 70, 100, 300, 500, 1000, names=("quality",))
    return evaluate(spark, d, data.unionByName(language_tasks(spark, d, 100)), ("kmer6d", "motif_random"), "S1")


def turns(spark, d, length: int = 300) -> DataFrame:
    """(contig, seq, role): a turn's key is its conversation and its number (under 1,000 turns by the bound of the key's step)."""
    rows = T.table(spark, d, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("contig"), F.explode(F.array(to_bases("text"))).alias("seq"), "role")
    return rows.select("contig", F.substring("seq", 1, length).alias("seq"), "role").where(F.length("seq") >= 30)


def human_tasks(spark, d) -> DataFrame:
    """Four languages and the toxic label at three lengths, and three roles: 18 tasks."""
    lengths = (300, 600, 1000)
    sets = [language_tasks(spark, d, *lengths, langs=("en", "de", "fr", "es")), label_tasks(spark, d, *lengths, names=("toxic",))]
    return reduce(DataFrame.unionByName, [*sets, one_of(turns(spark, d), "role", "user", "assistant", "system")])


@query("w03_human_tasks")
def w03(spark, d):
    return evaluate(spark, d, human_tasks(spark, d), ("kmer6d", "motif_random"), "S2")


def element_sets(spark, d) -> DataFrame:
    """(category, contig, seq, label) of balanced(), stored: its scan is dear. The key is of contig and start."""
    return T.stored(balanced(spark, d).select("category", (F.col("contig") * 1_000_000 + F.col("start")).alias("contig"), "seq", "label"))


def regulatory_tasks(spark, d, sets: DataFrame | None = None) -> DataFrame:
    """Elements against tiles, planted passages against their shuffled bases, elements of each language and toxic ones against tiles: seven sets of three tasks."""
    passages = texts(spark, d, "benchmark", "item_id", "text", 100)
    lang, toxic = F.split_part("category", F.lit("_"), F.lit(1)), F.split_part("category", F.lit("_"), F.lit(2))
    own = [("element", F.col("label")), (F.when(lang.isin("en", "de", "fr", "es"), F.concat(F.lit("element_"), lang)), F.col("label")), (F.when(toxic == "1", "element_toxic"), F.col("label"))]
    b = (element_sets(spark, d) if sets is None else sets).select("contig", "seq", marks(own))
    return b.unionByName(versus("passage", passages, shuffled(passages)))


@query("w04_regulatory_tasks")
def w04(spark, d):
    return evaluate(spark, d, regulatory_tasks(spark, d), ("kmer6d", "motif_random"), "S3")


def mixed_tasks(spark, d) -> DataFrame:
    """Texts of different tables, roles and languages against each other, and the language that a page declares. Of a page only its text is read, not its tags."""
    docs = T.prefixes(spark, d).where(F.length("seq") >= 30)
    said, one, none = turns(spark, d), F.lit(1), F.lit(0)
    pages = texts(spark, d, "pages", "page_id", page_text("html"), 300, page_lang=F.regexp_extract("html", '<html lang="([a-z]+)', 1))
    only = lambda wanted, name: F.when(wanted, name)
    yes = [
        pages.select("contig", "seq", marks([*((f"page_lang_{x}", F.col("page_lang") == x) for x in ("en", "de", "fr", "es")), ("page_document", one)])),
        texts(spark, d, "benchmark", "item_id", "text", 300).select("contig", "seq", marks([("passage_document", one)])),
        said.select("contig", "seq", marks([(only(F.col("role") == "user", "user_assistant"), one), ("turn_document", one)])),
        docs.where("lang = 'es'").select("contig", "seq", marks([("es_de", one)])),
    ]
    # The other side of each task, by negative keys as in versus(): documents are read once for four tasks.
    no = [
        docs.select("contig", "seq", marks([*((f"{x}_document", none) for x in ("page", "passage", "turn")), (only(F.col("lang") == "de", "es_de"), none)])),
        said.where("role = 'assistant'").select("contig", "seq", marks([("user_assistant", none)])),
    ]
    return reduce(DataFrame.unionByName, [*yes, *(x.withColumn("contig", -F.col("contig") - 1) for x in no)])


@query("w05_mixed_tasks")
def w05(spark, d):
    return evaluate(spark, d, mixed_tasks(spark, d), ("kmer6d", "motif_random"), "S4")


def element_tasks(spark, d, sets: DataFrame | None = None) -> DataFrame:
    """Each category of elements against its own sampled tiles."""
    return (element_sets(spark, d) if sets is None else sets).select("contig", "seq", marks([(F.col("category"), F.col("label"))]))


@query("w06_balanced_elements")
def w06(spark, d):
    return evaluate(spark, d, element_tasks(spark, d), ("kmer6d", "motif_random"), "S5")


def first_suite(spark, d) -> DataFrame:
    """The quality label at five lengths, three languages at 100 bases, the toxic label at 300."""
    named = lambda n: [(f"quality_{n}", F.col("quality")), *([(f"toxic_{n}", F.col("toxic"))] if n == 300 else [])]
    return by_length(labelled(spark, d, 1000), (70, 100, 300, 500, 1000), named).unionByName(language_tasks(spark, d, 100))


SUITES = {"S1": first_suite, "S2": human_tasks, "S3": regulatory_tasks, "S4": mixed_tasks, "S5": element_tasks}


def on_suites(spark, d, tokenizers: tuple[str, ...]) -> DataFrame:
    """(suite, task, tokenizer, mcc, accuracy) of the tasks of all five suites."""
    sets, data = element_sets(spark, d), []
    for suite, tasks in SUITES.items():
        own = tasks(spark, d, sets) if suite in ("S3", "S5") else tasks(spark, d)
        prefix = F.lit(f"{suite}/")
        named = F.transform("marks", lambda m: F.struct(F.concat(prefix, m["task"]).alias("task"), m["label"].alias("label"), m["fold"].alias("fold")))  # noqa: B023
        data.append(own.select("contig", "seq", named.alias("marks")))
    scored = evaluate(spark, d, reduce(DataFrame.unionByName, data), tokenizers, "")
    name = F.split("task", "/", 2)
    return scored.select(name[0].alias("suite"), name[1].alias("task"), "tokenizer", "mcc", "accuracy")


def by_suite(scored: DataFrame) -> DataFrame:
    """(suite, tokenizer, mean, std, n, place): over a suite's tasks, of the accuracy in S3 and of the MCC elsewhere. Place 1 is the best tokenizer of a suite, 2 the second best;
    equal means share a place."""
    value = scored.withColumn("value", F.when(F.col("suite") == "S3", F.col("accuracy")).otherwise(F.col("mcc")))
    return M.places(M.mean_std(value, "suite", "tokenizer"), "suite")


@query("suite_marks")
def suite_marks(spark, d):
    """All five suites: mean, deviation and place of disjoint 6-mers and of the dictionary."""
    return by_suite(on_suites(spark, d, ("kmer6d", "motif_random")))


#: Tokenizers of the experiments whose tasks are languages, and, where said so, labels. `on_suites` takes any of these over all suites.
COMPARED = {
    "w01_baselines": (True, ("kmer3", "kmer6", "kmer6d", "bpe_foreign_4096", "bpe_whole_4096")),
    "w09_vocabulary_size": (False, ("bpe_whole_1024", "bpe_whole_2048", "bpe_whole_4096")),
    "w10_domains": (False, tuple(f"bpe_{c}_{n}" for c in ("whole", "motif", "element") for n in (1024, 2048, 4096))),
    "w11_dictionary_vs_bpe": (True, ("motif_random", "bpe_whole_4096", "bpe_motif_4096", "bpe_element_4096")),
    "w12_pick_rules": (False, ("motif_random", "motif_longest", "motif_shortest")),
}
for _name, (_labels, _tokenizers) in COMPARED.items():

    @query(_name)
    def _compared(spark, d, labels=_labels, tokenizers=_tokenizers):
        data = language_tasks(spark, d, 300)
        return evaluate(spark, d, together(data, label_tasks(spark, d, 300)) if labels else data, tokenizers, "S1")


@query("w14_seeds")
def w14(spark, d):
    runs = evaluate(spark, d, language_tasks(spark, d, 300), ("motif_random_1", "motif_random_2", "motif_random_3", "motif_random_4"), "S1")
    return M.mean_std(runs, "suite", "task", value="mcc")


@query("w07_zero_shot")
def w07(spark, d):
    """Clusters of token profiles against languages, and the share of vectors nearest to their own class's mean."""
    near = E.nearest_centroid(spark, d).agg(F.round(F.sum(F.when(F.col("label") == F.col("yhat"), F.col("n")).otherwise(0)) / F.sum("n"), 4).alias("vector_accuracy"))
    return E.zero_shot(spark, d).crossJoin(near)


@query("w13_other_species")
def w13(spark, d):
    """Labels learnt on one language and tried on two others."""
    p, fold = labelled(spark, d, 300), lambda x: F.when(F.col("lang") == x, 0).otherwise(1)
    to = lambda x: p.where(F.col("lang").isin("en", x)).select("contig", "seq", marks([(f"{y}_300_{x}", F.col(y), fold(x)) for y in ("quality", "toxic")]))
    return evaluate(spark, d, to("de").unionByName(to("es")), ("kmer6d", "motif_random"), "S1_other")


@query("w15_interpretability")
def w15(spark, d):
    """Tokens among the 200 highest of both classes, of one only, and how many of them are motifs."""
    top, motifs = E.top200_tokens(spark, d), spark.createDataFrame([(w,) for w in words(spark, d)], "token string").withColumn("motif", F.lit(1))
    per = top.groupBy("token").agg(F.count_distinct("y").alias("classes")).join(motifs, "token", "left")
    return per.groupBy("classes").agg(F.count(F.lit(1)).alias("tokens"), F.count("motif").alias("motifs"))


@query("w17_region_coverage")
def w17(spark, d):
    """Share of all bases under motif hits and under elements."""
    total = T.contigs(spark, d).agg(F.sum(F.length("seq")).alias("total"))
    regions = {"motif": G.scan_motifs(T.contigs(spark, d), words(spark, d)), "element": elements(spark, d)}
    rows = [R.covered(df.select("contig", "start", "end")).select(F.lit(name).alias("region"), "regions", "bases") for name, df in regions.items()]
    return reduce(DataFrame.unionByName, rows).crossJoin(F.broadcast(total)).select("region", "regions", "bases", F.round(F.col("bases") / F.col("total"), 6).alias("ratio"))


@query("w18_training_corpora")
def w18(spark, d):
    """For each tokenizer on whole documents: segments of 512 tokens, those over half N, tokens, bases a token, and passes over the corpus in the budget."""
    total, out = T.contigs(spark, d).agg(F.sum(F.length("seq")).alias("corpus")), []
    for name in ("kmer3", "kmer6d", "motif_random", "bpe_whole_4096"):
        cut = SEG.pack_segments(tokenised(spark, d, T.contigs(spark, d).select("contig", "seq"), name))
        share = cut.select("n_tokens", SEG.n_share(F.col("tokens")).alias("n_share"))
        out.append(share.agg(F.count(F.lit(1)).alias("segments"), F.count_if(F.col("n_share") > 0.5).alias("discarded"), F.sum("n_tokens").alias("tokens")).withColumn("tokenizer", F.lit(name)))
    grid = reduce(DataFrame.unionByName, out).crossJoin(F.broadcast(total))
    return grid.select("tokenizer", "segments", "discarded", "tokens", F.round(F.col("corpus") / F.col("tokens"), 6).alias("bases_per_token"), F.round(96 * 512 * 200_000 / F.col("tokens"), 2).alias("epochs"))
