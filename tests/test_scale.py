"""Cuts in the scan of the documents against joins of intervals, and naive Bayes in the workers against its relational form: no sequence or token is shuffled."""

from collections import Counter

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from seqlex.functions import bases as B
from seqlex.operators import bayes, bpe
from seqlex.operators import greedy as G
from seqlex.operators import intervals as R
from seqlex.operators import kmer as K
from seqlex.operators import models as M
from seqlex.plans import intervals, registry, vocabularies, workloads
from seqlex.plans.sequence import words
from seqlex.sources import tables as T

registry.load()
SF = "/root/testdata/sf0.001"


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_bases_in_the_workers(spark):
    texts = ["", " \t\r\n", "Ab cé\U0001f600\nxyz 1\r\n\nq", " n z", "a" * 40]
    rows = spark.createDataFrame([(t,) for t in texts], "t string").select("t", B.to_bases("t").alias("b"), B.first_bases("t", 5).alias("f")).collect()
    assert all(B.bases(r["t"]) == r["b"] and r["f"] == r["b"][:5] for r in rows)
    assert B.bases("a b\nc", keep="\n") == "TT\nC"


def test_elements_are_cut_in_the_scan(spark):
    """Lines, as SQL finds them, with their bases; neither a window nor the contigs are shuffled for it."""
    con = duckdb.connect()
    for t in ("documents", "labels"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    want = con.execute(registry.ORACLE["region_extract"]).fetchall()
    rows = intervals.element_rows(spark, SF)
    assert Counter(map(tuple, rows.collect())) == Counter(want)
    assert "Window" not in plan(rows)
    units = vocabularies.corpora(spark, SF)["element"]
    assert "Window" not in plan(units) and plan(units).count("Join") == 1
    assert {r["unit"]: r["n"] for r in units.collect()} == Counter(r[4] for r in want)


def test_lines_of_odd_texts(spark):
    text = "ab c\n" + "x" * 60 + "\n\n" + " " * 80 + "\n" + "y z" * 30 + "\n"
    df = spark.createDataFrame([(1, text, "en"), (2, None, "de"), (3, "", None)], "contig long, text string, lang string")
    got = {r["contig"]: [(s["start"], s["end"], s["seq"]) for s in r["spans"]] for r in R.line_spans(df, 50, 7).collect()}
    assert got == {1: [(63, 123, B.bases("yz" * 4)[:7])], 2: [], 3: []}


@pytest.mark.parametrize("n", [1, 1 << 20])
def test_covered_stretches(spark, monkeypatch, n):
    monkeypatch.setattr(G, "SCANNED", n)
    c = T.contigs(spark, SF).limit(40).unionByName(spark.createDataFrame([(-1, "", "x"), (-2, "ACG", "x")], "contig long, seq string, lang string")).cache()
    w = words(spark, SF)
    want = Counter(r["seq"] for r in R.extract(R.merge(G.scan_motifs(c, w)), c).collect())
    got = Counter()
    for r in G.covered_seqs(c, w).collect():
        got[r["seq"]] += r["n"]
    assert got == want and "Exchange" not in plan(G.covered_seqs(T.contigs(spark, SF).select("seq"), w)).split("MapInArrow")[0]
    c.unpersist()


def test_units_are_cut_once(spark):
    """Training reads the stored units: one scan of the corpus, not one for its size and one for its rows."""
    scans = spark.sparkContext.accumulator(0)

    def seen(batches):
        for b in batches:
            scans.add(b.num_rows)
            yield b

    u = bpe.units(T.table(spark, SF, "documents").limit(30).select("text").coalesce(1).mapInArrow(seen, "text string"))
    assert bpe.train_bpe(u, 40, 20) == bpe.train_bpe(u, 40, 20, symbols=10)
    assert scans.value == 60


@pytest.fixture(scope="module")
def odd(spark):
    """Sequences with their hash as key, among them an empty one, some without a word, equal ones and all N."""
    c = T.prefixes(spark, SF, 400).limit(30).select("seq").unionByName(spark.createDataFrame([("",), ("A",), ("ACN",), ("N" * 40,), ("ACGTN" * 9,)], "seq string"))
    return c.distinct().select(F.xxhash64("seq").alias("contig"), "seq").cache()


@pytest.mark.parametrize("name", ["kmer3", "kmer6", "kmer6d", "motif_random", "motif_random_3", "motif_longest", "motif_shortest", "bpe_whole_1024"])
def test_numbered_tokens(spark, odd, name):
    """A number for each token of the tokenizer, another for each other one, in the same places."""
    learnt = {"whole": bpe.train_bpe(bpe.units(T.table(spark, SF, "documents").limit(20)), 200, 20)}
    rows, cut = odd.collect(), workloads.cutter(spark, SF, name, learnt)
    ids, of = cut(np.array([r["contig"] for r in rows]), [r["seq"] for r in rows])
    want, named = {r["contig"]: r["tokens"] for r in workloads.tokenised(spark, SF, odd, name, learnt).collect()}, {}
    for k, r in enumerate(rows):
        own = ids[of == k].tolist()
        assert len(own) == len(want[r["contig"]])
        for i, t in zip(own, want[r["contig"]], strict=True):
            assert named.setdefault(t, i) == i and 0 <= i < cut.size
    assert len(set(named.values())) == len(named)


@pytest.mark.parametrize("size", [1, 1 << 20])
def test_bayes_in_the_workers(spark, odd, monkeypatch, size):
    """Against the relational form on (task, label) classes, each row scored against its own task's; without an exchange before the counts."""
    monkeypatch.setattr(bayes, "CUT", size)
    texts = [(r["contig"], r["seq"]) for r in odd.collect()] + [(r["contig"], r["seq"]) for r in odd.limit(5).collect()]
    marks = [[(1000 * t + k, f"{task}|{(k * (t + 3) // 7) % 2}", (k + t) % 4 == 0) for t, task in enumerate(("a", "b|c", "one"))] for k in range(len(texts))]
    marks = [[m if m[1][:3] != "one" else (m[0], "one|1", m[2]) for m in x] + ([(9000 + k, "none|0", True)] if k == 4 else []) for k, x in enumerate(marks)]
    rows = spark.createDataFrame([(*x, m) for x, m in zip(texts, marks, strict=True)], "key long, seq string, marks array<struct<id:long,y:string,test:boolean>>").repartition(3)
    got = {(r["id"], r["task"], r["y"], r["yhat"]) for r in bayes.tried(rows, K.Cutter(3, 3)).collect()}
    flat = rows.select(F.inline("marks"), F.col("seq"), F.col("id").alias("contig"))
    counts = M.profile(K.kmer_tokens(flat, 3, 3).select("id", F.explode("tokens").alias("token")))
    w, prior = M.nb_train(counts, flat.where("not test").select("id", "y"))
    weight, first = {(r["y"], r["token"]): r["w"] for r in w.collect()}, {r["y"]: r["prior"] for r in prior.collect()}
    told: dict = {}
    for r in counts.collect():
        told.setdefault(r["id"], []).append((r["token"], r["n"]))
    want = set()
    for r in flat.where("test").collect():
        task, _, y = r["y"].rpartition("|")
        own = [c for c in first if c.rpartition("|")[0] == task]
        if own:
            best = max(own, key=lambda c: (round(first[c] + sum(n * weight.get((c, t), 0.0) for t, n in told.get(r["id"], [])), 9), c))
            want.add((r["id"], task, int(y), int(best[-1])))
    assert got == want and len(got) > 20 and "Exchange" not in plan(bayes.parts(odd.select(F.col("contig").alias("key"), "seq", F.array().cast("array<struct<id:long,y:string,test:boolean>>").alias("marks")), K.Cutter(3, 3))).split("InMemory")[0]
    assert bayes.tried(rows.limit(0), K.Cutter(3, 3)).count() == 0


def test_tasks_share_a_scan(spark):
    """Languages at three lengths, and a label, each read the documents once; a mark without a label takes no part, and the mark's own fold holds."""
    assert plan(workloads.language_tasks(spark, SF, 300, 600, 1000)).count("FileScan") == 1
    assert plan(workloads.human_tasks(spark, SF)).count("documents.parquet") == 2
    rows = spark.createDataFrame([(k, "ACGT" * 10 if k % 2 else "GGTA" * 10, [("t", k % 2, k // 8), ("u", None, 0)]) for k in range(16)], "contig long, seq string, marks array<struct<task:string,label:int,fold:int>>")
    got = workloads.evaluate(spark, SF, rows, ("kmer3",), "X").collect()
    assert [tuple(r) for r in got] == [("X", "t", "kmer3", 1.0, 1.0)]


@pytest.mark.parametrize("name", ["balanced_sets", "interval_complement"])
def test_sets_against_sql(spark, name):
    con = duckdb.connect()
    for t in ("documents", "labels"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    got = registry.QUERIES[name](spark, SF)
    assert Counter(map(tuple, got.collect())) == Counter(con.execute(registry.ORACLE[name]).fetchall())


def test_suites_share_scans(spark):
    """Whole tables are read once for each side of their tasks, whatever the number of tasks, and the elements once for the balanced sets."""
    assert plan(workloads.mixed_tasks(spark, SF)).count("pages.parquet") == 1
    assert plan(workloads.first_suite(spark, SF)).count("documents.parquet") == 2
    tasks = {m["task"] for r in workloads.mixed_tasks(spark, SF).select("marks").distinct().collect() for m in r["marks"]}
    assert tasks - {None} == {*(f"page_lang_{x}" for x in ("en", "de", "fr", "es")), "page_document", "passage_document", "user_assistant", "turn_document", "es_de"}
    assert "labels.parquet" not in plan(workloads.element_tasks(spark, SF, workloads.element_sets(spark, SF)))


@pytest.mark.parametrize("weights", [False, True])
def test_linked_merges_tell_all_changes(monkeypatch, weights):
    """A merge looks at the places of the rarer of its symbols only, and the changes that it tells add up to a recount, runs of one symbol included."""
    rng = np.random.default_rng(5)
    units = ["".join(rng.choice(list("AAAACG"), 300)) + "GT" * (k % 2) for k in range(20)] + ["A" * 9, "AC" * 5, "T"]
    chain = bpe.Chain([bpe.codes(u) for u in units], np.arange(len(units)) + 1 if weights else np.ones(len(units), np.int64))
    counts, looked, seen = Counter(dict(zip(*(x.tolist() for x in chain.pairs()), strict=True))), bpe.Chain._places, []
    monkeypatch.setattr(bpe.Chain, "_places", lambda self, k: seen.append(len(self.where.get(k, ()))) or looked(self, k))
    chain.merge(2, 3, 5)
    assert seen == [11]  # the T, not the hundreds of G
    chain = bpe.Chain([bpe.codes(u) for u in units], np.arange(len(units)) + 1 if weights else np.ones(len(units), np.int64))
    for a, b, c in ((0, 0, 5), (0, 1, 6), (5, 5, 7), (1, 6, 8), (5, 6, 9), (6, 5, 10), (7, 0, 11), (9, 9, 12)):
        for k, n in zip(*(x.tolist() for x in bpe.changes(a, b, c, [chain.merge(a, b, c)])), strict=True):
            counts[k] += n
        symbols, ends = chain.symbols()
        fresh = Counter()
        for k, (x, y) in enumerate(zip([0, *ends[:-1].tolist()], ends.tolist(), strict=True)):
            for p in zip(symbols[x:y].tolist(), symbols[x + 1 : y].tolist(), strict=False):
                fresh[p[0] << 32 | p[1]] += k + 1 if weights else 1
        assert +counts == fresh and min(counts.values()) >= 0


def test_ranked_pairs_wait_under_the_floor():
    """Rare pairs stay out of the heap until the frequent ones are used up; a square array and one by key give the same."""
    out = []
    for size in (50, 20_000):
        ranked = bpe.Ranked(size, bpe.Names(), 2)
        for k in range(5, 45):
            ranked.names.add("A" * (k - 3))
        n = np.array([900, 800, 500, 30, 2, 1], np.int64)
        ranked.change(np.array([x << 32 | x + 1 for x in (0, 5, 9, 20, 30, 40)], np.int64), n)
        assert not ranked.heap and ranked.lower() and sorted(x[0] for x in ranked.heap) == [-900, -800, -500]
        ranked.change(np.array([9 << 32 | 10, 20 << 32 | 21, 20 << 32 | 21], np.int64), np.array([-499, 400, 400], np.int64))
        assert (ranked.get(9 << 32 | 10), ranked.get(20 << 32 | 21), type(ranked.n)) == (1, 830, np.ndarray if size == 50 else dict)
        while ranked.lower():
            pass
        out.append(sorted(ranked.heap))
        assert ranked.floor == 2 and min(-x[0] for x in out[-1]) == 2
    assert out[0] == out[1]


def test_corpora_are_cut_in_the_workers(spark):
    """Bases of whole lines and motif regions are made in the workers, not by expressions that the plan repeats; the units stay."""
    found = vocabularies.corpora(spark, SF)
    assert not any("regexp" in plan(found[x]) or "translate" in plan(found[x]) for x in ("whole", "motif", "foreign"))
    docs = T.table(spark, SF, "documents").limit(60).unionByName(spark.createDataFrame([("Éa\r\n\nb \U0001f600c\n",), (None,)], "text string"), allowMissingColumns=True)
    line = docs.select(F.explode(F.split("text", "\n")).alias("line")).select(B.to_bases("line").alias("unit")).where("unit <> ''")
    assert Counter({r["unit"]: r["n"] for r in bpe.units(docs).collect()}) == Counter(r["unit"] for r in line.collect())
    w, got = words(spark, SF), [Counter(), Counter()]
    for k, df in enumerate((G.covered_seqs(docs.select(B.to_bases("text").alias("seq")), w), G.covered_seqs(docs, w, "text"))):
        for r in df.collect():
            got[k][r["seq"]] += r["n"]
    assert got[0] == got[1] and got[0]


def test_first_bases_are_dealt_out_after_the_cut(spark):
    """No whole text is shuffled where a scan has fewer tasks than there are cores."""
    p = plan(T.prefixes(spark, SF, 300))
    assert p.index("Exchange") < p.index("Generate")


def test_chains_keep_two_bytes_a_base():
    """A chain made of symbols of several bases goes on as one that began with the bases, weights and a unit without bases included; a base takes two bytes of it."""
    units, weights = ["ACACGT", "", "GTACAC", "TTTT"], np.array([1, 1, 1, 3])
    whole = bpe.Chain([bpe.codes(u) for u in units], weights)
    first, then = ((0, 1, 5), (3, 3, 6)), ((5, 5, 7), (2, 3, 8), (6, 6, 9))
    for m in first:
        whole.merge(*m)
    symbols, ends = whole.symbols()
    flat = np.concatenate([[-1], *([*symbols[a:b], -1] for a, b in zip([0, *ends[:-1]], ends, strict=True))]).astype(np.int16)
    later = bpe.Chain(flat, weights, [1] * 5 + [2, 2])
    assert whole.symbol.dtype == later.symbol.dtype == np.int16 and len(whole.symbol) == len(later.symbol) == sum(map(len, units)) + 5
    for m in then:
        x, y = whole.merge(*m), later.merge(*m)
        assert all(np.array_equal(p, q) for p, q in zip(x, y, strict=True))
    assert all(np.array_equal(p, q) for p, q in zip(whole.symbols(), later.symbols(), strict=True))
    assert x[2] == 3 and later.symbols()[0].tolist() == [7, 8, 8, 7, 9]


def test_small_corpora_are_trained_by_few_tasks(spark, monkeypatch):
    """A task for so many bases, not for each slot; the merges stay."""
    u, asked, dealt = vocabularies.unit_rows(spark, SF).cache(), [], type(spark.range(0)).repartition
    want = bpe.train_batched(u, 60, 20)
    monkeypatch.setattr(type(u), "repartition", lambda self, n, *a: asked.append(n) or dealt(self, n, *a))
    assert bpe.train_bpe(u, 60, 20, symbols=0) == want and asked == [1]
    u.unpersist()


def test_vocabularies_of_a_corpus_are_cut_together(spark):
    """One replay comes by the nested sizes, and each is learnt and tried by itself; a size beyond the merges has all of them."""
    merges = bpe.train_local([(r["unit"], r["n"]) for r in vocabularies.unit_rows(spark, SF).collect()], 120, 20)
    sizes, data = [30, 60, 4096], T.prefixes(spark, SF, 120).limit(120)
    mark = F.struct(F.col("contig").alias("id"), F.concat_ws("|", F.lit("de"), (F.col("lang") == "de").cast("int").cast("string")).alias("y"), (F.col("contig") % 3 == 0).alias("test"))
    rows = data.where("lang IS NOT NULL").select(F.col("contig").alias("key"), "seq", F.array(mark).alias("marks")).cache()
    cut, seqs = bpe.Cutter(merges, sizes), ["ACGT" * 30, "", "N", "GATTACA" * 9]
    firsts = [merges[: n - bpe.SPECIAL_AND_ALPHABET] for n in sizes]
    for (ids, of), first in zip(cut.each(np.arange(4), seqs), firsts, strict=True):
        want = bpe.Cutter(first)(np.arange(4), seqs)
        assert np.array_equal(ids, want[0]) and np.array_equal(of, want[1])
    for got, first in zip(bayes.tried_each(rows, cut), firsts, strict=True):
        want = Counter(map(tuple, bayes.tried(rows, bpe.Cutter(first)).collect()))
        assert Counter(map(tuple, got.collect())) == want and want
    learnt = dict.fromkeys(("whole", "motif", "element"), merges)
    groups = [names for names, _ in workloads.cutters(spark, SF, workloads.COMPARED["w10_domains"][1], learnt)]
    assert [len(x) for x in groups] == [3, 3, 3]
    rows.unpersist()


def test_labels_and_languages_share_their_cut(spark, monkeypatch):
    """A row for each contig, with the marks of all its tasks, goes to the tokenizers; no mark is lost."""
    sets = [workloads.language_tasks(spark, SF, 300), workloads.label_tasks(spark, SF, 300)]
    seen = []
    monkeypatch.setattr(workloads, "evaluate", lambda s, d, data, *a: seen.append(data) or data)
    registry.QUERIES["w11_dictionary_vs_bpe"](spark, SF)
    rows = seen[0].select("contig", "seq", F.size("marks").alias("n"), "marks").collect()
    assert len(rows) == len({r["contig"] for r in rows}) == sets[0].count()
    want = Counter((r["contig"], r["seq"], *m) for s in sets for r in s.collect() for m in r["marks"])
    assert Counter((r["contig"], r["seq"], *m) for r in rows for m in r["marks"]) == want
