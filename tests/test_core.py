"""Hand fixtures, invariants and cross-engine equality of the sequence operators."""

import itertools

import pytest
from pyspark.sql import functions as F

from seqlex.functions import bases as B
from seqlex.operators import bpe, greedy, intervals, kmer, models, segments
from seqlex.sources import formats, tables
from seqlex.streaming import tokens as streams

WORDS = ["ACGT", "ACGTAC", "GTACGT", "TTGCA", "TGCAA"]
SF = "/root/testdata/sf0.001"


def scan(spark, seq, **options):
    df = spark.createDataFrame([(0, seq)], "contig long, seq string")
    return " ".join(t["token"] for t in greedy.greedy_tokenize(df, WORDS, **options).first()["tokens"])


# The expected cuts of the hand fixtures (longest, shortest, random with seed 7, longest without look-ahead).
CASES = [
    ("ACGTACGT", "ACGTAC G T", "GTACGT", "GTACGT", "ACGTAC G T"),
    ("GACGTACTT", "ACGTAC T T", "ACGT ACT T", "ACGT ACT T", "GAC GTA CTT"),
    ("CCTTGCAANNACG", "TTGCA A ACG", "TTGCA A ACG", "TTGCA A ACG", "CCT TGCAA N N ACG"),
    ("AAACGT", "ACGT", "ACGT", "ACGT", "AAA CGT"),
    ("NNNNN", "N N N N N", "N N N N N", "N N N N N", "N N N N N"),
    ("AC", "A C", "A C", "A C", "A C"),
    ("", "", "", "", ""),
]


@pytest.mark.parametrize("seq,longest,shortest,random,plain", CASES)
def test_hand_fixtures(spark, seq, longest, shortest, random, plain):
    assert scan(spark, seq, pick="longest") == longest
    assert scan(spark, seq, pick="shortest") == shortest
    assert scan(spark, seq, pick="random", seed=7) == random
    assert scan(spark, seq, pick="longest", max_offset=0) == plain
    assert scan(spark, seq, pick="longest", skip="emit").replace(" ", "") == seq


@pytest.mark.parametrize("size,pick", list(itertools.product((64, 257), ("random", "longest", "shortest"))))
def test_chunks_give_the_tokens_of_the_whole(spark, size, pick):
    contigs = tables.contigs(spark, SF).where("contig < 25")
    words = [a + b + c + d for a, b, c, d in itertools.product("ACGT", repeat=4)][::5] + ["ACGTACGTAC", "TTTATTTATTTA"]
    whole = {(r["contig"], r["pos"], r["token"]) for r in greedy.token_rows(greedy.greedy_tokenize(contigs, words, pick=pick)).collect()}
    cut = greedy.greedy_chunked(tables.chunks(contigs, size), words, size=size, pick=pick)
    parts = cut.select("contig", "token_offset", F.posexplode("tokens").alias("k", "t")).collect()
    assert {(r["contig"], r["t"]["pos"], r["t"]["token"]) for r in parts} == whole
    assert len({(r["contig"], r["token_offset"] + r["k"]) for r in parts}) == len(parts) == len(whole)


def test_projection_and_primitives(spark):
    row = spark.createDataFrame([("The cat\tSAT, 1\n",)], "t string").select(B.to_bases("t").alias("s")).select("s", B.revcomp("s").alias("r"), B.n_share(F.col("s")).alias("n")).first()
    assert row["s"] == "CGACTCTTCNN" and row["r"] == "NNGAAGAGTCG" and abs(row["n"] - 2 / 11) < 1e-12


def test_kmers(spark):
    df = spark.createDataFrame([(0, "ACGTNAC")], "contig long, seq string")
    get = lambda *a, **k: df.select(kmer.kmers(F.col("seq"), *a, **k).alias("t")).first()["t"]
    assert get(3, 1) == ["ACG", "CGT", "GTN", "TNA", "NAC"] and get(3, 3) == ["ACG", "TNA", "C"]
    assert get(3, 3, remainder="drop") == ["ACG", "TNA"] and get(3, 3, n_policy="unk") == ["ACG", "[UNK]", "C"] and get(9, 1) == []


def test_bpe_trainers_agree_and_nest(spark):
    u = bpe.units(tables.table(spark, SF, "documents").limit(30))
    small, local = bpe.train_sql(u, 6), bpe.train_bpe(u, 60, 20)
    assert local[:6] == small
    v = [set(bpe.vocab(local, s)) for s in (20, 40, 60)]
    assert v[0] < v[1] <= v[2]
    seqs = tables.prefixes(spark, SF).where("contig < 20")
    assert bpe.train_bpe(u, 40, 20, symbols=10) == bpe.train_bpe(u, 40, 20)
    exact = {r["contig"]: r["t"] for r in seqs.select("contig", bpe.apply_sql(F.col("seq"), local[:10]).alias("t")).collect()}
    for r in bpe.apply_bpe(seqs, local[:10]).collect():
        assert r["tokens"] == exact[r["contig"]]
    assert all("".join(r["tokens"]) == r["seq"] for r in bpe.apply_bpe(seqs, local).join(seqs, "contig").collect())


def test_intervals(spark):
    iv = spark.createDataFrame([(0, 0, 5), (0, 3, 8), (0, 8, 9), (0, 20, 30)], "contig long, start long, end long")
    merged = intervals.merge(iv)
    assert sorted((r["start"], r["end"]) for r in merged.collect()) == [(0, 9), (20, 30)]
    assert sorted((r["start"], r["end"]) for r in intervals.merge_binned(iv, 4).collect()) == [(0, 9), (20, 30)]
    bounds = spark.createDataFrame([(0, 40), (1, 7)], "contig long, length int")
    assert sorted((r["contig"], r["start"], r["end"]) for r in intervals.complement(merged, bounds).collect()) == [(0, 9, 20), (0, 30, 40), (1, 0, 7)]
    assert intervals.tile(iv, 4).count() == 1 + 1 + 0 + 2


def test_scores(spark):
    rows = [("a", 1, 1)] * 90 + [("a", 0, 0)] * 80 + [("a", 0, 1)] * 20 + [("a", 1, 0)] * 10 + [("b", 0, 0)] * 100
    got = {r["task"]: r for r in models.scores(spark.createDataFrame(rows, "task string, y int, yhat int"), "task").collect()}
    assert abs(got["a"]["mcc"] - 0.703526) < 1e-6 and got["b"]["mcc"] == 0
    multi = models.mcc_multiclass(spark.createDataFrame(rows[:200], "task string, y int, yhat int")).first()["mcc"]
    assert abs(multi - got["a"]["mcc"]) < 1e-6


def test_segments(spark):
    df = spark.createDataFrame([(0, list("ACGTN") * 3), (1, ["N"] * 9), (2, [])], "contig long, tokens array<string>")
    kept = segments.pack_segments(df, 4)
    assert sorted((r["contig"], r["seg_no"], r["n_tokens"]) for r in kept.collect()) == [(0, 0, 4), (0, 1, 4), (0, 2, 4), (0, 3, 3), (1, 0, 4), (1, 1, 4), (1, 2, 1)]
    assert segments.drop_n_segments(kept).count() == 4
    assert all(r["n_tokens"] == 4 for r in segments.pack_segments(df, 4, tail="drop").collect())
    assert all(len(r["tokens"]) == 4 for r in segments.pack_segments(df, 4, tail="pad").collect())


def test_streaming_equals_batch(spark, tmp_path):
    seqs = tables.prefixes(spark, SF).select("contig", "seq").repartition(3)
    seqs.write.parquet(str(tmp_path / "in"))
    stream = streams.stream_tokenize(streams.read_files(spark, str(tmp_path / "in"), seqs.schema), WORDS, pick="longest")
    got = streams.run_available(stream, "tokens_out", str(tmp_path / "ck"))
    want = greedy.greedy_tokenize(seqs, WORDS, pick="longest")
    assert got.exceptAll(want).count() == 0 and got.count() == want.count()
    events = tables.table(spark, SF, "events")
    events.write.parquet(str(tmp_path / "ev"))
    live = streams.run_available(streams.windowed(streams.read_files(spark, str(tmp_path / "ev"), events.schema), "1 day"), "win_out", str(tmp_path / "ck2"), "complete")
    assert live.exceptAll(streams.windowed(events, "1 day")).count() == 0 and live.count() > 0


def test_formats(spark, tmp_path):
    (tmp_path / "x.fa").write_text(">c1 first\nACGT\nac\n>c2\nNN\n")
    assert sorted(tuple(r) for r in formats.read_fasta(spark, str(tmp_path / "x.fa")).collect()) == [("c1", "ACGTAC"), ("c2", "NN")]
    (tmp_path / "x.bed").write_text("c1\t0\t5\tPLS\n")
    assert tuple(formats.read_intervals(spark, str(tmp_path / "x.bed")).first()) == ("c1", 0, 5, "PLS")
    (tmp_path / "m.txt").write_text(">M1 name\nA [ 1 2 ]\nC [ 3 4 ]\nG [ 0 0 ]\nT [ 5 6 ]\n")
    rows = {r["base"]: r["counts"] for r in formats.read_matrices(spark, str(tmp_path / "m.txt")).collect()}
    assert rows["C"] == [3.0, 4.0] and len(rows) == 4


def test_sql_functions(spark):
    from seqlex.functions.sql import register

    register(spark, WORDS)
    row = spark.sql("SELECT to_bases('The cat') AS b, revcomp('AAC') AS r, kmers('ACGT', 3) AS k, motif_tokens('ACGTACGT') AS m").first()
    assert row["b"] == "CGACTC" and row["r"] == "GTT" and row["k"] == ["ACG", "CGT"] and row["m"] == ["ACGTAC", "G", "T"]


def test_plans_push_down_and_prune(spark):
    df = tables.contigs(spark, SF).where("lang = 'de'").select("contig", "seq")
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert "EqualTo(lang,de)" in plan and "n_chars" not in plan


def test_queries_of_the_library(spark):
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())
    assert e.entry(spark).count() == 4


@pytest.mark.parametrize("units", [[("ACACGTGTACAC", 3), ("GTGTACGT", 2), ("AAAAA", 4), ("NNACNN", 1)], [("AAAAAAAA", 1)], [("ACGT" * 5, 2), ("TTTTACCA" * 3, 5), ("GGTTACAT", 7)], []])
def test_batched_training_gives_the_merges_of_one_by_one(spark, units):
    frame = spark.createDataFrame(units, "unit string, n long")
    want = bpe.train_local(sorted(units), 40, 2)
    assert bpe.train_batched(frame, 40, 2) == want
    assert bpe.train_sql(frame, 30, 2) == want


def test_batched_training_on_documents(spark):
    u = bpe.units(tables.table(spark, SF, "documents")).cache()
    assert bpe.train_batched(u, 34, 20) == bpe.train_local([(r["unit"], r["n"]) for r in u.collect()], 34, 20)


def test_stream_packer(spark, tmp_path):
    parts = [(1, 0, list("ACGTA")), (1, 1, list("CC")), (2, 0, list("GGG")), (3, 0, [])]
    spark.createDataFrame(parts, "contig long, part_no long, tokens array<string>").coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = streams.read_files(spark, str(tmp_path / "in"), "contig long, part_no long, tokens array<string>")
    got = streams.run_available(streams.pack_stream(stream, 3), "packed", str(tmp_path / "cp")).collect()
    assert sorted((r["contig"], r["seg_no"], "".join(r["tokens"])) for r in got) == [(1, 0, "ACG"), (1, 1, "TAC"), (2, 0, "GGG")]
