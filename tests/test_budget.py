"""The training budget: what it sees of the corpus, against SQL and by the tokens themselves, on odd documents too."""

import os
import random

import duckdb
import pytest

from seqlex.functions.bases import bases
from seqlex.operators import greedy as G
from seqlex.operators import segments
from seqlex.plans import registry

registry.load()
SF = "/root/testdata/sf0.001"
WORDS = ["ACGT", "ACGTAC", "GTACGT", "TTGCA", "TGCAA", "ACGTACGTACGT", "TTTT", "TTTTTT"]
ODD = [(1, "The cat and the dog.\n\tTHE CAT"), (2, ""), (3, None), (4, "é中!? 12"), (5, " \t\r\n"), (7, "ab" * 700)]


def folder_of(path, rows):
    """The given tables, with documents of rows (doc_id, text)."""
    for f in os.listdir(SF):
        if f != "documents.parquet":
            os.symlink(f"{SF}/{f}", path / f)
    con = duckdb.connect()
    con.execute("CREATE TABLE documents (doc_id BIGINT, text VARCHAR, lang VARCHAR, source VARCHAR, n_chars BIGINT)")
    if rows:
        con.executemany("INSERT INTO documents VALUES (?, ?, 'en', 's', 0)", [list(r) for r in rows])
    con.execute(f"COPY documents TO '{path}/documents.parquet'")
    return str(path)


@pytest.mark.parametrize("rows", [ODD, [(1, ""), (2, None)], []], ids=["odd", "blank", "none"])
def test_budget_reads_the_documents(spark, tmp_path, rows):
    folder = folder_of(tmp_path, rows)
    con = duckdb.connect()
    for f in ("documents", "embeddings"):
        con.execute(f"CREATE VIEW {f} AS SELECT * FROM '{folder}/{f}.parquet'")
    found = con.execute(registry.ORACLE["pretrain_budget"])
    columns, want = [c[0] for c in found.description], found.fetchall()
    got = registry.QUERIES["pretrain_budget"](spark, folder)
    assert got.columns == columns == ["vocab_size", "params", "tokens", "flops", "bases_seen", "epochs"]
    assert [tuple(r) for r in got.collect()] == want and len(want) == 1
    assert all(any(t in f for f in got.inputFiles()) for t in ("documents", "embeddings"))
    if rows is ODD:
        words = [r[0] for r in con.execute(registry.ORACLE["motif_strands"]).fetchall()]
        seqs = [(k, bases(t or "")) for k, t in rows]
        tokens = sum(len(r["tokens"]) for r in G.greedy_tokenize(spark.createDataFrame(seqs, "contig long, seq string"), words).collect())
        budget = 96 * 512 * 200_000
        assert want[0][4] == pytest.approx(budget * sum(len(s) for _, s in seqs) / tokens) and want[0][5] == pytest.approx(budget / tokens)
    else:
        assert want[0][4:] == (None, None)


def test_budget_by_hand(spark):
    row = segments.training_budget(spark.createDataFrame([(1000, 700, 200)], "vocab_size long, corpus_bases long, corpus_tokens long"), batch=2, max_len=10, steps=50).first()
    assert (row["tokens"], row["bases_seen"], row["epochs"]) == (1000, 3500.0, 5.0) and row["flops"] == 6.0 * row["params"] * 1000


@pytest.mark.parametrize("pick,max_offset", [("random", 2), ("longest", 2), ("shortest", 2), ("random", 0), ("longest", 1)])
def test_counts_are_those_of_the_tokens(spark, pick, max_offset):
    """Whatever the pieces, with sequences at and around their size."""
    r = random.Random(5)
    sizes = [0, 1, 2, 3, 15, 16, 17, 31, 32, 33, 64, 65, 400, 3000, 0, 1]
    rows = [(k, "".join(r.choice(["A", "C", "G", "T", "N", "ACGT", "GTAC", "TTT"]) for _ in range(n))[:n]) for k, n in enumerate(sizes)] + [(50, "ACGT" * 100), (51, "N" * 70), (52, "T" * 200)]
    df = spark.createDataFrame(rows, "contig long, seq string")
    want = {x["contig"]: (x["n_bases"], len(x["tokens"])) for x in G.greedy_tokenize(df, WORDS, pick=pick, max_offset=max_offset).collect()}
    got = G.token_counts(df, WORDS, pick=pick, max_offset=max_offset).collect()
    assert {x["contig"]: (x["n_bases"], x["n_tokens"]) for x in got} == want and len(got) == len(rows)
    keys, seqs = zip(*rows, strict=True)
    for size in (1, 2, 3, 16, 32, 100, 1000):
        assert G.n_tokens(G.PackedDict(WORDS), list(keys), list(seqs), pick, 7, max_offset, size) == [want[k][1] for k in keys]


def test_counts_of_given_documents(spark):
    from seqlex.plans.sequence import words
    from seqlex.sources import tables as T

    w, c = words(spark, SF), T.contigs(spark, SF)
    want = {x["contig"]: (x["n_bases"], len(x["tokens"])) for x in G.greedy_tokenize(c, w).collect()}
    text = T.table(spark, SF, "documents").withColumnRenamed("doc_id", "contig")
    for df, column in ((c, "seq"), (text, "text")):
        assert {x["contig"]: (x["n_bases"], x["n_tokens"]) for x in G.token_counts(df, w, column=column).collect()} == want
