"""Queries of the reference's operators read whole contigs, and BPE its whole corpus: against SQL and by plain definitions, on documents of some length."""

import os
from collections import Counter

import duckdb
import numpy as np
import pytest

from seqlex.operators import bpe
from seqlex.operators import greedy as G
from seqlex.operators import intervals as R
from seqlex.operators import kmer as K
from seqlex.plans import registry, vocabularies

registry.load()
SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def small(spark, tmp_path_factory):
    """Eight documents of 400 to 1,500 characters, one of 20, an empty one, and the other tables as they are."""
    folder = tmp_path_factory.mktemp("whole")
    for f in os.listdir(SF):
        if f != "documents.parquet":
            os.symlink(f"{SF}/{f}", folder / f)
    docs = f"'{SF}/documents.parquet'"
    duckdb.sql(f"""COPY (SELECT * FROM (SELECT d.* FROM {docs} d JOIN '{SF}/labels.parquet' l USING (doc_id) WHERE n_chars BETWEEN 400 AND 1500 ORDER BY lang = 'en', doc_id LIMIT 8)
    UNION ALL SELECT 900001, 'The cat and the dog.', 'en', 's', 20 UNION ALL SELECT 900002, '', 'de', 's', 0) TO '{folder}/documents.parquet'""")
    return str(folder)


def plain(x):
    return tuple(plain(y) for y in (x.values() if isinstance(x, dict) else x)) if isinstance(x, (list, tuple, dict)) else round(x, 5) if isinstance(x, float) else x


NAMES = ["greedy_random", "greedy_offset1", "greedy_emit", "greedy_chunked", "interval_nearest", "kmer_general", "mlm_mask", "tokens_to_ids", "vocab_jaccard", "wilcoxon_rank_sum"]


@pytest.mark.parametrize("name", NAMES)
def test_whole_contigs(spark, small, name):
    con = duckdb.connect()
    for f in os.listdir(small):
        con.execute(f"CREATE VIEW {f.removesuffix('.parquet')} AS SELECT * FROM '{small}/{f}'")
    found = con.execute(registry.ORACLE[name])
    columns, want = [c[0] for c in found.description], found.fetchall()
    got = registry.QUERIES[name](spark, small)
    assert got.columns == columns
    assert Counter(plain(tuple(r)) for r in got.collect()) == Counter(plain(r) for r in want)


def test_no_sql_reads_a_part_of_the_contigs():
    cut = {k for k, v in registry.ORACLE.items() if "substr(seq, 1, 300)" in v}
    # Slices of 300 bases are these queries' task.
    assert all(k.startswith(("nb_", "w", "token_profile", "mcc_", "motif_enrichment", "attribution", "integrated", "token_attr", "top", "e_", "suite", "proxy", "length_", "token_to")) for k in cut), cut


def test_training_takes_all_units(spark):
    units = [(r["unit"], r["n"]) for r in vocabularies.unit_rows(spark, SF).orderBy("unit").collect()]
    assert bpe.train_bpe(vocabularies.unit_rows(spark, SF), 128, 20) == bpe.train_local(units, 128, 20)


def by_recounting(units, merges, least):
    """Pairs counted anew for each merge."""
    words, out = [(list(u), n) for u, n in units], []
    for _ in range(merges):
        counts = Counter()
        for w, n in words:
            for p in zip(w, w[1:], strict=False):
                counts[p] += n
        best = min(counts, key=lambda p: (-counts[p], p), default=None)
        if best is None or counts[best] < least:
            break
        out.append((*best, counts[best]))
        words = [(replayed(w, [best]), n) for w, n in words]
    return out


def replayed(w, merges):
    for a, b in merges:
        new, k = [], 0
        while k < len(w):
            hit = k + 1 < len(w) and w[k] == a and w[k + 1] == b
            new.append(a + b if hit else w[k])
            k += 2 if hit else 1
        w = new
    return w


@pytest.mark.parametrize("seed", range(6))
def test_chains_against_recounting(spark, seed):
    rng = np.random.default_rng(seed)
    units = sorted({"".join(rng.choice(list("ACGTN" if seed % 2 else "AC"), rng.integers(1, 60))): int(rng.integers(1, 9)) for _ in range(40)}.items())
    want = by_recounting(units, 40, 3)
    assert bpe.train_local(units, 50, 3) == want
    seqs = ["".join(rng.choice(list("ACGTN"), n)) for n in (0, 1, 2, 200, 3)] + [u for u, _ in units[:5]] + ["AAAAAAA"]
    symbols, ends, names = bpe.replay(seqs, want)
    got = [[names[s] for s in symbols[a:b]] for a, b in zip([0, *ends[:-1]], ends, strict=True)]
    assert got == [replayed(list(s), [(a, b) for a, b, _ in want]) for s in seqs]


def test_sizes_nest_and_lose_nothing(spark):
    """Vocabularies of 1,024, 2,048 and 4,096 from one training on all units: each in the next, and every contig comes back."""
    merges = bpe.train_bpe(vocabularies.unit_rows(spark, SF), 4096, 2)
    v = [set(bpe.vocab(merges, s)) for s in (1024, 2048, 4096)]
    assert v[0] < v[1] < v[2] and len(merges) == 4086
    from seqlex.sources import tables as T

    c = T.contigs(spark, SF).select("contig", "seq")
    for n in (1014, 4086):
        rows = bpe.apply_bpe(c, merges[:n]).join(c, "contig").collect()
        assert len(rows) == 200 and all("".join(r["tokens"]) == r["seq"] for r in rows)


def test_packed_counts_are_those_of_the_tokens(spark):
    df = spark.createDataFrame([(0, "ACGTNACGTAC", "en"), (1, "AC", "de"), (2, "", "de"), (3, "NNNNNNNN", None)], "contig long, seq string, lang string")
    for k, stride in ((1, 1), (3, 1), (3, 3), (6, 6), (2, 2), (9, 1)):
        want = Counter((r["lang"], t) for r in K.kmer_tokens(df, k, stride).collect() for t in r["tokens"])
        assert {(r["lang"], r["token"]): r["n"] for r in K.kmer_counts(df, k, stride, by="lang").collect()} == want


def test_extraction_by_pieces(spark):
    seq = "".join("ACGT"[i * i % 4] for i in range(300))
    contigs = spark.createDataFrame([(0, seq), (1, "ACG")], "contig long, seq string")
    iv = [(0, 0, 300), (0, 10, 25), (0, 10, 25), (0, 99, 101), (0, 299, 300), (0, 5, 5), (1, 0, 3)]
    got = R.extract(spark.createDataFrame(iv, "contig long, start long, end long"), contigs, 16).collect()
    assert Counter(tuple(r) for r in got) == Counter((c, a, b, (seq if c == 0 else "ACG")[a:b]) for c, a, b in iv)


def test_exits_of_merged_walks():
    rng = np.random.default_rng(0)
    for end in (1, 5, 14, 200):
        length, offset = rng.integers(1, 13, end + 30), rng.integers(0, 3, end + 30)
        to, n = G.exits(length, offset, end)
        for e in range(G.REACH):
            places, at = G.walk(length, offset, e, end)
            assert (to[e], n[e]) == (at, len(places))


def test_batched_training_to_the_full_size(spark, monkeypatch):
    """Scanned or linked, told by files or by the stage's messages: the merges of one-by-one training, in a stage that costs no job for each round."""
    u = vocabularies.unit_rows(spark, SF).cache()
    want = bpe.train_local([(r["unit"], r["n"]) for r in u.collect()], 4096, 20)
    assert len(want) > 800
    jobs = spark.sparkContext.statusTracker()
    spark.sparkContext.setJobGroup("bpe", "bpe")
    for linked in (0, 300_000, 1 << 40):
        assert bpe.train_batched(u, 4096, 20, linked=linked) == want
    assert len(jobs.getJobIdsForGroup("bpe")) < 30
    monkeypatch.setattr(bpe, "shared_folder", lambda spark: None)
    assert bpe.train_batched(u, 18, 20) == want[:8]
    u.unpersist()
