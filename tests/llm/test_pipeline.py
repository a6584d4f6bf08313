"""The pipeline's stages against plain Python on a small table."""

from collections import Counter, defaultdict

import pytest
from pyspark.sql import functions as F

from seqlex.llm import langid, mixing, unigram_pieces

from .test_operators import brute_classes

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def stages(spark):
    import corpus_pipeline as p
    from seqlex.llm.common import spool, table

    docs = table(spark, SF, "documents")
    out = [docs]
    for _, stage in p.STAGES:
        out.append(spool(stage(spark, out[-1], SF), "test"))
    return out


def test_stage_decisions(spark, stages):
    docs, known, lines, single, mixed, encoded = stages
    assert all(s.columns == docs.columns for s in (known, lines, single, mixed))
    verdict = {r["doc_id"]: r["rejected"] for r in langid.identify(docs).collect()}
    assert {r["doc_id"] for r in known.collect()} == {i for i, bad in verdict.items() if not bad}

    rows = {r["doc_id"]: r for r in known.collect()}
    sites, first = defaultdict(set), {}
    for i in sorted(rows):
        for x in rows[i]["text"].split("\n"):
            if len(x.strip(" ")) >= 20:
                sites[x.strip(" ")].add(rows[i]["source"])
                first.setdefault(x.strip(" "), i)
    want = {}
    for i, r in rows.items():
        kept = [x for x in r["text"].split("\n") if not (len(sites[x.strip(" ")]) >= 10 and first[x.strip(" ")] != i)]
        if len(kept) == len(r["text"].split("\n")) or "\n".join(kept).strip(" "):
            want[i] = "\n".join(kept)
    assert {r["doc_id"]: r["text"] for r in lines.collect()} == want

    heads = {min(c) for c in brute_classes([(i, t) for i, t in want.items()])}
    assert {r["doc_id"] for r in single.collect()} == heads
    kept = {r["doc_id"] for r in mixing.mix_to_targets(single, keep=0.75).where("__kept").collect()}
    assert {r["doc_id"] for r in mixed.collect()} == kept and len(kept) > 0.5 * len(heads)

    p = unigram_pieces.load()
    assert {r["doc_id"]: p.decode(r["ids"]) for r in encoded.collect()} == {i: want[i] for i in kept}


def test_run_is_repeatable(spark, stages):
    import corpus_pipeline as p

    assert {(r["doc_id"], r["n_pieces"]) for r in p.run(spark, SF).collect()} == {(r["doc_id"], r["n_pieces"]) for r in stages[-1].collect()}


def test_empty_documents(spark, tmp_path):
    import corpus_pipeline as p

    spark.read.parquet(f"{SF}/documents.parquet").limit(0).write.parquet(str(tmp_path / "documents.parquet"))
    assert p.run(spark, str(tmp_path)).count() == 0


def edge_rows():
    """Nulls, empty and blank texts, repeated rows and ids, ties, and user columns named like the operators' own."""
    import random

    rng = random.Random(1)
    word = lambda lang, n: " ".join(rng.choice({"en": "the and of that with this from".split(), "de": "der und die nicht auf dem sich".split()}[lang]) for _ in range(n))
    line = "This very line stands on many sites."
    rows = [(i, (line + "\n" if i % 2 else "") + word(lang, 60), lang, f"s{i % 24}", 777) for i in range(120) for lang in [["en", "de"][i % 4 // 2]]]
    rows += [(500, None, "en", "s1", 777), (501, "", "en", None, 777), (502, "  ", None, "s2", 777), (503, line, "en", "s3", 777), (504, "12 345", "de", "s4", 777), (None, word("en", 50), None, None, None)]
    return [*rows, rows[3], rows[3], (600, rows[4][1], "de", "s9", 777), (505, word("de", 30000), "de", "s5", 777)]


SHAPE = "doc_id long, text string, lang string, source string, n_removed int"


@pytest.mark.parametrize("number", range(5))
def test_stages_on_edges(spark, tmp_path, number):
    """Each stage by itself: its columns, what it does to null and empty texts and repeated rows, clashing names, and an empty table."""
    import corpus_pipeline as p

    name, stage = p.STAGES[number]
    docs = spark.createDataFrame(edge_rows(), SHAPE).withColumns({"__kept": F.lit("mine"), "__topic": F.lit(1), "h1": F.lit(2), "node": F.lit("n"), "__removed": F.lit(3)}).repartition(3)
    docs.write.parquet(str(tmp_path / "in"))
    docs = spark.read.parquet(str(tmp_path / "in"))
    got = stage(spark, docs, SF).collect()
    assert stage(spark, docs.limit(0), SF).count() == 0
    texts, ids = [r["text"] for r in got] if name != "sentencepiece" else [], Counter(r["doc_id"] for r in got)
    if name != "sentencepiece":
        assert stage(spark, docs, SF).columns == docs.columns
        assert all(r["n_removed"] in (777, None) and r["__kept"] == "mine" and r["__topic"] == 1 and r["h1"] == 2 and r["__removed"] == 3 for r in got)
    if name == "language_id":
        assert not any(t is None or not t.strip() or t == "12 345" for t in texts) and ids[3] in (0, 3) and ids[505] == 1
    elif name == "line_dedup":
        assert None in texts and "" in texts and ids[503] == 0 and ids[3] == 3 and len(got) == docs.count() - 1
        assert sum("stands on many sites" in (t or "") for t in texts) == 1
    elif name == "minhash":
        assert ids[3] == 1 and ids[600] == 0 and ids[500] == 1 and ids[501] == 1 and ids[None] == 1
    elif name == "mixing":
        assert ids[500] == ids[501] == ids[502] == 1 and ids[3] in (0, 3)
    else:
        assert len(got) == docs.count() and all((r["ids"] is None) == (r["doc_id"] == 500) and r["round_trip"] for r in got)


def test_run_leaves_its_last_stage_only(spark, tmp_path):
    import corpus_pipeline as p
    from seqlex.llm import common

    spark.createDataFrame(edge_rows(), SHAPE).write.parquet(str(tmp_path / "documents.parquet"))
    before = len(common.spooled)
    assert p.run(spark, str(tmp_path)).count() > 0 and len(common.spooled) == before + 1
