"""A training corpus from `documents`: each stage is one of the training-data operators, written as Parquet and read again.

What the stages share: columns that a stage doesn't read pass through, whatever their names; a null in them, and a null id, does no harm; very long texts are read whole; an
empty table gives an empty one. Each stage says what becomes of null and empty texts, ties and repeated rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from seqlex.llm import bagminhash, langid, line_dedup, mixing, unigram_pieces
from seqlex.llm.common import discard, fresh, spool, spooled, table


def known_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language is recognised; the rejected ones (no letter, or a score under the calibrated threshold) go, and so do null and empty texts. A score equal to
    the threshold stays. Repeated rows stay or go together. Without any labelled row no language is known and all go."""
    model = langid.train(langid.sample(docs, 4000))
    kept = langid.keep_recognised(docs, model)
    return kept.select(*docs.columns)


def without_boilerplate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines on ten sites or more go from all documents but the one of the least id (rows without an id come last, and of repeated ids all keep it); a document of which nothing
    is left goes. A null or empty text has no such line and stays as it is; a null source is a site."""
    lines = fresh(docs.columns, "n_lines")
    removed = fresh([*docs.columns, lines], "n_removed")
    cleaned = line_dedup.clean(docs, counts=(lines, removed))
    return cleaned.where(f"{removed} = 0 or length(trim(text)) > 0").select(*docs.columns)


def without_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates stays, the one of the least id; of rows that repeat with its id one stays. Empty texts are one group; null texts and
    rows without an id stay."""
    return bagminhash.one_of_each(docs)


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A sample whose sources, languages and forms approach their target shares. Null sources and languages are categories of their own; a text without a word stays;
    rows of one id stay or go together, rows without an id by their text."""
    prefix = "__"
    while any(c.lower().startswith(prefix) for c in docs.columns):
        prefix += "_"
    return mixing.mix_to_targets(docs, keep=0.75, prefix=prefix).where(f"{prefix}kept").select(*docs.columns)


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A row for each document, repeated ones too: its piece ids, which decode to its text. A null text has null ids, an empty one none."""
    return unigram_pieces.encode_documents(docs, unigram_pieces.load())


STAGES = [
    ("language_id", known_language),
    ("line_dedup", without_boilerplate),
    ("minhash", without_near_copies),
    ("mixing", mixed),
    ("sentencepiece", encoded),
]

#: Signatures, raking and Viterbi paths have no SQL; tests hold run() against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in turn. What a stage spooled, its input included, is deleted when its output is written."""
    docs = table(spark, sf_dir, "documents")
    before = len(spooled)
    for name, stage in STAGES:
        docs = spool(stage(spark, docs, sf_dir), name)
        discard(spark, spooled[before:-1])
    return docs
