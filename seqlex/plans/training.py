"""Training segments and budgets."""

from __future__ import annotations

from pyspark.sql import functions as F

from seqlex.operators import greedy as G
from seqlex.operators import kmer as K
from seqlex.operators import segments as P
from seqlex.sources import tables as T

from . import sql as S
from .registry import query
from .sequence import SEED, motif_vocab, words

SEG = f"{S.CONTIGS}, tok AS (SELECT contig, list_transform(range(0, length(seq)), lambda i: substr(seq, i + 1, 1)) AS t FROM contigs WHERE length(seq) > 0), seg AS (SELECT contig, k::INT AS seg_no, t[k * 512 + 1 : k * 512 + 512] AS tokens FROM tok, LATERAL (SELECT unnest(range(0, (len(t) + 511) // 512)) AS k))"


def segments(spark, d):
    """One-base tokens: a segment is a chunk, so no contig's token array is ever held whole (substrings of a long string would cost its square)."""
    cut = T.chunks(T.contigs(spark, d), 512, 0).where("n > 0")
    return cut.select("contig", F.col("chunk_no").alias("seg_no"), F.split("bases", "").alias("tokens"), F.length("bases").alias("n_tokens"))


@query("segments_512", f"WITH {SEG} SELECT contig, seg_no, len(tokens)::INT AS n_tokens, array_to_string(tokens, '') AS bases FROM seg")
def segments_512(spark, d):
    return segments(spark, d).select("contig", "seg_no", "n_tokens", F.array_join("tokens", "").alias("bases"))


@query("segments_n_filter", f"WITH {SEG} SELECT count(*) AS kept FROM seg WHERE len(list_filter(tokens, lambda t: t = 'N')) / len(tokens) <= 0.5")
def segments_n_filter(spark, d):
    return P.drop_n_segments(segments(spark, d)).agg(F.count(F.lit(1)).alias("kept"))


@query("segments_chunked", f"WITH {S.greedy('random', 7)} SELECT contig, idx // 512 AS seg_no, count(*) AS n_tokens, sum(len)::BIGINT AS bases FROM scan GROUP BY ALL")
def segments_chunked(spark, d):
    """Segments of the chunk-parallel scan: the running index comes from chunk counts."""
    t = G.greedy_chunked(T.chunks(T.contigs(spark, d), 4096), words(spark, d), size=4096)
    return P.pack_chunks(t).groupBy("contig", "seg_no").agg(F.count(F.lit(1)).alias("n_tokens"), F.sum("len").alias("bases"))


@query("mlm_mask", sql=f"WITH {SEG}, r AS (SELECT contig, seg_no, (i - 1)::INT AS slot, tokens[i] AS token FROM seg, LATERAL (SELECT unnest(range(1, len(tokens) + 1)) AS i)) SELECT contig, count(*) AS n, count(*) FILTER (('0x' || substr(md5('1|' || contig || '|' || seg_no || '|' || slot), 1, 8))::BIGINT < 644245094) AS selected FROM r GROUP BY contig")
def mlm_mask(spark, d):
    m = P.mask_segments(segments(spark, d))
    return m.groupBy("contig").agg(F.count(F.lit(1)).alias("n"), F.count_if("selected").alias("selected"))


_params = "(vocab_size + 512 + 2) * 768 + 2 * 768 + 12 * (4 * (768 * 768 + 768) + 2 * 768 + 768 * 3072 + 3072 + 3072 * 768 + 768 + 2 * 768) + 768 * 768 + 768 + 2 * 768 + vocab_size"


@query("pretrain_budget", f"""WITH {S.greedy('random', SEED)}, {S.VOCAB.replace(S.MOTIFS + ', ', '')}, v AS (SELECT count(*) AS vocab_size FROM vocab), c AS (SELECT (SELECT sum(length(seq)) FROM whole)::BIGINT AS bases, (SELECT count(*) FROM scan) AS n_tokens),
b AS (SELECT vocab_size, ({_params})::BIGINT AS params, 96::BIGINT * 512 * 200000 AS tokens, 6.0::DOUBLE * ({_params}) * (96::BIGINT * 512 * 200000) AS flops, (96::BIGINT * 512 * 200000)::DOUBLE * bases / nullif(n_tokens, 0) AS bases_seen, bases FROM v, c)
SELECT vocab_size, params, tokens, flops, bases_seen, bases_seen / nullif(bases, 0) AS epochs FROM b""")
def pretrain_budget(spark, d):
    """The budget of an encoder over the dictionary's own vocabulary, and what it sees of the documents cut by that dictionary."""
    docs = T.spread(T.table(spark, d, "documents").select(F.col("doc_id").alias("contig"), "text"))
    corpus = G.token_counts(docs, words(spark, d), seed=SEED, column="text").agg(F.sum("n_bases").alias("corpus_bases"), F.sum("n_tokens").alias("corpus_tokens"))
    return P.training_budget(motif_vocab(spark, d).agg(F.count(F.lit(1)).alias("vocab_size")).crossJoin(F.broadcast(corpus)))


@query("batch_pack", f"WITH {SEG}, h AS (SELECT contig, seg_no, md5('1|' || contig || '|' || seg_no) AS h FROM seg), n AS (SELECT *, row_number() OVER (PARTITION BY substr(h, 1, 2) ORDER BY h, contig, seg_no) - 1 AS nth FROM h) SELECT contig, seg_no, substr(h, 1, 2) || '-' || (nth // 96) AS batch_no, nth % 96 AS slot FROM n")
def batch_pack(spark, d):
    return P.make_batches(segments(spark, d))


@query("max_input_length", sql=f"WITH {S.WHOLE} SELECT lang, max(greatest(0, length(seq) - 2)) AS overlap3, max(length(seq) // 6 + length(seq) % 6) AS disjoint6 FROM whole GROUP BY lang")
def max_input_length(spark, d):
    three = K.kmer_tokens(T.contigs(spark, d), 3).select("lang", "seq", F.size("tokens").cast("long").alias("a"))
    p = K.kmer_tokens(three, 6, 6).select("lang", "a", F.size("tokens").cast("long").alias("b"))
    return p.groupBy("lang").agg(F.max("a").alias("overlap3"), F.max("b").alias("disjoint6"))


@query("truncate_pad", sql=f"WITH {S.WHOLE}, t AS (SELECT contig, list_transform(range(0, length(seq)), lambda i: instr('ACGTN', substr(seq, i + 1, 1))) AS ids FROM whole) SELECT contig, list_concat(ids[1:128], list_transform(range(0, greatest(0, 128 - len(ids))), lambda x: 0)) AS ids, list_concat(list_transform(ids[1:128], lambda x: 1), list_transform(range(0, greatest(0, 128 - len(ids))), lambda x: 0)) AS mask FROM t")
def truncate_pad(spark, d):
    ids = F.transform("tokens", lambda t: F.instr(F.lit("ACGTN"), t))
    t = K.kmer_tokens(T.contigs(spark, d), 1).select("contig", ids.alias("ids"))
    cut, mask = P.truncate_pad(F.col("ids"), 128, 0)
    return t.select("contig", cut.alias("ids"), mask.alias("mask"))
