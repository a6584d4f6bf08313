"""Primitives, k-mers, the motif dictionary and greedy tokenisation."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seqlex.functions import bases as B
from seqlex.operators import greedy as G
from seqlex.operators import kmer as K
from seqlex.operators import pwm as V
from seqlex.sources import tables as T

from . import sql as S
from .registry import query

SEED = 7


@query("bases_project", f"WITH {S.CONTIGS} SELECT contig, seq, lang FROM contigs")
def bases_project(spark, d):
    return T.contigs(spark, d)


_counts = ", ".join(f"sum(length(seq) - length(replace(seq, '{b}', '')))::BIGINT AS n_{b.lower()}" for b in B.ALPHABET)


@query("base_composition", f"WITH {S.CONTIGS} SELECT lang, {_counts}, sum(length(seq))::BIGINT AS bases, round(sum(length(seq) - length(replace(replace(seq, 'G', ''), 'C', ''))) / sum(length(replace(seq, 'N', ''))), 6) AS gc FROM contigs GROUP BY lang")
def base_composition(spark, d):
    c = T.contigs(spark, d)
    sums = [F.sum(B.count_of(F.col("seq"), b)).alias(f"n_{b.lower()}") for b in B.ALPHABET]
    return c.groupBy("lang").agg(*sums, F.sum(F.length("seq")).alias("bases")).withColumn("gc", F.round((F.col("n_g") + F.col("n_c")) / (F.col("bases") - F.col("n_n")), 6))


@query("revcomp", sql=f"WITH {S.WHOLE} SELECT contig, {S.revcomp('seq')} AS rc FROM whole")
def revcomp(spark, d):
    return T.contigs(spark, d).select("contig", B.revcomp("seq").alias("rc"))


@query("n_share", f"WITH {S.CONTIGS} SELECT contig, round(CASE WHEN length(seq) > 0 THEN (length(seq) - length(replace(seq, 'N', ''))) / length(seq) ELSE 0 END, 9) AS n_share FROM contigs")
def n_share(spark, d):
    return T.contigs(spark, d).select("contig", F.round(B.n_share(F.col("seq")), 9).alias("n_share"))


@query("chunk_contigs", f"WITH {S.CONTIGS} SELECT contig, c::INT AS chunk_no, (c * 257)::INT AS start, length(seq)::INT AS n, substr(seq, c * 257 + 1, 271) AS bases FROM contigs, LATERAL (SELECT unnest(range(0, greatest(1, (length(seq) + 256) // 257))) AS c)")
def chunk_contigs(spark, d):
    return T.chunks(T.contigs(spark, d), 257)


@query("fixed_slices", f"WITH {S.CONTIGS} SELECT contig, lang, s::INT AS slice_no, substr(seq, s * 300 + 1, 300) AS seq FROM contigs, LATERAL (SELECT unnest(range(0, (length(seq) // 300))) AS s)")
def fixed_slices(spark, d):
    return T.slices(T.contigs(spark, d), 300, 300)


@query("canonical_kmer", sql=f"WITH {S.WHOLE} SELECT token, count(*) AS n FROM (SELECT least(k, {S.revcomp('k')}) AS token FROM (SELECT substr(seq, i + 1, 4) AS k FROM whole, LATERAL (SELECT unnest(range(0, length(seq) - 3)) AS i))) GROUP BY token")
def canonical_kmer(spark, d):
    return K.kmer_counts(T.contigs(spark, d), 4).groupBy(B.canonical(F.col("token")).alias("token")).agg(F.sum("n").alias("n"))


def _kmers(name: str, k: int, stride: int) -> None:
    full = f"list_transform(range(0, greatest(0, length(seq) - {k} + 1), {stride}), lambda i: substr(seq, i + 1, {k}))"
    rest = f"list_transform(range(length(seq) - length(seq) % {k}, length(seq)), lambda i: substr(seq, i + 1, 1))" if stride == k else "[]"

    @query(name, sql=f"WITH {S.WHOLE} SELECT contig, list_concat({full}, {rest}) AS tokens FROM whole")
    def run(spark, d):
        return K.kmer_tokens(T.contigs(spark, d), k, stride).select("contig", "tokens")

    @query(f"{name}_counts", f"WITH {S.CONTIGS} SELECT token, count(*) AS n FROM (SELECT unnest(list_concat({full}, {rest})) AS token FROM contigs) GROUP BY token")
    def counts(spark, d):
        return K.kmer_counts(T.contigs(spark, d), k, stride)


for _name, _k, _stride in (("kmer3_overlap", 3, 1), ("kmer6_overlap", 6, 1), ("kmer6_disjoint", 6, 6), ("onemer", 1, 1)):
    _kmers(_name, _k, _stride)


@query("kmer_general", sql=f"WITH {S.WHOLE} SELECT contig, list_transform(list_transform(range(0, greatest(0, length(seq) - 4), 2), lambda i: substr(seq, i + 1, 5)), lambda t: CASE WHEN contains(t, 'N') THEN '[UNK]' ELSE t END) AS tokens FROM whole")
def kmer_general(spark, d):
    return K.kmer_tokens(T.contigs(spark, d), 5, 2, n_policy="unk").select("contig", "tokens")


@query("kmer_vocab", f"WITH {S.WHOLE}, b AS (SELECT unnest(['A', 'C', 'G', 'T']) AS b), v AS (SELECT x.b || y.b || z.b AS token FROM b x, b y, b z), c AS (SELECT seq[i : i + 2] AS token, count(*) AS n FROM (SELECT seq, unnest(range(1, length(seq) - 1)) AS i FROM whole) GROUP BY 1) SELECT token, coalesce(n, 0) AS n FROM v LEFT JOIN c USING (token)")
def kmer_vocab(spark, d):
    """All 3-mers over A, C, G, T, each with its places in the whole contigs."""
    used = K.kmer_counts(T.contigs(spark, d), 3).select("token", "n")
    return K.kmer_vocab(spark, 3).join(used, "token", "left").select("token", F.coalesce("n", F.lit(0)).alias("n"))


def motif_strings(spark: SparkSession, d: str) -> DataFrame:
    return V.both_strands(V.consensus(V.matrices(T.table(spark, d, "embeddings"))))


def words(spark: SparkSession, d: str) -> list[str]:
    """The dictionary's motif strings: at most two for each of the library's MATRICES matrices."""
    return sorted(r["seq"] for r in motif_strings(spark, d).select("seq").collect())


@query("pwm_from_counts", f"WITH {S.MATRICES} SELECT motif_id, p::INT AS pos, round(rows[p + 1][1], 9) AS a, round(rows[p + 1][2], 9) AS c, round(rows[p + 1][3], 9) AS g, round(rows[p + 1][4], 9) AS t FROM matrices, LATERAL (SELECT unnest(range(0, width)) AS p)")
def pwm_from_counts(spark, d):
    m = V.matrices(T.table(spark, d, "embeddings")).select("motif_id", F.posexplode("rows").alias("pos", "r"))
    counts = m.select("motif_id", "pos", *[(F.element_at("r", k + 1) * 1000).alias(b) for k, b in enumerate("acgt")])
    return V.normalise(counts).select("motif_id", "pos", *[F.round(b, 9).alias(b) for b in "acgt"])


@query("pwm_width_filter", f"WITH {S.MATRICES} SELECT width, count(*) AS n FROM matrices WHERE width <= 12 GROUP BY width")
def pwm_width_filter(spark, d):
    return V.matrices(T.table(spark, d, "embeddings")).where("width <= 12").groupBy("width").agg(F.count(F.lit(1)).alias("n"))


@query("pwm_binarise", f"WITH {S.MATRICES} SELECT motif_id, {S.marked('0.5')} AS marked FROM matrices")
def pwm_binarise(spark, d):
    return V.matrices(T.table(spark, d, "embeddings")).select("motif_id", V.marked(F.col("rows"), 0.5).alias("marked"))


@query("pwm_trim", f"WITH {S.CONSENSUS} SELECT motif_id, family, seq FROM consensus")
def pwm_trim(spark, d):
    return V.consensus(V.matrices(T.table(spark, d, "embeddings")))


@query("pwm_trim_reject", f"WITH {S.MATRICES} SELECT motif_id, family, upper(s) AS seq FROM (SELECT motif_id, family, {S.TRIM.format(S.marked('0.5'))} AS s FROM matrices WHERE width <= 12) WHERE length(s) > 0 AND NOT regexp_matches(s, '[acgt]')")
def pwm_trim_reject(spark, d):
    return V.consensus(V.matrices(T.table(spark, d, "embeddings")), interior="reject")


@query("motif_strands", f"WITH {S.MOTIFS} SELECT seq, n_sources FROM motifs")
def motif_strands(spark, d):
    return motif_strings(spark, d)


@query("motif_vocab", f"WITH {S.VOCAB} SELECT token_id, token, kind, len FROM vocab")
def motif_vocab(spark, d):
    return V.build_vocab(spark, motif_strings(spark, d))


@query("vocab_profile", f"WITH {S.VOCAB} SELECT kind, count(*) AS n, round(avg(len), 6) AS mean_len, count(*) FILTER (kind = 'motif' AND len < 4) AS unmatchable FROM vocab GROUP BY kind")
def vocab_profile(spark, d):
    v = V.build_vocab(spark, motif_strings(spark, d))
    return v.groupBy("kind").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("len"), 6).alias("mean_len"), F.count_if((F.col("kind") == "motif") & (F.col("len") < 4)).alias("unmatchable"))


@query("pwm_threshold_sweep", f"""WITH {S.MATRICES}, t AS (SELECT unnest([0.3, 0.4, 0.5, 0.6, 0.7, 0.8, 0.9])::DOUBLE AS threshold), m AS (SELECT threshold, {S.marked('threshold')} AS m FROM matrices, t WHERE width <= 12)
SELECT threshold, count(*) FILTER (length(s) > 0) AS motifs, round(avg(length(s)) FILTER (length(s) > 0), 6) AS mean_len, round(sum(length(regexp_replace(m, '[A-Z]', '', 'g'))) / sum(length(m)), 6) AS wildcard_share FROM (SELECT *, {S.TRIM.format('m')} AS s FROM m) GROUP BY threshold""")
def pwm_threshold_sweep(spark, d):
    return V.sweep(V.matrices(T.table(spark, d, "embeddings")), [0.3, 0.4, 0.5, 0.6, 0.7, 0.8, 0.9])


@query("pwm_information", f"WITH {S.MATRICES} SELECT motif_id, round(list_sum(list_transform(rows, lambda r: 2.0 + list_sum(list_transform(r, lambda p: CASE WHEN p > 0 THEN p * log2(p) ELSE 0 END)))), 6) AS bits FROM matrices")
def pwm_information(spark, d):
    return V.information(V.matrices(T.table(spark, d, "embeddings"))).select("motif_id", F.round("bits", 6).alias("bits"))


@query("greedy_candidates", f"WITH {S.HITS} SELECT contig, start, \"end\" FROM iv")
def greedy_candidates(spark, d):
    return G.scan_motifs(T.contigs(spark, d), words(spark, d))


def _greedy(name: str, pick: str, seed: int = SEED, max_offset: int = 2) -> None:
    @query(name, sql=f"WITH {S.greedy(pick, seed, max_offset)} SELECT contig, idx, pos, len, token, kind FROM scan")
    def run(spark, d):
        return G.token_rows(G.greedy_tokenize(T.contigs(spark, d).drop("lang"), words(spark, d), pick=pick, seed=seed, max_offset=max_offset))


for _name, _pick, _seed, _offset in (("greedy_random", "random", SEED, 2), ("greedy_longest", "longest", SEED, 2), ("greedy_shortest", "shortest", SEED, 2), ("greedy_offset0", "longest", SEED, 0), ("greedy_offset1", "random", SEED, 1), ("greedy_seed1", "random", 1, 2), ("greedy_seed2", "random", 2, 2), ("greedy_seed3", "random", 3, 2)):
    _greedy(_name, _pick, _seed, _offset)


@query("greedy_emit", sql=f"WITH {S.greedy('random', SEED)}, e AS (SELECT contig, pos, len, token, kind FROM scan UNION ALL SELECT s.contig, p, 1, substr(x.seq, p + 1, 1), 'one' FROM scan s JOIN whole x ON s.contig = x.contig, LATERAL (SELECT unnest(range(s.entry, s.pos)) AS p)) SELECT contig, pos, len, token, kind FROM e")
def greedy_emit(spark, d):
    return G.token_rows(G.greedy_tokenize(T.contigs(spark, d), words(spark, d), seed=SEED, skip="emit")).drop("idx")


@query("greedy_chunked", f"WITH {S.greedy('random', SEED)}, c AS (SELECT *, entry // 4096 AS chunk_no FROM scan), n AS (SELECT contig, chunk_no::INT AS chunk_no, min(idx)::BIGINT AS token_offset, list({{'pos': pos::INT, 'len': len::INT, 'token': token, 'kind': kind}} ORDER BY idx) AS tokens FROM c GROUP BY contig, chunk_no) SELECT contig, chunk_no, token_offset, tokens FROM n")
def greedy_chunked(spark, d):
    chunks = T.chunks(T.contigs(spark, d), 4096)
    return G.greedy_chunked(chunks, words(spark, d), size=4096, seed=SEED).where(F.size("tokens") > 0)


@query("detokenize", sql=f"WITH {S.greedy('longest', SEED)} SELECT contig, string_agg(token, '' ORDER BY idx) AS joined, sum(len)::BIGINT AS emitted FROM scan GROUP BY contig")
def detokenize(spark, d):
    t = G.greedy_tokenize(T.contigs(spark, d), words(spark, d), pick="longest", seed=SEED).where("n_bases > 0")
    joined = G.detokenize(F.col("tokens"))
    return t.select("contig", joined.alias("joined"), F.length(joined).cast("long").alias("emitted"))


@query("tokens_to_ids", sql=f"WITH {S.greedy('random', SEED)}, {S.VOCAB.replace(S.MOTIFS + ', ', '')} SELECT contig, list(coalesce(v.token_id, u.token_id) ORDER BY idx) AS ids FROM scan s LEFT JOIN vocab v ON s.token = v.token, (SELECT token_id FROM vocab WHERE token = '[UNK]') u GROUP BY contig")
def tokens_to_ids(spark, d):
    from seqlex.operators.segments import to_ids

    tokens = G.greedy_tokenize(T.contigs(spark, d), words(spark, d), seed=SEED).where("n_bases > 0")
    return to_ids(tokens, motif_vocab(spark, d)).select("contig", "ids")


def token_summary(spark: SparkSession, d: str) -> DataFrame:
    """The flagship: whole documents through the dictionary, by language."""
    t = G.greedy_tokenize(T.contigs(spark, d), words(spark, d), seed=SEED)
    emitted = F.aggregate("tokens", F.lit(0), lambda acc, x: acc + x["len"])
    motif = F.size(F.filter("tokens", lambda x: x["kind"] == "motif"))
    return t.groupBy("lang").agg(F.sum("n_bases").alias("bases"), F.sum(F.size("tokens")).alias("tokens"), F.sum(emitted).alias("emitted"), F.sum(motif).alias("motif_tokens"))


query("token_summary", f"WITH {S.greedy('random', SEED)}, b AS (SELECT lang, sum(length(seq))::BIGINT AS bases FROM whole GROUP BY lang) SELECT w.lang, any_value(bases) AS bases, count(*) AS tokens, sum(len)::BIGINT AS emitted, count(*) FILTER (kind = 'motif') AS motif_tokens FROM scan s JOIN whole w ON s.contig = w.contig JOIN b ON b.lang = w.lang GROUP BY w.lang")(token_summary)
