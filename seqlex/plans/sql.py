"""SQL of the shared projections, for the oracle."""

from __future__ import annotations

from seqlex.functions.bases import BASES, LETTERS


def to_bases(text: str) -> str:
    return f"regexp_replace(translate(regexp_replace({text}, '[ \t\r\n]', '', 'g'), '{LETTERS + LETTERS.upper()}', '{BASES * 2}'), '[^ACGT]', 'N', 'g')"


def revcomp(seq: str) -> str:
    return f"reverse(translate({seq}, 'ACGT', 'TGCA'))"


CONTIGS = f"contigs AS (SELECT doc_id AS contig, {to_bases('text')} AS seq, lang FROM documents)"
WHOLE = f"{CONTIGS}, whole AS (SELECT contig, seq, lang FROM contigs)"
PREFIXES = f"{CONTIGS}, prefixes AS (SELECT contig, substr(seq, 1, 300) AS seq, lang FROM contigs)"

MATRICES = """matrices AS (SELECT motif_id, width, family, list_transform(w, lambda r: list_transform(r, lambda x: CASE WHEN r[1] + r[2] + r[3] + r[4] > 0 THEN x / (r[1] + r[2] + r[3] + r[4]) ELSE 0.25 END)) AS rows FROM
 (SELECT vec_id AS motif_id, (5 + vec_id % 12)::INT AS width, label AS family, list_transform(range(0, 5 + vec_id % 12), lambda p: list_transform(range(1, 5), lambda j: greatest(embedding[4 * p + j]::DOUBLE, 0) * greatest(embedding[4 * p + j]::DOUBLE, 0))) AS w FROM embeddings WHERE vec_id < 879))"""


def marked(threshold: str) -> str:
    return f"array_to_string(list_transform(rows, lambda r: substr(CASE WHEN list_max(r) >= {threshold} THEN 'ACGT' ELSE 'acgt' END, list_position(r, list_max(r))::INT, 1)), '')"


TRIM = "regexp_replace({}, '^[acgt]+|[acgt]+$', '', 'g')"
CONSENSUS = f"{MATRICES}, consensus AS (SELECT motif_id, family, upper(s) AS seq FROM (SELECT motif_id, family, {TRIM.format(marked('0.5'))} AS s FROM matrices WHERE width <= 12) WHERE length(s) > 0)"
MOTIFS = f"{CONSENSUS}, motifs AS (SELECT seq, count(DISTINCT motif_id) AS n_sources FROM (SELECT motif_id, seq FROM consensus UNION ALL SELECT motif_id, {revcomp('seq')} FROM consensus) GROUP BY seq)"
VOCAB = f"""{MOTIFS}, vocab AS (SELECT (row_number() OVER (ORDER BY rank, token) - 1)::INT AS token_id, token, ['special', 'one', 'three', 'motif'][rank + 1] AS kind, length(token)::INT AS len FROM (SELECT token, min(rank) AS rank FROM (
 SELECT unnest(['[PAD]', '[UNK]', '[CLS]', '[SEP]', '[MASK]']) AS token, 0 AS rank UNION ALL SELECT unnest(['A', 'C', 'G', 'T', 'N']), 1 UNION ALL SELECT x.b || y.b || z.b, 2 FROM (SELECT unnest(['A', 'C', 'G', 'T']) AS b) x, (SELECT unnest(['A', 'C', 'G', 'T']) AS b) y, (SELECT unnest(['A', 'C', 'G', 'T']) AS b) z UNION ALL SELECT seq, 3 FROM motifs) GROUP BY token))"""


HITS = f"""{WHOLE}, {MOTIFS}, iv AS MATERIALIZED (SELECT contig, i AS start, i + n AS "end" FROM (SELECT contig, i, n, size, s[1 : n] AS s FROM (SELECT contig, length(seq) AS size, i, seq[i + 1 : i + 12] AS s FROM (SELECT contig, seq, unnest(range(0, length(seq))) AS i FROM whole)), (SELECT unnest(range(4, 13)) AS n)) h JOIN motifs m ON h.s = m.seq WHERE i + n <= size)"""
#: Doublings of a walk's steps: more than 65,536 steps of a contig are not followed.
DOUBLINGS = 17


def greedy(pick: str = "random", seed: int = 7, max_offset: int = 2, tag: str = "", base: str | None = None) -> str:
    """CTEs that end in `scan` (contig, entry, pos, len, token, kind, idx): the walk over whole contigs. The places that it visits are found by doubling: those within 2**k steps, and
    the jump of 2**k steps from each place, give those within 2**(k + 1). Names end in tag; base replaces the CTEs of contigs and motifs."""
    index = {"random": f"1 + (('0x' || substr(md5('{seed}|' || p.contig || '|' || p.i), 1, 8))::BIGINT % len(lens))", "longest": "len(lens)", "shortest": "1"}[pick]
    others = " ".join(f", lead(len, {o}) OVER w AS len{o}" for o in range(1, max_offset + 1))
    best = "greatest(len" + "".join(f", coalesce(len{o}, 0)" for o in range(1, max_offset + 1)) + ")" if max_offset else "len"
    offset = "CASE " + " ".join(f"WHEN {'len' if o == 0 else f'len{o}'} = {best} THEN {o}" for o in range(max_offset + 1)) + " END"
    parts = [f"{WHOLE}, {MOTIFS}" if base is None else base] if base != "" else []
    parts.append(f"places{tag} AS (SELECT contig, length(seq) AS size, i, seq[i + 1 : i + 12] AS s FROM (SELECT contig, seq, unnest(range(0, length(seq))) AS i FROM whole))")
    parts.append(f"hits{tag} AS (SELECT contig, i, list(n ORDER BY n) AS lens FROM (SELECT contig, i, n, s[1 : n] AS s, size FROM places{tag}, (SELECT unnest(range(4, 13)) AS n)) h JOIN motifs m ON h.s = m.seq WHERE i + n <= size GROUP BY contig, i)")
    three = "p.i + 3 <= p.size AND NOT contains(p.s[1 : 3], 'N')"
    parts.append(f"offer{tag} AS MATERIALIZED (SELECT p.contig, p.i, p.size, p.s, CASE WHEN lens IS NOT NULL THEN lens[{index}] WHEN {three} THEN 3 ELSE 1 END AS len, CASE WHEN lens IS NOT NULL THEN 'motif' WHEN {three} THEN 'three' ELSE 'one' END AS kind FROM places{tag} p LEFT JOIN hits{tag} h ON p.contig = h.contig AND p.i = h.i)")
    parts.append(f"near{tag} AS (SELECT *{others} FROM offer{tag} WINDOW w AS (PARTITION BY contig ORDER BY i))")
    parts.append(f"jump{tag} AS MATERIALIZED (SELECT contig, size, i, i + {offset} AS pos, i + {offset} + {best} AS next FROM near{tag})")
    parts.append(f"step{tag}_0 AS MATERIALIZED (SELECT contig, i, next AS j FROM jump{tag} WHERE next < size)")
    parts.append(f"walk{tag}_0 AS (SELECT contig, 0::BIGINT AS i FROM whole WHERE length(seq) > 0)")
    for k in range(DOUBLINGS):
        parts.append(f"walk{tag}_{k + 1} AS MATERIALIZED (SELECT contig, i FROM walk{tag}_{k} UNION ALL SELECT w.contig, s.j FROM walk{tag}_{k} w JOIN step{tag}_{k} s ON w.contig = s.contig AND w.i = s.i)")
        if k < DOUBLINGS - 1:
            parts.append(f"step{tag}_{k + 1} AS MATERIALIZED (SELECT a.contig, a.i, b.j FROM step{tag}_{k} a JOIN step{tag}_{k} b ON a.contig = b.contig AND a.j = b.i)")
    parts.append(f"scan{tag} AS MATERIALIZED (SELECT w.contig, w.i AS entry, j.pos, o.len, o.s[1 : o.len] AS token, o.kind, row_number() OVER (PARTITION BY w.contig ORDER BY w.i) - 1 AS idx FROM walk{tag}_{DOUBLINGS} w JOIN jump{tag} j ON w.contig = j.contig AND w.i = j.i JOIN offer{tag} o ON o.contig = w.contig AND o.i = j.pos)")
    return ", ".join(parts)
