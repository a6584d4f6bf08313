"""Exact top-k inner products over norm-sorted vectors, pruned by SVD-rotated partial sums.

Components become integers floor(256 x), so scores are exact. Vectors of a partition are handled by descending length, in
blocks. For a query with a k-th best score t so far, a block whose longest vector cannot reach t by Cauchy-Schwarz ends the
query's walk; within a block the inner product over the leading rotated coordinates plus the product of the two residual
lengths bounds each score from above, and only pairs whose bound reaches t are scored exactly, in integers. The first t comes
from the longest `HEAD` vectors of the table. Rotation and head only steer the pruning; results do not depend on them.

The rotation is the SVD of a bounded sample (`SAMPLE` rows). Queries travel in batches of `QUERIES` at most, so each broadcast has a fixed
bound; vectors are never shuffled, only k scores of a query from each partition.

Defined results: rows with a null id, a null vector, or null or non-finite components take no part, nor does a component whose 256-fold is beyond a
double. Products that doubles can't hold exactly are summed as whole numbers of any size; a score beyond a long is the nearest long. Shorter vectors count as
filled up with zeros. Rows repeated with one id count once, at their best score, and never as their own query's partner. Empty
tables give no rows. Only the id and the vector are read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

SAMPLE, HEAD, QUERIES, BLOCK = 4096, 1024, 8192, 2048
#: Sums of products below this are exact in doubles.
EXACT = 2.0**52
#: Components from here on have squares that may leave the range of a double; such vectors are never pruned.
WILD = 1e140
LEAST, MOST = -(2**63), 2**63 - 1


def matrix(ids: pa.Array, vectors: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(ids, integer vectors as float64) of the rows that take part."""
    there = pc.and_(pc.is_valid(ids), pc.is_valid(vectors))
    ids, vectors = ids.filter(there), vectors.filter(there)
    if not len(ids):
        return np.zeros(0, np.int64), np.zeros((0, 0))
    size = np.asarray(pc.list_value_length(vectors), np.int64)
    # A null component reads as not a number.
    flat = vectors.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    if (size == size[0]).all():
        out = flat.reshape(len(size), size[0])
    else:
        out = np.zeros((len(size), size.max()))
        row = np.repeat(np.arange(len(size)), size)
        out[row, np.arange(len(flat)) - np.repeat(np.cumsum(size) - size, size)] = flat
    with np.errstate(over="ignore"):
        out = np.floor(256 * out)
    ok = np.isfinite(out).all(1)
    return ids.to_numpy(zero_copy_only=False).astype(np.int64)[ok], out[ok]


def widen(m: np.ndarray, width: int) -> np.ndarray:
    return np.pad(m, ((0, 0), (0, max(0, width - m.shape[1]))))


def exact_scores(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Row by row inner products of integer-valued matrices, as int64."""
    if not len(a):
        return np.zeros(0, np.int64)
    if float(np.abs(a).max(initial=0)) * float(np.abs(b).max(initial=0)) * max(1, a.shape[1]) < EXACT:
        return np.einsum("ij,ij->i", a, b).astype(np.int64)
    sums = (sum(int(x) * int(y) for x, y in zip(p, q, strict=True)) for p, q in zip(a.tolist(), b.tolist(), strict=True))
    return np.array([max(LEAST, min(MOST, s)) for s in sums], np.int64)


def is_wild(m: np.ndarray) -> np.ndarray:
    return np.abs(m).max(1, initial=0) >= WILD


def lengths(m: np.ndarray) -> np.ndarray:
    """Euclidean lengths; infinite for wild rows."""
    return np.where(is_wild(m), np.inf, np.linalg.norm(np.where(is_wild(m)[:, None], 0.0, m), axis=1))


def best(ids: np.ndarray, scores: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """The k best (id, score) of different ids, ties to the smaller id."""
    order = np.lexsort((ids, ~scores))
    _, first = np.unique(ids[order], return_index=True)
    keep = order[np.sort(first)[:k]]
    return ids[keep], scores[keep]


class Search:
    """Queries of one batch against vectors that arrive in parts."""

    def __init__(self, ids: np.ndarray, queries: np.ndarray, rotation: np.ndarray, k: int) -> None:
        self.ids, self.k = ids, k
        width = len(rotation)
        self.queries, self.rotation = widen(queries, width), rotation
        self.lead = max(1, width // 4)
        self.wild = is_wild(self.queries)
        turned = np.where(self.wild[:, None], 0.0, self.queries) @ rotation
        self.turned, self.rest = turned[:, : self.lead], np.linalg.norm(turned[:, self.lead :], axis=1)
        self.length = lengths(self.queries)
        self.found: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        self.floor = np.full(len(ids), -np.inf)

    def offer(self, ids: np.ndarray, vectors: np.ndarray) -> None:
        vectors = widen(vectors, len(self.rotation))
        order = np.argsort(-lengths(vectors), kind="stable")
        ids, vectors = ids[order], vectors[order]
        length, wild = lengths(vectors), is_wild(vectors)
        turned = np.where(wild[:, None], 0.0, vectors) @ self.rotation
        rest = np.linalg.norm(turned[:, self.lead :], axis=1)
        active = np.arange(len(self.ids))
        for a in range(0, len(ids), BLOCK):
            b = slice(a, a + BLOCK)
            # A wild vector or query can reach any score; nothing is concluded from its length.
            reach = np.full(len(active), np.inf)
            tame = ~self.wild[active] & ~wild[a]
            reach[tame] = self.length[active[tame]] * length[a] * (1 + 1e-9) + 0.5
            active = active[reach >= self.floor[active]]
            for at in range(0, len(active), 512):
                q = active[at : at + 512]
                bound = self.turned[q] @ turned[b, : self.lead].T + np.outer(self.rest[q], rest[b])
                bound += np.where(self.wild[q], np.inf, 1e-9 * np.where(self.wild[q], 0.0, self.length[q]) * (0.0 if wild[a] else length[a]) + 0.5)[:, None]
                if wild[a]:
                    # The block's longest tame vector is not known here; the lengths of its own vectors bound the rounding.
                    own = np.where(wild[b], 0.0, length[b])
                    bound += 1e-9 * np.where(self.wild[q], 0.0, self.length[q])[:, None] * own
                    bound[:, wild[b]] = np.inf
                hit, at_c = np.nonzero((bound >= self.floor[q, None]) & (ids[b][None, :] != self.ids[q, None]))
                cut = np.searchsorted(hit, np.arange(len(q) + 1))
                for r in np.flatnonzero(np.diff(cut)):
                    i, c = q[r], a + at_c[cut[r] : cut[r + 1]]
                    got_ids, got = ids[c], exact_scores(np.broadcast_to(self.queries[i], (len(c), vectors.shape[1])), vectors[c])
                    if i in self.found:
                        got_ids, got = np.concatenate([self.found[i][0], got_ids]), np.concatenate([self.found[i][1], got])
                    self.found[i] = best(got_ids, got, self.k)
                    if len(self.found[i][1]) == self.k:
                        self.floor[i] = max(self.floor[i], self.found[i][1][-1])


def top_k(frame: DataFrame, *, id_col: str = "vec_id", vector_col: str = "embedding", k: int = 5, every: int = 50) -> DataFrame:
    """(query_id, rank, vec_id, score): for each row whose id `every` divides, the k best of the other rows."""
    spark = frame.sparkSession
    rows = frame.select(F.col(id_col).cast("long").alias("id"), F.col(vector_col).cast("array<double>").alias("v")).where("id is not null and v is not null")
    width = rows.agg(F.max(F.size("v"))).first()[0]
    out = "query_id long, vec_id long, score long"
    if not width:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    sample = rows.limit(SAMPLE).toArrow()
    _, some = matrix(sample["id"].combine_chunks(), sample["v"].combine_chunks())
    # The right singular vectors, by descending singular value.
    some = widen(some[~is_wild(some)], width)
    rotation = np.linalg.eigh(some.T @ some)[1][:, ::-1].copy()

    def longest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, kept = np.zeros(0, np.int64), np.zeros((0, width))
        for batch in batches:
            new_ids, new = matrix(batch["id"], batch["v"])
            ids, kept = np.concatenate([ids, new_ids]), np.concatenate([kept, widen(new, width)])
            order = np.argsort(-lengths(kept), kind="stable")[:HEAD]
            ids, kept = ids[order], kept[order]
        yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(lengths(kept)), pa.array(list(kept), pa.list_(pa.float64()))], ["id", "norm", "v"])

    head = rows.mapInArrow(longest, "id long, norm double, v array<double>").orderBy(F.desc("norm")).limit(HEAD).toArrow()
    head_ids = np.array(head["id"].to_pylist(), np.int64)
    head_rows = np.array(head["v"].to_pylist(), np.float64).reshape(len(head_ids), width)
    asked = rows.where((F.col("id") % every) == 0)
    batches_ = -(-asked.count() // QUERIES)
    parts = []
    for b in range(batches_):
        got = asked.where(F.pmod(F.xxhash64("id"), F.lit(batches_)) == b).toArrow()
        ids, queries = matrix(got["id"].combine_chunks(), got["v"].combine_chunks())
        ids, first = np.unique(ids, return_index=True)
        if not len(ids):
            continue
        start = Search(ids, queries[first], rotation, k)
        start.offer(head_ids, head_rows)
        shared = spark.sparkContext.broadcast((ids, queries[first], rotation, start.floor))

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            ids, queries, rotation, floor = shared.value
            search = Search(ids, queries, rotation, k)
            search.floor = floor.copy()
            for batch in batches:
                search.offer(*matrix(batch["id"], batch["v"]))
            flat = [(ids[i], v, s) for i, (vs, ss) in search.found.items() for v, s in zip(vs, ss, strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array([x[j] for x in flat], pa.int64()) for j in range(3)], ["query_id", "vec_id", "score"])

        parts.append(rows.mapInArrow(run, out))
    if not parts:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    found = parts[0]
    for part in parts[1:]:
        found = found.unionByName(part)
    found = found.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def oracle(k: int = 5, every: int = 50) -> str:
    return f"""
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)) AS e FROM embeddings WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id, list_dot_product(q.e, c.e)::BIGINT AS score FROM v q JOIN v c ON q.vec_id % {every} = 0 AND q.vec_id <> c.vec_id)
SELECT query_id, rank::INT AS rank, vec_id, score FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s) WHERE rank <= {k}"""
