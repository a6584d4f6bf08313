"""Near-duplicates by BagMinHash: weighted-Jaccard signatures of shingle multisets, banded, then verified exactly.

Signature. A shingle of multiplicity w owns the levels 1..w. The levels are cut into dyadic strips (0,1], (1,2], (2,4], ...;
each strip of each shingle carries one Poisson process over all signature places together, of a rate equal to its width
times the number of places. A point goes to one place and one level of the strip, and counts if that level is within w. A
place keeps its smallest point, so two documents agree on a place with a probability equal to their weighted Jaccard. Points
come in ascending order, and a process stops beyond the largest minimum of its document, so most stop after a point or two.

Candidates. Equal texts are one node from the start (64-bit hash). `rows` places make a band, `bands` bands a signature. In
each bucket every node is paired with the smallest (a star, not all pairs), and each pair is verified on the whole texts.
Jaccard distance is a metric, so with a verified ball around the centre: a node at similarity under 2t - 1 to the centre has
no link into the ball; nodes outside the ball are compared with each other, and with the ball where one of them is between
2t - 1 and t, in blocks of bounded rows and shingles. A pair of such nodes is passed over only if its shingles, counted in bins by hash, overlap too little
even when all of a bin could be shared: a bound from above, so no link between texts that share a bucket is lost. Two texts at similarity 0.8 share
no bucket with probability 7e-4, at 0.85 1e-5.

Groups are the connected components of the verified links, found by alternating star contractions on distributed tables. Where one bucket, text or component may hold
many rows, both sides of the join are written tables or fresh shuffles and nothing after it needs its partitioning, so that adaptive execution splits it.

Defined results: equal texts, the empty one included, are one group; a null text stands alone; a text of fewer than five words
is one shingle. Repeated rows with one id are members of one group like any equal texts. Only `doc_id` and `text` are read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import give_back, mix, slices, split_by, spool, utf8
from .shingles import multisets, overlap

BANDS, ROWS, THRESHOLD = 24, 6, 0.8
#: Rows and shingles of a block, on average; two blocks are compared at a time.
BLOCK, BLOCK_SHINGLES = 512, 1 << 19
#: Least and largest number of bins in which a text's shingles are counted, both powers of two.
FEW_BINS, MOST_BINS = 64, 8192

_STRIP = [np.uint64(int(x)) for x in np.random.default_rng(8).integers(1, 2**63, 64)]
_GAMMA = np.uint64(0x9E3779B97F4A7C15)


def signatures(row: np.ndarray, shingle: np.ndarray, count: np.ndarray, n: int, places: int) -> np.ndarray:
    """n x places smallest points, as float64; infinity in the rows without a shingle."""
    sig = np.full(n * places, np.inf)
    top = int(count.max()) if len(count) else 0
    parts, k = [], 0
    while (low := 0 if k == 0 else 1 << (k - 1)) < top:
        has = np.flatnonzero(count > low)
        parts.append((mix(shingle[has] ^ _STRIP[k]), row[has], count[has], np.full(len(has), low), np.full(len(has), max(1, low))))
        k += 1
    if not parts:
        return sig.reshape(n, places)
    state, doc, weight, low, width = (np.concatenate(x) for x in zip(*parts, strict=True))
    point, batch = np.zeros(len(state)), 1
    while len(state):
        steps = state[:, None] + _GAMMA * np.arange(1, batch + 1, dtype=np.uint64)
        r = mix(steps)
        gap = -np.log(((r >> np.uint64(11)).astype(np.float64) + 0.5) / 2.0**53) / (width * places)[:, None]
        gap[:, 0] += point
        x = np.cumsum(gap, axis=1)
        r = mix(r ^ _GAMMA)
        place = (r % np.uint64(places)).astype(np.int64)
        level = low[:, None] + 1 + ((r >> np.uint64(32)).astype(np.float64) * width[:, None] / 2.0**32).astype(np.int64)
        ok = level <= weight[:, None]
        np.minimum.at(sig, (doc[:, None] * places + place)[ok], x[ok])
        worst = sig.reshape(n, places).max(1)
        go = x[:, -1] < worst[doc]
        state, doc, weight, low, width, point = steps[go, -1], doc[go], weight[go], low[go], width[go], x[go, -1]
        batch = min(batch * 2, 64)
    return sig.reshape(n, places)


def _sign(bands: int, rows: int):
    places = bands * rows

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            offsets, data = utf8(batch["text"])
            for a, b in slices(offsets):
                for at in range(a, b, 2000):
                    end = min(at + 2000, b)
                    row, shingle, count = multisets(offsets[at : end + 1], data)
                    sig = mix(signatures(row, shingle, count, end - at, places).view(np.uint64))
                    band = np.zeros((end - at, bands), np.uint64)
                    for j in range(rows):
                        band = mix(band * _GAMMA + sig[:, j::rows] + np.arange(bands, dtype=np.uint64))
                    weight = np.bincount(row, count, end - at).astype(np.int64)
                    keys = pa.ListArray.from_arrays(pa.array(np.arange(0, (end - at + 1) * bands, bands), pa.int32()), pa.array(band.view(np.int64).ravel()))
                    yield pa.RecordBatch.from_arrays([*(batch[c].slice(at, end - at) for c in ("doc_id", "node")), pa.array(weight), keys], ["doc_id", "node", "weight", "keys"])
        give_back()

    return run


def bins_of(shingle: np.ndarray, count: np.ndarray) -> np.ndarray:
    """Counts of a multiset by the leading bits of its shingles, in twice as many bins as it has members or more (within bounds); none where a bin holds more than two
    bytes can say, so that nothing is concluded there."""
    bits = int(np.clip(np.ceil(np.log2(max(1, 2 * int(count.sum())))), np.log2(FEW_BINS), np.log2(MOST_BINS)))
    sums = np.bincount((shingle >> np.uint64(64 - bits)).astype(np.int64), count, 1 << bits)
    return sums.astype(np.uint16) if sums.max() < 1 << 16 else np.zeros(0, np.uint16)


def binned(texts: DataFrame) -> DataFrame:
    """(node, bins) of (node, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            offsets, data = utf8(batch["text"])
            for a, b in slices(offsets):
                row, shingle, count = multisets(offsets[a : b + 1], data)
                edge = np.searchsorted(row, np.arange(b - a + 1))
                bins = [bins_of(shingle[s:e], count[s:e]).tobytes() for s, e in zip(edge[:-1], edge[1:], strict=True)]
                yield pa.RecordBatch.from_arrays([batch["node"].slice(a, b - a), pa.array(bins, pa.binary())], ["node", "bins"])
        give_back()

    return texts.mapInArrow(run, "node long, bins binary")


class Bounds:
    """Upper bounds of the overlap of the multisets of some rows, from their bins."""

    def __init__(self, bins: list[bytes]) -> None:
        own = [np.frombuffer(b, np.uint16).astype(np.int32) for b in bins]
        self.size = np.array([len(x) for x in own])
        self.at = np.zeros(len(own), np.int64)
        self.levels: dict[int, np.ndarray] = {}
        for n in np.unique(self.size):
            rows = np.flatnonzero(self.size == n)
            self.at[rows] = np.arange(len(rows))
            self.levels[int(n)] = np.stack([own[i] for i in rows])
        self.coarse = np.stack([x.reshape(FEW_BINS, -1).sum(1) if len(x) else np.full(FEW_BINS, 1 << 24) for x in own]).astype(np.int32) if own else np.zeros((0, FEW_BINS), np.int32)

    def overlap(self, i: int, js: np.ndarray, enough: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(rows of js whose overlap with row i may be enough, its bound)."""
        bound = np.minimum(self.coarse[js], self.coarse[i]).sum(1).astype(np.float64)
        go = bound >= enough
        js, bound, enough = js[go], bound[go], enough[go]
        if self.size[i]:
            own = self.levels[int(self.size[i])][self.at[i]]
            for n in np.unique(self.size[js]):
                if n > FEW_BINS:
                    sel = np.flatnonzero(self.size[js] == n)
                    other, mine = self.levels[int(n)][self.at[js[sel]]], own
                    if n > len(own):
                        other = other.reshape(len(sel), len(own), -1).sum(2)
                    elif n < len(own):
                        mine = own.reshape(int(n), -1).sum(1)
                    bound[sel] = np.minimum(bound[sel], np.minimum(other, mine).sum(1))
            go = bound >= enough
            js, bound = js[go], bound[go]
        return js, bound


def verify(pairs: DataFrame, texts: DataFrame) -> DataFrame:
    """(a, b, similarity) of pairs (a, b) of nodes, by exact multiset overlap of their whole texts (node, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last: tuple = (None, None)
        for batch in batches:
            b_ids, scores = batch["b"].to_pylist(), np.zeros(batch.num_rows)
            offsets, data = utf8(batch["text_a"])
            others = batch["text_b"]
            for lo, hi in slices(offsets):
                row, shingle, count = multisets(offsets[lo : hi + 1], data)
                edge = np.searchsorted(row, np.arange(hi - lo + 1))
                for i in range(lo, hi):
                    if b_ids[i] != last[0]:
                        last = (b_ids[i], multisets(*utf8(others.slice(i, 1)))[1:])
                    s = slice(edge[i - lo], edge[i - lo + 1])
                    scores[i] = overlap((shingle[s], count[s]), last[1])
            yield pa.RecordBatch.from_arrays([batch["a"], batch["b"], pa.array(scores)], ["a", "b", "similarity"])

    left = texts.withColumnsRenamed({"node": "a", "text": "text_a"})
    right = texts.withColumnsRenamed({"node": "b", "text": "text_b"})
    return pairs.join(left, "a").join(right, "b").select("a", "b", "text_a", "text_b").mapInArrow(run, "a long, b long, similarity double")


def components(edges: DataFrame) -> DataFrame:
    """(node, label): for each node of the undirected edges (a, b) the smallest node of its component. Alternating large and small stars:
    each round links nodes to the smallest of their neighbourhood, until every tree is a star."""
    now = spool(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct(), "edges")
    while True:
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = spool(both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m")), "low")
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(low.select("u", F.col("m").alias("v"))).where("u <> v").distinct()
        after = spool(small, "edges")
        changed = after.join(now, ["u", "v"], "left_anti").limit(1).count() or now.join(after, ["u", "v"], "left_anti").limit(1).count()
        now = after
        if not changed:
            return now.select(F.col("u").alias("node"), F.col("v").alias("label"))


def _candidates(rows: pa.Table) -> Iterator[tuple[int, np.ndarray]]:
    """(i, js): row i of the first block and rows of the facing one that may be linked to it, the likeliest first: in different components, of near weights, and with
    bins that can overlap enough."""
    side, label = np.asarray(rows["side"]), np.asarray(rows["label"])
    weight, inside = np.asarray(rows["weight"]), np.asarray(rows["inside"])
    bounds = Bounds(rows["bins"].to_pylist())
    first, second = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
    same = bool(np.asarray(rows["same"])[0])
    share = THRESHOLD / (1 + THRESHOLD)
    for i in first:
        j = first[first > i] if same else second
        j = j[(label[j] != label[i]) & ~(inside[j] & inside[i])]
        j = j[np.minimum(weight[j], weight[i]) >= THRESHOLD * np.maximum(weight[j], weight[i])]
        if len(j):
            # Similarity s of weights x and y is an overlap of s / (1 + s) * (x + y).
            j, bound = bounds.overlap(int(i), j, share * (weight[j] + weight[i]) - 1e-6)
            yield int(i), j[np.argsort(-bound / (weight[j] + weight[i]), kind="stable")]


def _with_candidates(rows: pa.Table) -> pa.Table:
    """The rows of a pair of blocks that have a candidate at all."""
    keep = np.zeros(rows.num_rows, bool)
    for i, j in _candidates(rows):
        keep[j] = True
        keep[i] |= len(j) > 0
    return rows.filter(pa.array(keep))


def _block_links(rows: pa.Table) -> pa.Table:
    """Verified links of a pair of blocks that join its components: best agreement first, and none within a component that is joined already."""
    node, label = np.asarray(rows["node"]), np.asarray(rows["label"]).tolist()
    sets: dict[int, tuple] = {}
    parent: dict[int, int] = {}

    def root(x: int) -> int:
        while parent.setdefault(x, x) != x:
            parent[x] = x = parent[parent[x]]
        return x

    def multiset(i: int) -> tuple:
        if i not in sets:
            sets[i] = multisets(*utf8(rows["text"].slice(i, 1).combine_chunks()))[1:]
        return sets[i]

    out = []
    for i, js in _candidates(rows):
        for j in js.tolist():
            if root(label[i]) != root(label[j]) and (s := overlap(multiset(i), multiset(j))) >= THRESHOLD:
                parent[root(label[i])] = root(label[j])
                out.append((max(node[i], node[j]), min(node[i], node[j]), s))
    return pa.table({n: pa.array([x[k] for x in out], t) for k, (n, t) in enumerate((("a", pa.int64()), ("b", pa.int64()), ("similarity", pa.float64())))})


def remaining_links(members: DataFrame, centres: DataFrame, stars: DataFrame, labels: DataFrame, texts: DataFrame, threshold: float) -> DataFrame:
    """Verified links (a, b, similarity) between components of a bucket that its star did not settle: among the nodes outside the ball of the centre, and between them and the
    ball where one of them lies in the ring (2t-1 <= s < t) and in another component."""
    named = members.join(stars.withColumnsRenamed({"a": "node", "b": "centre"}), ["node", "centre"], "left")
    named = named.withColumn("similarity", F.when(F.col("node") == F.col("centre"), 1.0).otherwise(F.col("similarity")))
    found = labels.withColumnRenamed("label", "found")
    named = named.join(found, "node", "left").withColumn("label", F.coalesce("found", "node")).drop("found")
    outer = centres.join(labels.select(F.col("node").alias("centre"), F.col("label").alias("centre_label")), "centre", "left").select("bucket", F.coalesce("centre_label", "centre").alias("centre_label"))
    named = spool(named.join(outer, "bucket"), "named")
    inside = F.col("similarity") >= threshold
    ring = ~inside & (F.col("similarity") >= 2 * threshold - 1) & (F.col("label") != F.col("centre_label"))
    open_ = named.groupBy("bucket").agg(F.sum((~inside).cast("long")).alias("out"), F.max(ring.cast("int")).alias("ring"), F.count(F.lit(1)).alias("all"), F.sum(F.when(~inside, F.col("weight")).otherwise(0)).alias("out_weight"), F.sum("weight").alias("all_weight"))
    size = lambda c: F.when(F.col("ring") == 1, F.col(f"all{c}")).otherwise(F.col(f"out{c}"))
    open_ = open_.where("out > 0 and (out > 1 or ring = 1)").select("bucket", "ring", F.greatest(F.ceil(size("") / BLOCK), F.ceil(size("_weight") / BLOCK_SHINGLES)).cast("int").alias("blocks"))
    rows = named.join(spool(open_, "open"), "bucket").where(~inside | (F.col("ring") == 1)).select("bucket", "node", "label", inside.alias("inside"), "weight", "blocks", F.pmod(F.xxhash64("node", "bucket"), F.col("blocks")).cast("int").alias("block"))
    rows = spool(rows, "rest")
    bins = spool(binned(texts.join(rows.select("node").distinct(), "node", "left_semi")), "bins")
    rows = rows.join(bins, "node")
    facing = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other")
    dealt = rows.select("*", facing).select("bucket", F.least("block", "other").alias("b1"), F.greatest("block", "other").alias("b2"), (F.col("block") > F.col("other")).cast("int").alias("side"), (F.col("block") == F.col("other")).alias("same"), "node", "label", "inside", "weight", "bins")
    likely = dealt.groupBy("bucket", "b1", "b2").applyInArrow(_with_candidates, dealt.schema)
    return spool(likely, "likely").join(texts, "node").groupBy("bucket", "b1", "b2").applyInArrow(_block_links, "a long, b long, similarity double")


def classes(docs: DataFrame, *, bands: int = BANDS, rows: int = ROWS, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, class_id, class_size, representative (the group's smallest doc_id is its class id and representative)."""
    base = docs.select(F.col("doc_id").cast("long"), "text", F.xxhash64("text").alias("node"))
    signed = spool(base.where(F.col("text").isNotNull()).mapInArrow(_sign(bands, rows), "doc_id long, node long, weight long, keys array<long>"), "signed")
    nodes = spool(signed.where("weight > 0").select("node", "weight", "keys").dropDuplicates(["node"]), "nodes")
    spread = nodes.select("node", "weight", F.explode("keys").alias("bucket"))
    centres = spool(spread.groupBy("bucket").agg(F.min("node").alias("centre"), F.max("node").alias("last")).where("centre < last").drop("last"), "centres")
    members = spool(spread.join(centres, "bucket"), "members")
    pairs = spool(members.where("node <> centre").select(F.col("node").alias("a"), F.col("centre").alias("b")).distinct(), "pairs")
    wanted = spool(members.select("node").distinct(), "wanted")
    likely, _ = split_by(base.where(F.col("text").isNotNull()), F.col("node"), wanted, "node")
    texts = spool(likely.join(wanted, "node", "left_semi").select("node", "text").dropDuplicates(["node"]), "texts")
    stars = spool(verify(pairs, texts), "stars")
    labels = components(stars.where(F.col("similarity") >= threshold))
    more = spool(remaining_links(members, centres, stars, labels, texts, threshold), "more")
    if more.limit(1).count():
        # Components of components: the old stars and the new links.
        labels = components(labels.select(F.col("node").alias("a"), F.col("label").alias("b")).unionByName(more.select("a", "b")))
    # Rows are summed by text, texts by component; what a component comes to goes back the same way.
    by_text = signed.groupBy("node").agg(F.min("doc_id").alias("first"), F.count(F.lit(1)).alias("n"))
    by_text = spool(by_text.join(labels, "node", "left").withColumn("label", F.coalesce("label", "node")), "by_text")
    heads = spool(by_text.groupBy("label").agg(F.min("first").alias("class_id"), F.sum("n").alias("class_size")), "heads")
    by_class = spool(by_text.select("node", "label").join(heads, "label").drop("label"), "by_class")
    placed = signed.select("doc_id", "node").join(by_class, "node").select("doc_id", "class_id", "class_size")
    alone = docs.where(F.col("text").isNull()).select(F.col("doc_id").cast("long"), F.col("doc_id").cast("long").alias("class_id"), F.lit(1).cast("long").alias("class_size"))
    return placed.unionByName(alone).withColumn("representative", F.col("doc_id").eqNullSafe(F.col("class_id")))


def one_of_each(docs: DataFrame) -> DataFrame:
    """docs without the rows of a group but its representative; all columns stay. Of rows that repeat with the representative's
    id and text one stays. Rows without an id stay, as nothing names them."""
    found = spool(classes(docs), "classes")
    drop = spool(found.where("not representative").select(F.col("doc_id").alias("__gone")).distinct(), "gone")
    maybe, sure = split_by(docs, F.col("doc_id").cast("long"), drop, "__gone")
    kept = sure.unionByName(maybe.join(drop, maybe["doc_id"].cast("long") == F.col("__gone"), "left_anti"))
    twice = found.where("representative and doc_id is not null").groupBy("doc_id").count().where("count > 1").limit(1).count()
    return kept.where("doc_id is null").unionByName(kept.where("doc_id is not null").dropDuplicates(["doc_id"])) if twice else kept
