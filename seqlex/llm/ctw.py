"""Language-model scoring by context-tree weighting over bytes, beside a unigram word base.

Counts of all (DEPTH+1)-byte grams of the training texts (A-Z lower-cased, DEPTH zero bytes before a text, one after it as its end) are
gathered from every training document, partly summed in the workers and then by aggregation. A byte is eight binary decisions, so
each context of 0 to DEPTH bytes has up to 255 nodes with Krichevsky-Trofimov estimates. From the leaves up, a node's
weighted block probability is the even mixture of its own estimate and the product of its extensions; the posterior share of its
own estimate then weighs the prediction: p(d) = a(d) KT(d) + (1 - a(d)) p(d+1), from the deepest context that is
known up to the empty one. A text's score is the sum of the log10 probabilities of its bytes and its end; `bits_per_byte` is the code length.

Every node of every depth is kept. The grams of all texts, with their training counts (0 for one that only other texts have), are dealt out by the
last SPLIT bytes of their context; a part builds its subtrees from depth SPLIT down by itself and gives for each gram the prediction of its byte's bits up
to there, and for each node of depth SPLIT - 1 the sum over its extensions. The shallower nodes (at most 255 * 256) are
completed on the driver. The log-probabilities so known are a table; the grams that all texts have most often (at most `CAPACITY`) are looked up in the
workers, as a cache, all others by a join, pre-summed for each document. The cache has no say in the results.

The base takes word counts over the whole vocabulary: the words that all texts have most often (at most `HEAD_WORDS`, chosen by a count threshold from a
histogram) are looked up in the workers, all others by a join on their hash, pre-summed for each document. As held-out texts count for what is looked up, no
key of either join is frequent.

Defined results: a null text is an empty one (its one token is the end). Repeated rows each count and are each scored. Without
training documents N is 0 and every estimate is the prior. Only `doc_id` and `text` are read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import give_back, id_crc, least_count, slices, spool, utf8
from .shingles import word_hashes

DEPTH, CAPACITY, HEAD_WORDS = 5, 1 << 19, 1 << 18
#: Bytes of context by which grams are dealt out, and grams of which subtrees are built at once (those of one such context stay together).
SPLIT, BUILT = 2, 1 << 17
#: Bytes that are handled at once, and grams that a worker holds before it counts them and hands them on.
SLICE, HELD = 2 << 20, 6 << 20

_lower = np.arange(256, dtype=np.uint8)
_lower[65:91] += 32


def grams(offsets: np.ndarray, data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(gram, row) at each byte and end of the rows: the byte in the low eight bits, its context above it, older bytes higher."""
    base = int(offsets[0])
    own = _lower[data[base : int(offsets[-1])]]
    cut = np.asarray(offsets) - base
    n = len(cut) - 1
    gap = DEPTH + 1
    size = np.diff(cut)
    # Each row stands after DEPTH zeros and before one.
    start = cut[:-1] + np.arange(n) * gap + DEPTH
    buffer = np.zeros(len(own) + n * gap, np.uint8)
    row_of = np.repeat(np.arange(n), size)
    buffer[np.arange(len(own)) + (row_of + 1) * gap - 1] = own
    out = np.zeros(len(buffer) - DEPTH, np.uint64) if len(buffer) else np.zeros(0, np.uint64)
    for d in range(DEPTH + 1):
        out = out << np.uint64(8) | buffer[d : d + len(out)]
    row = np.repeat(np.arange(n), size + 1)
    at = np.arange(len(row)) + np.repeat(start - np.concatenate([[0], np.cumsum(size + 1)[:-1]]), size + 1) - DEPTH
    return out[at], row


def _summed(keys: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    if not len(keys):
        return keys, counts
    order = np.argsort(keys, kind="stable")
    keys, counts = keys[order], counts[order]
    first = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))
    return keys[first], np.add.reduceat(counts, first)


def gram_counts(base: DataFrame) -> DataFrame:
    """(gram, n, m) over all texts; n counts those that are not held out, m all."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []

        def out() -> pa.RecordBatch:
            # A gram has 48 bits; whether it counts for training is the lowest bit of what is sorted.
            flat = np.sort(np.concatenate([*held, np.zeros(0, np.uint64)]))
            held.clear()
            first = np.flatnonzero(np.concatenate([[True], flat[1:] != flat[:-1]])) if len(flat) else np.zeros(0, np.int64)
            keys, times = flat[first], np.diff(np.append(first, len(flat)))
            g = keys >> np.uint64(1)
            cut = np.flatnonzero(np.concatenate([[True], g[1:] != g[:-1]])) if len(g) else np.zeros(0, np.int64)
            n, m = (np.add.reduceat(x, cut) if len(cut) else np.zeros(0, np.int64) for x in (times * (keys & np.uint64(1)).astype(np.int64), times))
            return pa.RecordBatch.from_arrays([pa.array(g[cut].view(np.int64)), pa.array(n), pa.array(m)], ["gram", "n", "m"])

        for batch in batches:
            offsets, data = utf8(batch["text"])
            train = ~np.asarray(batch["held_out"].to_numpy(zero_copy_only=False), bool)
            for a, b in slices(offsets, SLICE):
                g, row = grams(offsets[a : b + 1], data)
                held.append(g << np.uint64(1) | train[a:b][row].astype(np.uint64))
                if sum(map(len, held)) > HELD:
                    yield out()
        yield out()

    return base.select("text", "held_out").mapInArrow(run, "gram long, n long, m long").groupBy("gram").agg(F.sum("n").alias("n"), F.sum("m").alias("m"))


def _often(table: DataFrame, key: str, value: str, capacity: int) -> tuple[np.ndarray, np.ndarray, int]:
    """(keys, values, least): rows of the table (key, value, m) of the highest m, at most capacity of them, by key; and the least m among them."""
    least = least_count(table, "m", capacity)
    got = table.where(F.col("m") >= least).select(key, value).toArrow()
    keys, values = np.asarray(got[key]).astype(np.int64).view(np.uint64), np.asarray(got[value])
    order = np.argsort(keys)
    return keys[order], values[order], least


def _log_kt(zeros: np.ndarray, ones: np.ndarray) -> np.ndarray:
    """Natural log of the Krichevsky-Trofimov block probability, by a table of log-gamma and its asymptotic form beyond."""
    return _lgamma(zeros + 0.5) + _lgamma(ones + 0.5) - _lgamma(zeros + ones + 1.0) - math.log(math.pi)


def _lgamma(x: np.ndarray) -> np.ndarray:
    shift = np.maximum(0, 8 - np.floor(x)).astype(int)
    y, low = np.asarray(x, float).copy(), np.zeros(len(x))
    for k in range(8):
        has = shift > k
        low[has] += np.log(y[has])
        y[has] += 1
    return (y - 0.5) * np.log(y) - y + 0.5 * math.log(2 * math.pi) + 1 / (12 * y) - 1 / (360 * y**3) + 1 / (1260 * y**5) - low


class Tree:
    """Nodes of depth `low` and on, as sorted keys (context << 8 | path), with the share of their own estimate and its probability of a one. `below` has the
    nodes' extensions beyond the last of levels, if there are any: keys, zeros, ones and log weights. `top` has the same of depth `low`."""

    def __init__(self, levels: list[tuple[np.ndarray, np.ndarray]], low: int = 0, below: tuple | None = None) -> None:
        self.low = low
        self.keys: list[np.ndarray] = []
        self.own: list[np.ndarray] = []
        self.one: list[np.ndarray] = []
        for d in range(low + len(levels) - 1, low - 1, -1):
            keys, zeros, ones = self._nodes(*levels[d - low])
            own_log = _log_kt(zeros, ones)
            weighted, share = own_log.copy(), np.ones(len(keys))
            if below is not None and len(below[0]):
                child_keys, child_zeros, child_ones, child_log = below
                mask = np.uint64((1 << (8 * d + 8)) - 1)
                at = np.searchsorted(keys, child_keys & mask)
                known = np.bincount(at, minlength=len(keys)) > 0
                extended = np.bincount(at, child_log, len(keys))
                # Extensions that a bound left out count as one pooled extension.
                rest0 = zeros - np.bincount(at, child_zeros, len(keys))
                rest1 = ones - np.bincount(at, child_ones, len(keys))
                pooled = (rest0 + rest1) > 0
                extended[pooled] += _log_kt(np.maximum(rest0[pooled], 0), np.maximum(rest1[pooled], 0))
                both = np.logaddexp(own_log, extended) - math.log(2)
                weighted = np.where(known, both, own_log)
                share = np.where(known, np.exp(np.minimum(0, own_log - math.log(2) - both)), 1.0)
            self.keys.insert(0, keys)
            self.own.insert(0, share.astype(np.float32))
            self.one.insert(0, ((ones + 0.5) / (zeros + ones + 1.0)).astype(np.float32))
            below = (keys, zeros, ones, weighted)
        self.top = below

    @staticmethod
    def _nodes(grams_: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Sums of each path length by themselves: the grams are sorted, so are their keys, and only the sums are held together."""
        context, byte = grams_ >> np.uint64(8), grams_ & np.uint64(255)
        parts = []
        for k in range(8 if len(grams_) else 0):
            key = context << np.uint64(8) | np.uint64(1 << k) | byte >> np.uint64(8 - k)
            one = (byte >> np.uint64(7 - k) & np.uint64(1)).astype(bool)
            first = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
            parts.append((key[first], np.add.reduceat(np.where(one, 0, counts), first), np.add.reduceat(np.where(one, counts, 0), first)))
        if not parts:
            return grams_[:0], np.zeros(0), np.zeros(0)
        keys, zeros, ones = (np.concatenate(x) for x in zip(*parts, strict=True))
        order = np.argsort(keys)
        return keys[order], zeros[order].astype(float), ones[order].astype(float)

    def bits(self, grams_: np.ndarray, p: np.ndarray | None = None) -> np.ndarray:
        """Probabilities of the eight bits of each gram's byte after its context, by the nodes of this tree; p has those of the depths beyond."""
        p = np.full((8, len(grams_)), 0.5) if p is None else p.copy()
        byte = grams_ & np.uint64(255)
        for k in range(8):
            path = np.uint64(1 << k) | byte >> np.uint64(8 - k)
            one = (byte >> np.uint64(7 - k) & np.uint64(1)).astype(bool)
            for d in range(len(self.keys) - 1, -1, -1):
                keys = self.keys[d]
                if not len(keys):
                    continue
                want = (grams_ & np.uint64((1 << (8 * (d + self.low) + 8)) - 1)) & ~np.uint64(255) | path
                at = np.minimum(np.searchsorted(keys, want), len(keys) - 1)
                found = keys[at] == want
                share, own = self.own[d][at], self.one[d][at]
                p[k] = np.where(found, share * np.where(one, own, 1 - own) + (1 - share) * p[k], p[k])
        return p

    def log10(self, grams_: np.ndarray) -> np.ndarray:
        """log10 probability of each gram's byte after its context."""
        return np.log10(self.bits(grams_)).sum(0)


def _levels(grams_: np.ndarray, counts: np.ndarray, depths: range) -> list[tuple[np.ndarray, np.ndarray]]:
    """Sums of the grams' counts by the gram's part of each depth."""
    return [_summed(grams_ & np.uint64((1 << (8 * d + 8)) - 1), counts) for d in depths]


def subtrees(counts: DataFrame) -> DataFrame:
    """(gram, m, bits, zeros, ones, log): for each gram its bits' probabilities by depths SPLIT and on; rows without bits have sums over the extensions of a
    node of depth SPLIT - 1, to be summed up. Rows come dealt out and sorted by the last SPLIT bytes of their context."""
    above = np.uint64((1 << (8 * SPLIT)) - 1)
    shape = ["gram", "m", "bits", "zeros", "ones", "log"]
    none = lambda n, kind: pa.nulls(n, kind)

    def build(g: np.ndarray, n: np.ndarray, m: np.ndarray) -> Iterator[pa.RecordBatch]:
        seen = n > 0
        tree = Tree(_levels(g[seen], n[seen], range(SPLIT, DEPTH + 1)), SPLIT)
        p = tree.bits(g).astype(np.float32)
        bits = pa.ListArray.from_arrays(pa.array(np.arange(0, 8 * len(g) + 1, 8, dtype=np.int32)), pa.array(np.ascontiguousarray(p.T).ravel()))
        yield pa.RecordBatch.from_arrays([pa.array(g.view(np.int64)), pa.array(m), bits, *(none(len(g), pa.float64()) for _ in range(3))], shape)
        keys, zeros, ones, log = tree.top
        if len(keys):
            up, at = np.unique(keys & above, return_inverse=True)
            sums = [pa.array(np.bincount(at, x, len(up))) for x in (zeros, ones, log)]
            yield pa.RecordBatch.from_arrays([pa.array(up.view(np.int64)), none(len(up), pa.int64()), none(len(up), bits.type), *sums], shape)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, ...]] = []
        for batch in batches:
            held.append((np.asarray(batch["gram"]).astype(np.int64).view(np.uint64), *(np.asarray(batch[c]).astype(np.int64) for c in "nm")))
            if sum(len(x[0]) for x in held) < BUILT:
                continue
            g, n, m = (np.concatenate(x) for x in zip(*held, strict=True))
            # The last context may go on in the next batch.
            own = g >> np.uint64(8) & above
            cut = int(np.flatnonzero(own != own[-1])[-1]) + 1 if (own != own[-1]).any() else 0
            if cut:
                yield from build(g[:cut], n[:cut], m[:cut])
            held = [(g[cut:], n[cut:], m[cut:])]
        if held:
            yield from build(*(np.concatenate(x) for x in zip(*held, strict=True)))
        give_back()

    key = F.shiftright("gram", 8).bitwiseAND(F.lit(int(above)))
    dealt = counts.withColumn("__key", key).repartition("__key").sortWithinPartitions("__key").drop("__key")
    return dealt.mapInArrow(run, "gram long, m long, bits array<float>, zeros double, ones double, log double")


def fit(base: DataFrame) -> DataFrame:
    """(gram, m, log): the log10 probability of every gram of all texts, from the training texts' counts, and its number in all texts."""
    counts = spool(gram_counts(base), "grams")
    parts = spool(subtrees(counts), "subtrees")
    sums = parts.where("bits is null").groupBy("gram").agg(F.sum("zeros").alias("zeros"), F.sum("ones").alias("ones"), F.sum("log").alias("log")).toArrow()
    keys = np.asarray(sums["gram"]).astype(np.int64).view(np.uint64)
    order = np.argsort(keys)
    below = keys[order], *(np.asarray(sums[c]).astype(float)[order] for c in ("zeros", "ones", "log"))
    mask = (1 << (8 * SPLIT)) - 1
    short = counts.where("n > 0").groupBy(F.col("gram").bitwiseAND(F.lit(mask)).alias("gram")).agg(F.sum("n").alias("n")).toArrow()
    g, n = np.asarray(short["gram"]).astype(np.int64).view(np.uint64), np.asarray(short["n"]).astype(np.int64)
    shared = base.sparkSession.sparkContext.broadcast(Tree(_levels(g, n, range(SPLIT)), 0, below))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            p = np.asarray(batch["bits"].flatten()).astype(float).reshape(-1, 8).T
            log = np.log10(shared.value.bits(np.asarray(batch["gram"]).astype(np.int64).view(np.uint64), p)).sum(0)
            yield pa.RecordBatch.from_arrays([batch["gram"], batch["m"], pa.array(log)], ["gram", "m", "log"])

    return spool(parts.where("bits is not null").select("gram", "m", "bits").mapInArrow(run, "gram long, m long, log double"), "predictions")


class Lookup:
    """Values by key in an open-addressed table a quarter full, for whole arrays of keys at once."""

    EMPTY = np.uint64(2**64 - 1)

    def __init__(self, keys: np.ndarray, values: np.ndarray) -> None:
        bits = max(4, int(4 * len(keys)).bit_length())
        self.shift, self.mask = np.uint64(64 - bits), np.int64((1 << bits) - 1)
        self.keys, self.at = np.full(1 << bits, self.EMPTY, np.uint64), np.zeros(1 << bits, np.int32)
        self.values = values
        left, slot = np.flatnonzero(keys != self.EMPTY), self._slot(keys)
        while len(left):
            # Of the keys that want a free slot the first takes it; the others try the next one.
            free = left[self.keys[slot[left]] == self.EMPTY]
            _, first = np.unique(slot[free], return_index=True)
            won = free[first]
            self.keys[slot[won]], self.at[slot[won]] = keys[won], won
            left = left[self.keys[slot[left]] != keys[left]]
            slot[left] = slot[left] + 1 & self.mask

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return (keys * np.uint64(0x9E3779B97F4A7C15) >> self.shift).astype(np.int64)

    def find(self, keys: np.ndarray) -> np.ndarray:
        """The place of each key among the values, or -1."""
        slot = self._slot(keys)
        got = self.keys[slot]
        out = np.where(got == keys, self.at[slot], -1)
        left = np.flatnonzero((got != keys) & (got != self.EMPTY))
        while len(left):
            slot[left] = slot[left] + 1 & self.mask
            got = self.keys[slot[left]]
            hit = got == keys[left]
            out[left[hit]] = self.at[slot[left[hit]]]
            left = left[~hit & (got != self.EMPTY)]
        return np.where(keys == self.EMPTY, -1, out)


def _rest(row: np.ndarray, key: np.ndarray, n: int) -> list[pa.Array]:
    """Different keys of each of n rows and how often they occur there, as two list columns."""
    if n <= 1 << 16 and len(key) and int(key.max()) < 1 << 48:
        both = np.sort(row.astype(np.uint64) << np.uint64(48) | key)
        r, t = (both >> np.uint64(48)).astype(np.int64), both & np.uint64((1 << 48) - 1)
    else:
        order = np.lexsort((key, row))
        r, t = row[order], key[order]
    first = np.flatnonzero(np.concatenate([[True], (r[1:] != r[:-1]) | (t[1:] != t[:-1])])) if len(r) else np.zeros(0, np.int64)
    times = np.diff(np.append(first, len(r)))
    ends = np.searchsorted(r[first], np.arange(n + 1)).astype(np.int32)
    return [pa.ListArray.from_arrays(pa.array(ends), pa.array(x)) for x in (t[first].view(np.int64), times.astype(np.int64))]


def word_counts(base: DataFrame) -> DataFrame:
    """(h, c, m): occurrences of each word in the texts that are not held out, and in all."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            offsets, data = utf8(batch["text"])
            train = ~np.asarray(batch["held_out"].to_numpy(zero_copy_only=False), bool)
            for a, b in slices(offsets, SLICE):
                row, h, _ = words(offsets[a : b + 1], data)
                h, at, n = np.unique(h, return_inverse=True, return_counts=True)
                c = np.bincount(at, train[a:b][row], len(h)).astype(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(c), pa.array(n, pa.int64())], ["h", "c", "m"])

    return base.select("text", "held_out").mapInArrow(run, "h long, c long, m long").groupBy("h").agg(F.sum("c").alias("c"), F.sum("m").alias("m"))


def words(offsets: np.ndarray, data: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, hash, words of each row), A-Z in lower case."""
    base = int(offsets[0])
    cut = np.asarray(offsets) - base
    spaced = np.insert(data[base : int(offsets[-1])], cut[:-1], 32)
    start, h = word_hashes(spaced)
    row = np.searchsorted(cut + np.arange(len(cut)), start, "right") - 1
    return row, h, np.bincount(row, minlength=len(cut) - 1)


def score(docs: DataFrame, *, fold: int = 5, held: int = 1) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score, bits_per_byte for each document."""
    sc = docs.sparkSession.sparkContext
    base = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", (id_crc("doc_id", fold) == held).alias("held_out"))
    vocabulary = spool(word_counts(base), "words")
    sums = vocabulary.agg(F.sum("c"), F.count_if(F.col("c") > 0)).first()
    ends = base.where("not held_out").count()
    total, distinct = (sums[0] or 0) + ends, sums[1] + (ends > 0)
    floor = total + 0.5 * (distinct + 1)
    head_h, head_c, least = _often(vocabulary, "h", "c", HEAD_WORDS)
    predictions = fit(base)
    head_g, head_p, least_gram = _often(predictions, "gram", "log", CAPACITY)
    model = sc.broadcast((Lookup(head_g, head_p.astype(float)), Lookup(head_h, np.log10((head_c.astype(np.int64) + 0.5) / floor)), head_c.astype(np.int64) > 0))
    end_log = math.log10((ends + 0.5) / floor) if floor else 0.0

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, head, head_seen = model.value
        for batch in batches:
            offsets, data = utf8(batch["text"])
            for a, b in slices(offsets, SLICE):
                n = b - a
                g, row = grams(offsets[a : b + 1], data)
                at = known.find(g)
                found = at >= 0
                total_log = np.bincount(row[found], known.values[at[found]], n)
                more = _rest(row[~found], g[~found], n)
                row, h, n_words = words(offsets[a : b + 1], data)
                at = head.find(h)
                found = at >= 0
                head_sum = np.bincount(row[found], head.values[at[found]], n)
                head_known = np.bincount(row[found], head_seen[at[found]], n).astype(np.int64)
                # The other words, summed within the document.
                rest = _rest(row[~found], h[~found], n)
                size = np.diff(offsets[a : b + 1]) + 1
                cols = [batch["doc_id"].slice(a, n), batch["held_out"].slice(a, n), pa.array(n_words + 1, pa.int64()), pa.array(head_known + (ends > 0), pa.int64()), pa.array(head_sum + end_log), pa.array(total_log), pa.array(size, pa.int64()), *rest, *more]
                yield pa.RecordBatch.from_arrays(cols, ["doc_id", "held_out", "n_tokens", "n_known", "base_score", "score", "size", "rest", "times", "rest_grams", "times_grams"])

    shape = "doc_id long, held_out boolean, n_tokens long, n_known long, base_score double, score double, size long, rest array<long>, times array<long>, rest_grams array<long>, times_grams array<long>"
    scored = spool(base.mapInArrow(run, shape).withColumn("uid", F.monotonically_increasing_id()), "scored")
    tail = scored.where(F.size("rest") > 0).select("uid", F.explode(F.arrays_zip("rest", "times")).alias("x")).select("uid", F.col("x.rest").alias("h"), F.col("x.times").alias("n"))
    # Words of the head never reach the join, so no key of it is frequent; every other word of a text is in the table.
    rare = vocabulary.where(F.col("m") < least).select("h", "c")
    sums = tail.join(rare, "h").groupBy("uid").agg(F.sum(F.when(F.col("c") > 0, F.col("n")).otherwise(0)).alias("more_known"), F.sum(F.col("n") * F.log10((F.col("c") + 0.5) / F.lit(floor or 1.0))).alias("more"))
    deep = scored.where(F.size("rest_grams") > 0).select("uid", F.explode(F.arrays_zip("rest_grams", "times_grams")).alias("x")).select("uid", F.col("x.rest_grams").alias("gram"), F.col("x.times_grams").alias("times"))
    logs = deep.join(predictions.where(F.col("m") < least_gram).select("gram", "log"), "gram").groupBy("uid").agg(F.sum(F.col("times") * F.col("log")).alias("deep"))
    out = scored.drop("rest", "times", "rest_grams", "times_grams").join(sums, "uid", "left").join(logs, "uid", "left")
    total_log = F.col("score") + F.coalesce("deep", F.lit(0.0))
    return out.select("doc_id", "held_out", "n_tokens", (F.col("n_known") + F.coalesce("more_known", F.lit(0))).alias("n_known"), F.lit(int(total)).cast("long").alias("train_tokens"), (F.col("base_score") + F.coalesce("more", F.lit(0.0))).alias("base_score"), total_log.alias("score"), (-total_log / math.log10(2) / F.col("size")).alias("bits_per_byte"))
