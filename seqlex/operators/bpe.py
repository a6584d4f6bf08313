"""Byte-pair encoding over bases: pair counts, training and application.

Units (lines) are deduplicated with their multiplicity before training. A `Chain` holds the symbols of many units in one flat array at the places of their bases, and the
places of each symbol, so a merge costs the occurrences of the rarer of its two symbols and not the corpus. `train_local` runs it on the driver for at most LOCAL_SYMBOLS bases of distinct units
(checked; about 40 bytes a base), `train_batched` on Spark for more: the units stay in the tasks of one barrier stage, and only changes of pair counts, whose number the
vocabulary bounds, are told. `train_sql` is the plain form, an aggregation a round. Ties go to the smaller left, then right, symbol in all three, so they give the same merges.

Applying a merge list replays it: each merge in its order, from left to right, over all units of a batch. This gives the cuts that training saw.
"""

from __future__ import annotations

import base64
import heapq
import itertools
import os
import shutil
import time
import uuid
from collections import Counter
from collections.abc import Callable, Iterator
from urllib.parse import urlparse

import numpy as np
import pyarrow as pa
from pyspark import BarrierTaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from seqlex.functions.bases import bases
from seqlex.sources.tables import checkpoint_dir, settled, spread, stored

SPECIAL_AND_ALPHABET = 10
LOCAL_SYMBOLS = 3_000_000
#: Bases that one chain of a worker holds.
CHAIN_SYMBOLS = 4_000_000
#: Symbols from which a worker's blocks become a chain: two bytes a base, eight a symbol, and four a base of lines that count several times.
LINKED_SYMBOLS = 24_000_000
#: Bases of a block that is scanned; a scan has some 50 bytes of arrays for each.
BLOCK_SYMBOLS = 1 << 20
#: Bases for each task of a training that needs less than all slots: what all tasks do for each merge costs more than sharing fewer bases saves.
TASK_SYMBOLS = 15_000_000
ALPHABET = ("A", "C", "G", "T", "N")

Merge = tuple[str, str, int]

_code = np.full(256, 4, np.int32)
for _i, _b in enumerate(b"ACGTN"):
    _code[_b] = _i


def units(df: DataFrame, text: str = "text") -> DataFrame:
    """(unit, n): different lines of bases with their number, cut in the workers."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, batch.num_rows, 256):
                lines = Counter(x for t in batch[text].slice(a, 256).to_pylist() if t is not None for x in bases(t, keep="\n").split("\n") if x)
                yield pa.RecordBatch.from_arrays([pa.array(lines.keys(), pa.string()), pa.array(lines.values(), pa.int64())], ["unit", "n"])

    return spread(df.select(text)).mapInArrow(run, "unit string, n long").groupBy("unit").agg(F.sum("n").alias("n"))


def spelled(u: DataFrame) -> DataFrame:
    return u.select(F.regexp_replace("unit", "(.)", "<$1>").alias("spelled"), "n")


def pair_counts(s: DataFrame) -> DataFrame:
    """(left, right, n): adjacent symbols, each place counted (three in a row make two pairs)."""
    symbols = s.select(F.split(F.regexp_replace("spelled", "^<|>$", ""), "><").alias("s"), "n").where(F.size("s") > 1)
    pairs = F.inline(F.zip_with(F.slice("s", 1, F.size("s") - 1), F.slice("s", 2, F.size("s") - 1), lambda a, b: F.struct(a.alias("left"), b.alias("right"))))
    return symbols.select(pairs, "n").groupBy("left", "right").agg(F.sum("n").alias("n"))


def merge_pair(s: DataFrame, left: str, right: str) -> DataFrame:
    return s.withColumn("spelled", F.replace("spelled", F.lit(f"<{left}><{right}>"), F.lit(f"<{left}{right}>")))


def train_sql(u: DataFrame, merges: int, min_freq: int = 100) -> list[Merge]:
    """The first merges, each with its count, as one aggregation a round; only the winner comes to the driver. For a few merges: the plan grows with each."""
    s, out = settled(spelled(u)), []
    for _ in range(merges):
        best = pair_counts(s).orderBy(F.desc("n"), "left", "right").first()
        if best is None or best["n"] < min_freq:
            break
        out.append((best["left"], best["right"], best["n"]))
        s = merge_pair(s, best["left"], best["right"])
    return out


class Chain:
    """Symbols of units in one flat array, at the places of their bases: a symbol, one more than its number, stands at its first place and as a complement at its last, 0 stands between
    units. So a symbol's length leads to both its neighbours. `where` has the places of each symbol in their order, stale ones included, so a merge looks at those of the rarer of
    its two. With weights a merge tells how the numbers of pairs change.

    symbols: an array for each unit, or one flat array with -1 before, between and after units. length: of each symbol in bases; alone the alphabet where it is not given."""

    INSIDE = -1

    def __init__(self, symbols: list[np.ndarray] | np.ndarray, weights: np.ndarray | None = None, length: list[int] | None = None) -> None:
        if isinstance(symbols, list):
            sizes = np.array([len(x) for x in symbols], np.int64)
            ends = np.cumsum(sizes + 1)
            flat = np.full(int(ends[-1]) + 1 if len(ends) else 1, -1, np.int16)
            inside = np.ones(len(flat), bool)
            inside[np.concatenate([[0], ends])] = False
            flat[inside] = np.concatenate(symbols) if symbols else 0
        else:
            flat = symbols
        most = int(flat.max())
        self.length = list(length) if length else [1] * (max(most, len(ALPHABET) - 1) + 1)
        self.counted, self.weight = weights is not None, None
        kind = np.int16 if most < (1 << 15) - 2 else np.int32
        if max(self.length) == 1:
            at, self.symbol = None, flat.astype(kind) + kind(1)
        else:
            size = np.array([*self.length, 1], np.int64)[flat]
            at = np.cumsum(size) - size
            self.symbol = np.full(int(at[-1]) + 1, self.INSIDE, kind)
            self.symbol[at] = flat + 1
            more = np.flatnonzero(size > 1)
            self.symbol[at[more] + size[more] - 1] = ~(flat[more] + 1)
        if most < 16:
            self.where = {k: np.flatnonzero(flat == k) if at is None else at[flat == k] for k in range(most + 1)}
        else:
            order = np.argsort(flat, kind="stable")
            cut = np.concatenate([[0], np.cumsum(np.bincount(flat.astype(np.int64) + 1, minlength=most + 2))]).tolist()
            order = order if at is None else at[order]
            self.where = {k: order[cut[k + 1] : cut[k + 2]] for k in range(most + 1) if cut[k + 1] < cut[k + 2]}
        self.alive = [len(self.where.get(k, ())) for k in range(len(self.length))]
        if self.counted and (weights != 1).any():
            # From the first unit that counts several times on; a unit's separator stands before it.
            between = np.flatnonzero(self.symbol == 0)
            first = int(np.argmax(weights != 1))
            self.heavy = int(between[first])
            self.weight = np.append(np.repeat(weights[first:], np.diff(between[first:])), 0)
            self.weight = self.weight.astype(np.int32 if self.weight.max() < 1 << 31 else np.int64)

    def _weights(self, at: np.ndarray) -> np.ndarray | None:
        """Of these places, in their order; none where all are 1."""
        first = len(at) if self.weight is None else int(np.searchsorted(at, self.heavy))
        if first == len(at):
            return None
        out = np.ones(len(at))
        out[first:] = self.weight[at[first:] - self.heavy]
        return out

    def pairs(self) -> tuple[np.ndarray, np.ndarray]:
        """(pair, weighted number) before any merge."""
        at = np.flatnonzero((self.symbol[:-1] > 0) & (self.symbol[1:] > 0))
        side = int(self.symbol.max()) + 1
        n = np.bincount((self.symbol[at].astype(np.int64) - 1) * side + self.symbol[at + 1] - 1, self._weights(at), side * side)
        found = np.flatnonzero(n)
        return (found // side) << 32 | found % side, n[found].astype(np.int64)

    def _places(self, k: int) -> np.ndarray:
        """Of a symbol, in their order; a third of them is stale at most."""
        at = self.where.get(k, np.zeros(0, np.int64))
        if 2 * len(at) > 3 * self.alive[k]:
            at = self.where[k] = at.compress(self.symbol.take(at) == k + 1)
        return at

    def merge(self, a: int, b: int, c: int) -> tuple[np.ndarray, np.ndarray, int, int] | None:
        """Each a that a b follows becomes c, from left to right. With weights: the number of each symbol before them, unless that is itself merged, and of each one behind them, the
        number of merged pairs, and of those that another one follows at once."""
        for known in (self.length, self.alive):
            known += [0] * (c + 1 - len(known))
        self.length[c] = self.length[a] + self.length[b]
        if c + 2 >= 1 << 15 and self.symbol.dtype == np.int16:
            self.symbol = self.symbol.astype(np.int32)
        if not (self.alive[a] and self.alive[b]):
            return None
        symbol, size, end = self.symbol, self.length[a], self.length[c] - 1
        if a == b or len(self.where.get(a, ())) <= len(self.where.get(b, ())):
            left = self._places(a)
            left = left.compress(symbol[size:].take(left) == b + 1)
            left = left.compress(symbol.take(left) == a + 1)
        else:
            right = self._places(b)
            right = right.compress(symbol.take(right - 1) == (a + 1 if size == 1 else ~(a + 1)))
            left = right.compress(symbol.take(right) == b + 1) - size
        if a == b and len(left) > 1:
            # In a run, every other place.
            starts = np.concatenate([[True], left[1:] != left[:-1] + size])
            nth = np.arange(len(left))
            left = left[(nth - np.maximum.accumulate(np.where(starts, nth, 0))) % 2 == 0]
        if not len(left):
            return None
        told = None
        if self.counted:
            apart, w = np.ones(len(left), bool), self._weights(left)
            np.not_equal(left[1:], left[:-1] + (end + 1), out=apart[1:])
            before = symbol.take(left - 1)
            # The separator's 0 comes first and goes.
            x = np.bincount(np.where(before < 0, ~before, before).compress(apart), None if w is None else w.compress(apart))[1:].astype(np.int64)
            y = np.bincount(symbol[end + 1 :].take(left), w)[1:].astype(np.int64)
            told = (x, y, len(left) if w is None else int(w.sum()), len(left) - int(apart.sum()) if w is None else int(w[:-1].compress(~apart[1:]).sum()))
        if end > size:
            symbol[left + size] = self.INSIDE
        symbol[left] = c + 1
        symbol[left + end] = ~(c + 1)
        for k, n in ((a, -len(left)), (b, -len(left)), (c, len(left))):
            self.alive[k] += n
        known = self.where.get(c)
        self.where[c] = left if known is None else np.sort(np.concatenate([known, left]))
        return told

    def symbols(self) -> tuple[np.ndarray, np.ndarray]:
        """(symbols of all units, end of each unit among them)."""
        first = self.symbol > 0
        ends = np.cumsum(first)[np.flatnonzero(self.symbol == 0)[1:]]
        return self.symbol[first].astype(np.int32) - 1, ends


def changes(a: int, b: int, c: int, told: list) -> tuple[np.ndarray, np.ndarray]:
    """(pair, change of its number) by a merge, of what the chains told of it; a pair can come several times."""
    told = [t for t in told if t is not None]
    if not told:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    x, y = (told[0][i] if len(told) == 1 else np.sum([np.pad(t[i], (0, max(len(u[i]) for u in told) - len(t[i]))) for t in told], axis=0) for i in (0, 1))
    n, runs = (sum(t[i] for t in told) for i in (2, 3))
    xs, ys = np.flatnonzero(x), np.flatnonzero(y)
    # Behind a merged pair that another one follows stands no a any more, but the other one's c.
    keys = [xs << 32 | a, xs << 32 | c, b << 32 | ys, c << 32 | ys, np.array([a << 32 | b, c << 32 | a, c << 32 | c], np.int64)]
    return np.concatenate(keys), np.concatenate([-x[xs], x[xs], -y[ys], y[ys], [-n, -runs, runs]]).astype(np.int64)


_symbol = np.where(np.arange(256) == ord("."), 255, _code).astype(np.uint8)


def codes(unit: str) -> np.ndarray:
    return _code[np.frombuffer(unit.encode(), np.uint8)]


class Names:
    """Symbols by number; a symbol is its string, however it was put together."""

    def __init__(self) -> None:
        self.of, self.number = list(ALPHABET), {b: i for i, b in enumerate(ALPHABET)}

    def add(self, name: str) -> int:
        if name not in self.number:
            self.number[name] = len(self.of)
            self.of.append(name)
        return self.number[name]


def train_local(rows: list[tuple[str, int]], vocab_size: int, min_freq: int = 100) -> list[Merge]:
    names, chain = Names(), Chain([codes(u) for u, _ in rows], np.array([n for _, n in rows], np.int64))
    counts = dict(zip(*(x.tolist() for x in chain.pairs()), strict=True))
    entry = lambda k: (-counts[k], names.of[k >> 32], names.of[k & 0xFFFFFFFF])
    heap = [entry(k) for k in counts]
    heapq.heapify(heap)
    out: list[Merge] = []
    while heap and len(out) < vocab_size - SPECIAL_AND_ALPHABET:
        n, left, right = heapq.heappop(heap)
        a, b = names.number[left], names.number[right]
        if counts.get(a << 32 | b) != -n:
            continue
        if -n < min_freq:
            break
        out.append((left, right, -n))
        c = names.add(left + right)
        keys, change = _summed(*changes(a, b, c, [chain.merge(a, b, c)]))
        for k, x in zip(keys[change != 0].tolist(), change[change != 0].tolist(), strict=True):
            counts[k] = counts.get(k, 0) + x
            if counts[k] > 0:
                heapq.heappush(heap, entry(k))
            else:
                del counts[k]
    return out


def next_merges(heap: list, counts: Ranked, names: Names, room: int, min_freq: int) -> list[Merge]:
    """The next merges of a one-by-one training that leave each other alone, popped from the heap: the ranked pairs up to the first of which a symbol stands on both sides.

    No occurrence of two of them overlaps, so their counts stay. A symbol that they make is new, and a pair with it was a pair not among them before, so it counts no more
    than the first pair left in the heap; the last ones that count no more than that wait, as the names would decide. A pair of equal symbols, or one that spells a
    known symbol anew, stands alone."""
    head: list[Merge] = []
    lefts: set[int] = set()
    rights: set[int] = set()
    made: dict[str, int] = {}
    top = lambda: heap[0] if heap else None

    def fresh() -> None:
        while heap:
            n, left, right = heap[0]
            key = names.number[left] << 32 | names.number[right]
            if counts.get(key) == -n and made.get(left + right) != key:
                return
            heapq.heappop(heap)

    while len(head) < room:
        fresh()
        if top() is None or -top()[0] < min_freq:
            break
        n, left, right = top()
        a, b = names.number[left], names.number[right]
        alone = a == b or left + right in names.number or left + right in made
        if head and (alone or a in rights or b in lefts):
            break
        heapq.heappop(heap)
        head.append((left, right, -n))
        if alone:
            return head
        lefts.add(a)
        rights.add(b)
        made[left + right] = a << 32 | b
    fresh()
    while len(head) > 1 and heap and head[-1][2] == -heap[0][0]:
        left, right, n = head.pop()
        del made[left + right]
        heapq.heappush(heap, (-n, left, right))
    return head


class Ranked:
    """Numbers of pairs of symbols: a square array where that is of 256 MB at most, else by key. The heap has the pairs that count `floor` at least; it is lowered when they are used up."""

    def __init__(self, size: int, names: Names, least: int) -> None:
        self.size, self.names, self.least, self.floor = size, names, least, 1 << 62
        self.heap: list[tuple[int, str, str]] = []
        self.n: np.ndarray | dict[int, int] | None = None

    def _number(self, at: np.ndarray) -> np.ndarray:
        return self.n[at] if isinstance(self.n, np.ndarray) else np.array([self.n.get(k, 0) for k in at.tolist()], np.int64)

    def _push(self, at: np.ndarray) -> None:
        for k, x in zip(at.tolist(), self._number(at).tolist(), strict=True):
            heapq.heappush(self.heap, (-x, self.names.of[k // self.size], self.names.of[k % self.size]))

    def get(self, key: int) -> int:
        at = (key >> 32) * self.size + (key & 0xFFFFFFFF)
        return int(self.n[at] if isinstance(self.n, np.ndarray) else self.n.get(at, 0))

    def change(self, keys: np.ndarray, by: np.ndarray) -> None:
        at = (keys >> 32) * self.size + (keys & 0xFFFFFFFF)
        if self.n is None:
            # No pair ever counts more than all do at first.
            kind = np.int32 if by.sum() < 1 << 31 else np.int64
            self.n = np.zeros(self.size**2, kind) if self.size**2 * np.dtype(kind).itemsize <= 1 << 28 else {}
        if isinstance(self.n, np.ndarray):
            np.add.at(self.n, at, by.astype(self.n.dtype))
        else:
            for k, x in zip(at.tolist(), by.tolist(), strict=True):
                self.n[k] = self.n.get(k, 0) + x
        self._push(np.unique(at[self._number(at) >= self.floor]))

    def lower(self) -> bool:
        """Half as much as the largest number under the floor is the new one; false if there is none."""
        if self.floor <= self.least:
            return False
        # Only the symbols so far have pairs.
        n, before = self.n[: len(self.names.of) * self.size] if isinstance(self.n, np.ndarray) else np.array(list(self.n.values()), np.int64), self.floor
        self.floor = max(self.least, int(np.where(n < before, n, 0).max(initial=0)) // 2)
        at = np.flatnonzero((n >= max(1, self.floor)) & (n < before))
        self._push(at if isinstance(self.n, np.ndarray) else np.array(list(self.n), np.int64)[at])
        return True


def _summed(keys: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    found, at = np.unique(keys, return_inverse=True)
    return found, np.bincount(at, n, len(found)).astype(np.int64)


class Blocks:
    """Symbols of a task's units in flat arrays, a separator before, between and after units, at first one byte a symbol and two from the 250th on. A merge of pairs that
    leave each other alone is one scan of a block. From `linked` symbols on, when they are few enough, they become chains, and a merge costs its occurrences."""

    def __init__(self, linked: int) -> None:
        self.linked, self.flat, self.weights, self.chains = linked, [], [], []
        self.length = [1] * len(ALPHABET)
        #: Lines, each with a dot behind it, and their weights for the next blocks: of those that count once, and of the others.
        self.waiting: list[list[tuple[str, np.ndarray]]] = [[], []]

    def add(self, units: list[str], n: np.ndarray) -> None:
        for kind, own in enumerate((n == 1, n != 1)):
            lines, weights, a = list(itertools.compress(units, own.tolist())), n[own].astype(np.int64), 0
            block = np.cumsum([len(x) + 1 for x in lines]) // BLOCK_SYMBOLS
            for b in [*(np.flatnonzero(np.diff(block)) + 1).tolist(), len(lines)] if lines else []:
                self.waiting[kind].append((".".join(lines[a:b]) + ".", weights[a:b]))
                a = b
                if sum(len(x) for x, _ in self.waiting[kind]) >= BLOCK_SYMBOLS:
                    self._close(kind)

    def _close(self, kind: int) -> None:
        units, self.waiting[kind] = self.waiting[kind], []
        if units:
            self.flat.append(_symbol[np.frombuffer(("." + "".join(u for u, _ in units)).encode(), np.uint8)])
            self.weights.append(np.concatenate([x for _, x in units]) if kind else None)

    def _keys(self, flat: np.ndarray, at: np.ndarray, weight: np.ndarray | None, sign: int) -> tuple[np.ndarray, np.ndarray]:
        """(pair, weighted number) of the pairs at these places, without those that hold a separator."""
        end = np.iinfo(flat.dtype).max
        left, right = flat[at].astype(np.int64), flat[at + 1].astype(np.int64)
        inside = (left != end) & (right != end)
        left, right = left[inside], right[inside]
        n = None if weight is None else weight[inside]
        side = int(max(left.max(initial=0), right.max(initial=0))) + 1
        if side <= 512 and side * side <= 16 * len(left):
            total = np.bincount(left * side + right, n, side * side)
            found = np.flatnonzero(total)
            return (found // side) << 32 | found % side, sign * total[found].astype(np.int64)
        found, total = _summed(left << 32 | right, np.ones(len(left)) if n is None else n)
        return found, sign * total

    def pairs(self) -> tuple[np.ndarray, np.ndarray]:
        self._close(0)
        self._close(1)
        got = [(np.zeros(0, np.int64), np.zeros(0, np.int64))]
        for flat, w in zip(self.flat, self.weights, strict=True):
            weight = None if w is None else np.repeat(np.append(w, 0), np.diff(np.flatnonzero(flat == 255), append=len(flat)))[: len(flat) - 1]
            got.append(self._keys(flat, np.arange(len(flat) - 1), weight, 1))
        return _summed(np.concatenate([k for k, _ in got]), np.concatenate([n for _, n in got]))

    def _scan(self, flat: np.ndarray, w: np.ndarray | None, merges: list[tuple[int, int, int]], out: list) -> np.ndarray:
        end = np.iinfo(flat.dtype).max
        if len(merges) == 1:
            a, b, _ = merges[0]
            at = np.flatnonzero((flat[:-1] == a) & (flat[1:] == b))
            if a == b and len(at) > 1:
                # In a run, every other place.
                starts = np.concatenate([[True], at[1:] != at[:-1] + 1])
                nth = np.arange(len(at))
                at = at[(nth - np.maximum.accumulate(np.where(starts, nth, 0))) % 2 == 0]
            new = np.full(len(at), merges[0][2], flat.dtype)
        else:
            # All pairs in one mask, as looking for its places costs more than comparing; which pair a place has is told by a binary search.
            mask = np.zeros(len(flat) - 1, bool)
            for a, b, _ in merges:
                mask |= (flat[:-1] == a) & (flat[1:] == b)
            at = np.flatnonzero(mask)
            pair = np.array([a << 32 | b for a, b, _ in merges], np.int64)
            order = np.argsort(pair)
            nth = order[np.searchsorted(pair[order], flat[at].astype(np.int64) << 32 | flat[at + 1])]
            new = np.array([c for _, _, c in merges], flat.dtype)[nth]
        if not len(at):
            return flat
        weight = None if w is None else np.repeat(w, np.diff(np.searchsorted(at, np.flatnonzero(flat == end))))
        of = lambda mask: None if weight is None else weight[mask]
        # A pair between two merged places counts once.
        apart = np.concatenate([[True], at[1:] != at[:-1] + 2])
        every = np.ones(len(at), bool)
        for places, mask in ((at[apart] - 1, apart), (at, every), (at + 1, every)):
            out.append(self._keys(flat, places, of(mask), -1))
        keep = np.ones(len(flat), bool)
        keep[at + 1] = False
        flat[at] = new
        flat = flat[keep]
        now = at - np.arange(len(at))
        for places, mask in ((now[apart] - 1, apart), (now, every)):
            out.append(self._keys(flat, places, of(mask), 1))
        return flat

    def _link(self) -> None:
        """One chain of all blocks, those whose units count once first."""
        flats, weights = [], []
        for k in sorted(range(len(self.flat)), key=lambda k: self.weights[k] is not None):
            flat, w = self.flat[k], self.weights[k]
            end = np.iinfo(flat.dtype).max
            flats.append(np.where(flat == end, -1, flat.astype(np.int16 if flat.max(where=flat != end, initial=0) < 1 << 15 else np.int32))[:-1])
            weights.append(np.ones(int((flat == end).sum()) - 1, np.int64) if w is None else w)
        self.flat, self.weights = [], []
        self.chains.append(Chain(np.concatenate([*flats, [np.int16(-1)]]), np.concatenate(weights), self.length))

    def merge(self, merges: list[tuple[int, int, int]]) -> tuple[np.ndarray, np.ndarray]:
        """(pair, change of its number) when these pairs, which leave each other alone, are merged; a pair can come several times."""
        out = [(np.zeros(0, np.int64), np.zeros(0, np.int64))]
        if self.flat and max(c for _, _, c in merges) >= 250 and self.flat[0].dtype == np.uint8:
            self.flat = [np.where(x == 255, np.uint16(65535), x.astype(np.uint16)) for x in self.flat]
        if self.flat and sum(map(len, self.flat)) <= self.linked:
            self._link()
        for k, flat in enumerate(self.flat):
            self.flat[k] = self._scan(flat, self.weights[k], merges, out)
        for a, b, c in merges if self.chains else []:
            out.append(changes(a, b, c, [chain.merge(a, b, c) for chain in self.chains]))
        for a, b, c in merges:
            self.length += [0] * (c + 1 - len(self.length))
            self.length[c] = self.length[a] + self.length[b]
        return np.concatenate([k for k, _ in out]), np.concatenate([n for _, n in out])


def shared_folder(spark: SparkSession) -> str | None:
    """A new folder within the one that driver and executors share, or none where it isn't a plain path."""
    at = urlparse(checkpoint_dir(spark))
    if at.scheme not in ("", "file") or not os.path.isdir(at.path):
        return None
    folder = f"{at.path.rstrip('/')}/seqlex-bpe-{uuid.uuid4().hex}"
    os.mkdir(folder)
    return folder


def everywhere(context: BarrierTaskContext, folder: str | None) -> Callable[[bytes], list[bytes]]:
    """A function by which each task of a barrier stage tells all others something and hears them, in the order of the tasks."""
    if folder is None:
        return lambda said: [base64.b64decode(x) for x in context.allGather(base64.b64encode(said).decode())]
    own, tasks = context.partitionId(), len(context.getTaskInfos())
    # Another folder for each attempt of the stage: the name that its first task proposes.
    here, rounds = f"{folder}/{context.allGather(uuid.uuid4().hex)[0]}", itertools.count()
    os.makedirs(here, exist_ok=True)

    def tell(said: bytes) -> list[bytes]:
        nth, heard = next(rounds), []
        with open(f"{here}/new-{own}", "wb") as f:
            f.write(said)
        os.rename(f"{here}/new-{own}", f"{here}/{nth}-{own}")
        for task in range(tasks):
            # A task that is lost ends the whole stage, and with it this wait.
            while not os.path.exists(f"{here}/{nth}-{task}"):
                time.sleep(0.001)
            with open(f"{here}/{nth}-{task}", "rb") as f:
                heard.append(f.read())
        if nth:
            # Who has told this round has heard the one before.
            os.remove(f"{here}/{nth - 1}-{own}")
        return heard

    return tell


def train_batched(u: DataFrame, vocab_size: int, min_freq: int = 100, linked: int = LINKED_SYMBOLS, symbols: int | None = None) -> list[Merge]:
    """The merges of train_local for units of any number. One barrier stage with a task for each slot, or for TASK_SYMBOLS where `symbols`, their bases in all, says that fewer do, holds the units; the tasks tell each other how the counts of pairs change, and so
    all know the next merges: by small files of the shared checkpoint folder, or, where that is no plain folder, by the stage's own messages of a second each. Each keeps its units as `Blocks`: a byte or two a symbol, and linked only when there are few."""

    def learn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        context, own, names, out = BarrierTaskContext.get(), Blocks(linked), Names(), []

        told = everywhere(context, folder)

        def together(keys: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            parts = [np.frombuffer(x, np.int64).reshape(2, -1) for x in told(np.concatenate([keys, n]).tobytes())]
            return np.concatenate([x[0] for x in parts]), np.concatenate([x[1] for x in parts])

        for batch in batches:
            own.add(batch["unit"].to_pylist(), np.asarray(batch["n"]))
        most, ranked = vocab_size - SPECIAL_AND_ALPHABET, Ranked(max(vocab_size, SPECIAL_AND_ALPHABET), names, min_freq)
        ranked.change(*together(*own.pairs()))
        while len(out) < most:
            head = next_merges(ranked.heap, ranked, names, most - len(out), min_freq)
            if head:
                out += head
                ranked.change(*together(*own.merge([(names.number[a], names.number[b], names.add(a + b)) for a, b, _ in head])))
            elif not ranked.lower():
                break
        if context.partitionId() == 0:
            yield pa.RecordBatch.from_arrays([pa.array([x[i] for x in out], kind) for i, kind in enumerate((pa.string(), pa.string(), pa.int64()))], ["a", "b", "n"])

    jvm = u.sparkSession.sparkContext._jsc.sc()
    slots = jvm.maxNumConcurrentTasks(jvm.resourceProfileManager().defaultResourceProfile())
    folder = shared_folder(u.sparkSession)
    tasks = max(1, slots if symbols is None else min(slots, -(-symbols // TASK_SYMBOLS)))
    got = u.select("unit", F.col("n").cast("long").alias("n")).repartition(tasks).mapInArrow(learn, "a string, b string, n long", barrier=True)
    try:
        return [tuple(r) for r in got.collect()]
    finally:
        if folder:
            shutil.rmtree(folder, ignore_errors=True)


def train_bpe(u: DataFrame, vocab_size: int, min_freq: int = 100, symbols: int = LOCAL_SYMBOLS) -> list[Merge]:
    """Units of more than `symbols` bases go to the batched trainer; the merges are the same."""
    u = stored(u.select("unit", F.col("n").cast("long").alias("n")))  # else the corpus is cut and shuffled once for its size and once for the training
    size = u.agg(F.sum(F.length("unit"))).first()[0] or 0
    if size > symbols:
        return train_batched(u, vocab_size, min_freq, symbols=size)
    rows = u.select("unit", "n").toArrow().sort_by("unit")
    return train_local(list(zip(rows["unit"].to_pylist(), rows["n"].to_pylist(), strict=True)), vocab_size, min_freq)


def vocab(merges: list[Merge], size: int) -> list[str]:
    """The tokens of a vocabulary of `size`: the alphabet and the first size - 10 merges. Prefixes of one training are nested."""
    return [*ALPHABET, *dict.fromkeys(a + b for a, b, _ in merges[: size - SPECIAL_AND_ALPHABET])]


def apply_sql(seq: Column, merges: list[Merge]) -> Column:
    """Tokens by a chain of replaces; for a few dozen merges."""
    s = F.regexp_replace(seq, "(.)", "<$1>")
    for a, b, _ in merges:
        s = F.replace(s, F.lit(f"<{a}><{b}>"), F.lit(f"<{a}{b}>"))
    return F.split(F.regexp_replace(s, "^<|>$", ""), "><")


def replays(seqs: list[str], merges: list[Merge], firsts: list[int]) -> Iterator[tuple[np.ndarray, np.ndarray, list[str]]]:
    """(symbols of all sequences, their ends, names of the symbols) after each of so many first merges, in rising order."""
    names, chain, done = Names(), Chain([codes(s) for s in seqs]), 0
    for first in firsts:
        for a, b, _ in merges[done:first]:
            chain.merge(names.number[a], names.number[b], names.add(a + b))
        done = first
        yield *chain.symbols(), names.of


def replay(seqs: list[str], merges: list[Merge]) -> tuple[np.ndarray, np.ndarray, list[str]]:
    """replays() of all merges."""
    return next(replays(seqs, merges, [len(merges)]))


class Cutter:
    """The tokens of apply_bpe as numbers, in the order of vocab(), by vocabularies of some sizes (of all merges, if none is given) in rising order: a replay of the merges
    comes by all of them."""

    def __init__(self, merges: list[Merge], sizes: list[int] | None = None) -> None:
        self.merges, self.firsts = merges, [min(len(merges), n - SPECIAL_AND_ALPHABET) for n in sizes or [len(merges) + SPECIAL_AND_ALPHABET]]
        self.sizes = [len(vocab(merges, n + SPECIAL_AND_ALPHABET)) for n in self.firsts]
        self.size, self.at_once = self.sizes[-1], CHAIN_SYMBOLS

    def each(self, keys: np.ndarray, seqs: list[str]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        for symbols, ends, _ in replays(seqs, self.merges, self.firsts):
            yield symbols, np.repeat(np.arange(len(seqs)), np.diff(ends, prepend=0))

    def __call__(self, keys: np.ndarray, seqs: list[str]) -> tuple[np.ndarray, np.ndarray]:
        *_, last = self.each(keys, seqs)
        return last


def apply_bpe(df: DataFrame, merges: list[Merge]) -> DataFrame:
    """(contig, tokens) for (contig, seq), in Arrow batches of at most CHAIN_SYMBOLS bases; the merge list is bounded by the vocabulary."""
    shared = df.sparkSession.sparkContext.broadcast(merges)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            seqs, a = [s or "" for s in batch["seq"].to_pylist()], 0
            while a < len(seqs):
                b, size = a, 0
                while b < len(seqs) and (b == a or size + len(seqs[b]) <= CHAIN_SYMBOLS):
                    size, b = size + len(seqs[b]), b + 1
                symbols, ends, names = replay(seqs[a:b], shared.value)
                tokens = pa.array(names, pa.string()).take(pa.array(symbols))
                yield pa.RecordBatch.from_arrays([batch["contig"].slice(a, b - a), pa.ListArray.from_arrays(pa.array(np.concatenate([[0], ends]), pa.int32()), tokens)], ["contig", "tokens"])
                a = b

    return df.select("contig", "seq").mapInArrow(run, "contig long, tokens array<string>")


def base_pair_counts(u: DataFrame) -> DataFrame:
    """(left, right, n) of (unit, n) before any merge, counted in the workers: a task hands on 25 rows at most."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        totals = np.zeros(36, np.int64)
        for batch in batches:
            for a in range(0, batch.num_rows, 20_000):
                part = batch.slice(a, 20_000)
                # A sixth letter between units.
                own = [np.append(codes(x), 5) for x in part["unit"].to_pylist()]
                flat = np.concatenate(own)
                weight = np.repeat(np.asarray(part["n"]).astype(np.int64), [len(x) for x in own])
                totals += np.bincount(flat[:-1] * 6 + flat[1:], weight[:-1], 36).astype(np.int64)
        rows = [(x, y, int(totals[6 * i + j])) for i, x in enumerate(ALPHABET) for j, y in enumerate(ALPHABET) if totals[6 * i + j]]
        yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.string()), pa.array([r[1] for r in rows], pa.string()), pa.array([r[2] for r in rows], pa.int64())], ["left", "right", "n"])

    return u.select("unit", "n").mapInArrow(run, "left string, right string, n long").groupBy("left", "right").agg(F.sum("n").alias("n"))
