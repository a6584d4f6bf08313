"""Quality rules with isolation forests on their statistics.

The rule statistics of every whole text are counted in numpy from the Arrow buffers. Two base rules fail a document at once. For the others
isolation forests decide: trees, each over `SAMPLE` documents, cut a random statistic at a random place; documents that end on short
paths are anomalous. One forest of `TREES` trees sees all statistics together, and one of `SINGLE` trees each statistic alone, where a score is a step function
of the value. The trees need a bounded sample by nature; it is drawn by a hash of id and statistics over all documents.

Each forest has a threshold of its own, calibrated on all labelled rows (`labels.quality`) outside a held-out fifth: forest by forest, the one is taken whose best threshold
gains most, counting the share of the remaining bad rows above it less `PRICE` times the share of the good ones; a forest that gains nothing decides nothing.
`score` is the largest ratio of a forest's score to its threshold, and a document above 1 is not kept. `held_out` gives the shares of bad and good rows of the held-out
fifth that the forests drop. Path lengths are computed for all documents.

Defined results: a null text has no words and fails the base rules, as does an empty one. Repeated rows are judged alike; labels that repeat for an id count once, as the
lower one. Without bad labelled rows the threshold of the joint forest is the score above which `MISSED` of the good rows (without any, of the sample) fall; without documents
there are no rows. Only `doc_id` and `text` are read (and `doc_id` and `quality` of the labels).
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import mix, slices, spool, utf8
from .shingles import word_hashes

TREES, SINGLE, SAMPLE, MISSED, PRICE = 100, 25, 256, 0.005, 10.0
#: Scores are multiples of 1 / GRID, so a histogram of them is bounded whatever the number of rows.
GRID = 1 << 20
STATS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")

_white = np.zeros(256, bool)
_white[[32, *range(9, 14)]] = True
_symbol = np.zeros(256, bool)
_symbol[list(b"#*$%&|<>")] = True


def _repeated(row: np.ndarray, key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(equal to another key of its row, equal to an earlier one), element by element; elements come in order."""
    order = np.lexsort((np.arange(len(key)), key, row))
    r, k = row[order], key[order]
    same = np.concatenate([[False], (r[1:] == r[:-1]) & (k[1:] == k[:-1])]) if len(r) else np.zeros(0, bool)
    earlier, other = np.zeros(len(key), bool), np.zeros(len(key), bool)
    earlier[order] = same
    other[order] = same | np.concatenate([same[1:], [False]]) if len(r) else same
    return other, earlier


def statistics_of(offsets: np.ndarray, data: np.ndarray) -> np.ndarray:
    """A row of STATS for each text."""
    n = len(offsets) - 1
    base = int(offsets[0])
    cut = np.asarray(offsets) - base
    # A line break before each text keeps texts apart.
    own = np.insert(data[base : int(offsets[-1])], cut[:-1], 10)
    cut = cut + np.arange(n + 1)
    white = _white[own]
    sums = lambda mask: np.diff(np.concatenate([[0], np.cumsum(mask)])[cut])
    chars, symbols = sums(((own & 0xC0) != 0x80) & ~white), sums(_symbol[own])
    start, h = word_hashes(own, fold=False)
    row = np.searchsorted(cut, start, "right") - 1
    words = np.bincount(row, minlength=n)
    repeat = np.zeros(n, np.int64)
    if len(h) > 2:
        i = np.flatnonzero(row[2:] == row[:-2])
        odd = np.uint64(0x9E3779B97F4A7C15)
        window = mix(mix(mix(h[i]) * odd + h[i + 1]) * odd + h[i + 2])
        twice = i[_repeated(row[i], window)[0]]
        inside = np.zeros(len(h), bool)
        for k in range(3):
            inside[twice + k] = True
        repeat = np.bincount(row[inside], minlength=n)
    # Lines: hashed as words are, with the break as the only separator; the words within give whether there is one.
    at, line = word_hashes(own, fold=False, newline_only=True)
    end = np.append(np.flatnonzero(own == 10), len(own))
    end = end[np.searchsorted(end, at)]
    worded = np.searchsorted(start, end) > np.searchsorted(start, at)
    line_row = np.searchsorted(cut, at, "right") - 1
    dup = np.bincount(line_row[worded][_repeated(line_row[worded], line[worded])[1]], minlength=n)
    return np.stack([words, chars, symbols, dup, repeat], 1).astype(np.int64)


def statistics(docs: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            offsets, data = utf8(batch["text"])
            for a, b in slices(offsets):
                got = statistics_of(offsets[a : b + 1], data)
                yield pa.RecordBatch.from_arrays([batch["doc_id"].slice(a, b - a), *(pa.array(np.ascontiguousarray(c)) for c in got.T)], ["doc_id", *STATS])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, " + ", ".join(f"{c} long" for c in STATS))


def features(stats: np.ndarray) -> np.ndarray:
    """Scale-free views of the statistics, so that length alone is but one of five."""
    words, chars, symbols, dup, repeat = (stats[:, k].astype(float) for k in range(5))
    n = np.maximum(words, 1)
    return np.stack([np.log1p(words), chars / n, symbols / np.maximum(chars, 1), np.log1p(dup), repeat / n], 1)


def _expected(n: float) -> float:
    """Mean path length of an unsuccessful search among n."""
    return 0.0 if n < 2 else 2 * (math.log(n - 1) + 0.5772156649 if n > 2 else 0.5) - (2 * (n - 1) / n if n > 2 else 0)


class Forest:
    def __init__(self, sample: np.ndarray, *, trees: int = TREES, size: int = SAMPLE, seed: int = 10) -> None:
        rng = np.random.default_rng(seed)
        size = min(size, len(sample))
        height = max(1, math.ceil(math.log2(max(2, size))))
        nodes = 2 ** (height + 1) - 1
        self.feature, self.cut = np.full((trees, nodes), -1, np.int8), np.zeros((trees, nodes))
        self.depth = np.zeros((trees, nodes))
        self.height, self.norm = height, _expected(size) or 1.0
        for t in range(trees):
            todo = [(0, 0, sample[rng.choice(len(sample), size, replace=False)])] if size else []
            while todo:
                node, depth, rows = todo.pop()
                low, high = rows.min(0), rows.max(0)
                open_ = np.flatnonzero(high > low)
                if depth == height or not len(open_):
                    self.depth[t, node] = depth + _expected(len(rows))
                    continue
                f = int(rng.choice(open_))
                cut = rng.uniform(low[f], high[f])
                self.feature[t, node], self.cut[t, node] = f, cut
                left = rows[:, f] <= cut
                todo += [(2 * node + 1, depth + 1, rows[left]), (2 * node + 2, depth + 1, rows[~left])]

    def scores(self, x: np.ndarray) -> np.ndarray:
        total, rows = np.zeros(len(x)), np.arange(len(x))
        for feature, cut, depth in zip(self.feature, self.cut, self.depth, strict=True):
            at = np.zeros(len(x), np.int64)
            for _ in range(self.height):
                f = feature[at]
                go = f >= 0
                at = np.where(go, 2 * at + 1 + (x[rows, np.maximum(f, 0)] > cut[at]), at)
            total += depth[at]
        return 2.0 ** (-total / max(1, len(self.feature)) / self.norm)


class Steps:
    """A forest over one statistic as the step function that its scores are: between two cuts of any tree all values have the same paths."""

    def __init__(self, forest: Forest) -> None:
        self.edges = np.unique(forest.cut[forest.feature >= 0])
        # A value equal to a cut goes left of it.
        inside = np.append(self.edges, self.edges[-1] + 1 if len(self.edges) else 0.0)
        self.values = forest.scores(inside[:, None])

    def scores(self, x: np.ndarray) -> np.ndarray:
        return self.values[np.searchsorted(self.edges, x, "left")]


class Forests:
    """The joint forest and one for each statistic alone; scores() has a column for each."""

    def __init__(self, sample: np.ndarray) -> None:
        self.joint = Forest(sample)
        self.single = [Steps(Forest(sample[:, [k]], trees=SINGLE, seed=20 + k)) for k in range(sample.shape[1])]

    def scores(self, x: np.ndarray) -> np.ndarray:
        return np.round(np.stack([self.joint.scores(x), *(f.scores(x[:, k]) for k, f in enumerate(self.single))], 1) * GRID) / GRID


def thresholds(good: np.ndarray, bad: np.ndarray, fallback: np.ndarray) -> np.ndarray:
    """The threshold of each column of scores, infinite where the column decides nothing."""
    out = np.full(fallback.shape[1], np.inf)
    if not len(bad):
        base = good if len(good) else fallback
        out[0] = np.quantile(base[:, 0], 1 - MISSED) if len(base) else np.inf
        return out
    left, n_good, n_bad = bad, max(1, len(good)), len(bad)
    kept = good
    while len(left):
        best = (0.0, -1, 0.0)
        for k in np.flatnonzero(np.isinf(out)):
            tries = np.unique(np.concatenate([kept[:, k], left[:, k]]))
            above = lambda x: len(x) - np.searchsorted(np.sort(x), tries, "right")  # noqa: E731, B023
            gain = above(left[:, k]) / n_bad - PRICE * above(kept[:, k]) / n_good
            at = int(np.argmax(gain))
            if gain[at] > best[0]:
                # Half way to the next score, so that rows like the ones kept stay.
                best = (float(gain[at]), int(k), float((tries[at] + tries[min(at + 1, len(tries) - 1)]) / 2))
        if best[1] < 0:
            break
        _, k, out[best[1]] = best
        left, kept = left[left[:, k] <= out[k]], kept[kept[:, k] <= out[k]]
    return out


def _drawn(salt: str, want: int, of: int, *columns: str):
    """Rows that a hash of the columns picks, twice as many as wanted."""
    return F.pmod(F.xxhash64(*columns, F.lit(salt)), F.lit(1_000_003)) < min(1.0, 2 * want / max(1, of)) * 1_000_003


def _rows(df: DataFrame, salt: str, want: int, *columns: str) -> np.ndarray:
    """Of these columns (long) at most want rows, the first by hash."""
    few = df.select("doc_id", *columns).orderBy(F.xxhash64("doc_id", *columns, F.lit(salt)), "doc_id", *columns).limit(want)
    return np.array([list(r) for r in few.select(*columns).collect()], np.int64).reshape(-1, len(columns))


def thresholds_of(scored: DataFrame, fallback: np.ndarray) -> np.ndarray:
    """thresholds() of the rows (good, scores), of any number: a histogram of each column, bounded by GRID, comes to the driver for each threshold found."""
    out = np.full(fallback.shape[1], np.inf)
    total = scored.agg(F.count_if("good").alias("good"), F.count_if(~F.col("good")).alias("bad")).first()

    def histogram(rows: DataFrame) -> list[np.ndarray]:
        cells = rows.select("good", F.posexplode("scores").alias("k", "x")).groupBy("k", "x")
        t = cells.agg(F.count_if("good").alias("good"), F.count_if(~F.col("good")).alias("bad")).toArrow().sort_by([("k", "ascending"), ("x", "ascending")])
        cell = np.stack([t[c].to_numpy() for c in ("k", "x", "good", "bad")], 1).astype(float)
        return [cell[cell[:, 0] == k, 1:] for k in range(len(out))]

    if not total["bad"]:
        if not total["good"]:
            return thresholds(fallback[:0], fallback[:0], fallback)
        x, n = histogram(scored)[0][:, :2].T
        place = (n.sum() - 1) * (1 - MISSED)
        at = np.searchsorted(np.cumsum(n), [math.floor(place), math.ceil(place)], "right")
        out[0] = x[at[0]] + (x[at[1]] - x[at[0]]) * (place - math.floor(place))
        return out
    n_good, n_bad = max(1, total["good"]), total["bad"]
    while True:
        best = (0.0, -1, 0.0)
        for k, cell in enumerate(histogram(scored)):
            if np.isinf(out[k]) and len(cell) and cell[:, 2].any():
                tries, above = cell[:, 0], cell[:, 1:].sum(0) - np.cumsum(cell[:, 1:], 0)
                gain = above[:, 1] / n_bad - PRICE * above[:, 0] / n_good
                at = int(np.argmax(gain))
                if gain[at] > best[0]:
                    # Half way to the next score, so that rows like the ones kept stay.
                    best = (float(gain[at]), k, float((tries[at] + tries[min(at + 1, len(tries) - 1)]) / 2))
        if best[1] < 0:
            return out
        _, k, out[best[1]] = best
        scored = scored.where(F.col("scores")[k] <= float(out[k]))


def fitted(stats: DataFrame, labels: DataFrame) -> tuple[Forests, np.ndarray, DataFrame]:
    """(forests, thresholds, (held, good, scores) of all labelled rows that pass the base rules)."""
    passed = stats.where(~base_failed())
    sample = _rows(passed.where(_drawn("forest", TREES * SAMPLE, stats.count(), "doc_id", *STATS)), "forest", TREES * SAMPLE, *STATS)
    forests = Forests(features(sample))
    shared = stats.sparkSession.sparkContext.broadcast(forests)
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("long").alias("quality")).where("doc_id is not null and quality is not null")
    known = known.groupBy("doc_id").agg(F.min("quality").alias("quality"))
    held = (F.pmod(F.xxhash64("doc_id", F.lit("part")), F.lit(5)) == 0).alias("held")
    rows = known.select("doc_id", held, (F.col("quality") == 1).alias("good")).join(passed, "doc_id").select("held", "good", *STATS)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = shared.value.scores(features(np.stack([np.asarray(batch[c]) for c in STATS], 1)))
            at = pa.array(np.arange(len(x) + 1) * x.shape[1], pa.int32())
            yield pa.RecordBatch.from_arrays([batch["held"], batch["good"], pa.ListArray.from_arrays(at, pa.array(x.ravel()))], ["held", "good", "scores"])

    scored = spool(rows.mapInArrow(run, "held boolean, good boolean, scores array<double>"), "scored")
    return forests, thresholds_of(scored.where("not held"), forests.scores(features(sample))), scored


def calibrate(stats: DataFrame, labels: DataFrame) -> tuple[Forests, np.ndarray, tuple[np.ndarray, np.ndarray]]:
    """(forests, thresholds, scores of the good and of the bad rows of the held-out fifth); for tables whose labels the driver can hold."""
    forests, limits, scored = fitted(stats, labels)
    rows = scored.where("held").select("good", "scores").collect()
    part = lambda good: np.array([r["scores"] for r in rows if r["good"] == good]).reshape(-1, len(limits))
    return forests, limits, (part(True), part(False))


def held_out(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """(n_good, n_bad, lost, caught): shares of the good and bad labelled rows of the held-out fifth that pass the base rules and are dropped."""
    _, limits, scored = fitted(spool(statistics(docs), "statistics"), labels)
    over = F.lit(False)
    for k, x in enumerate(limits):
        if np.isfinite(x):
            over = over | (F.col("scores")[k] / float(x) > 1)
    share = lambda mask: F.coalesce(F.avg(F.when(mask, over.cast("double"))), F.lit(0.0))
    good = F.col("good")
    return scored.where("held").agg(F.count_if(good).alias("n_good"), F.count_if(~good).alias("n_bad"), share(good).alias("lost"), share(~good).alias("caught"))


def judge(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, the statistics, score, base_failed, kept for each document."""
    stats = spool(statistics(docs), "statistics")
    forests, limits, _ = fitted(stats, labels)
    shared = docs.sparkSession.sparkContext.broadcast((forests, limits))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forests, limits = shared.value
        for batch in batches:
            x = features(np.stack([np.asarray(batch[c]) for c in STATS], 1))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array((forests.scores(x) / limits).max(1))], [*batch.schema.names, "score"])

    shape = "doc_id long, " + ", ".join(f"{c} long" for c in STATS) + ", score double"
    scored = stats.mapInArrow(run, shape)
    return scored.withColumn("base_failed", base_failed()).withColumn("kept", ~F.col("base_failed") & (F.col("score") <= 1))


def base_failed():
    return (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
