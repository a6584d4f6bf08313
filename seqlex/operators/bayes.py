"""Naive Bayes on token counts in the workers: a sequence is cut once, adds to the counts of the classes that it teaches, and stays as token numbers where it is to be
scored. So neither sequences nor tokens are shuffled, and the model, a number for each token and class, is all that the driver holds.

A cutter numbers the tokens of sequences: `size` numbers in all, and a call on (keys, sequences) gives the numbers of all tokens and the place of the sequence of each, in order. One
of several vocabularies has their `sizes`, and `each` gives what the call gives for each. `at_once` are the bases that it is given at once, where it says so."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqlex.sources.tables import stored

#: Bases that a worker cuts at once.
CUT = 1 << 20
PARTS = "cut int, y string, token int, n long, marks array<struct<id:long,y:string>>, ids array<int>"
_schema = pa.schema([("cut", pa.int32()), ("y", pa.string()), ("token", pa.int32()), ("n", pa.int64()), ("marks", pa.list_(pa.struct([("id", pa.int64()), ("y", pa.string())]))), ("ids", pa.list_(pa.int32()))])


def _filled(rows: int, **columns) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([columns[f.name].cast(f.type) if f.name in columns else pa.nulls(rows, f.type) for f in _schema], schema=_schema)


def _lists(values: pa.Array, owner: np.ndarray, rows: int) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(np.bincount(owner, minlength=rows))]), pa.int32()), values)


def sizes_of(cutter: Callable) -> list[int]:
    return getattr(cutter, "sizes", None) or [cutter.size]


def parts(rows: DataFrame, cutter: Callable) -> DataFrame:
    """Of (key, seq, marks array<(id, y, test)>): the training marks' counts (y, token, n), token -1 for the number of sequences, a row for each task at most; and (marks, ids) of
    each sequence that test marks stand at; `cut` is the place of the cutter's vocabulary. Sequences of a batch that are equal are cut once."""
    shared = rows.sparkSession.sparkContext.broadcast(cutter)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cut = shared.value
        sizes, counts, most = sizes_of(cut), {}, getattr(cut, "at_once", CUT)
        for batch in batches:
            if not batch.num_rows:
                continue
            coded = batch["seq"].dictionary_encode()
            which, seqs = np.asarray(coded.indices), coded.dictionary.to_pylist()
            keys = np.zeros(len(seqs), np.int64)
            keys[which] = np.asarray(batch["key"])
            lists = batch["marks"]
            marks, at = lists.flatten(), np.asarray(lists.offsets)
            owner, test = np.repeat(which, np.diff(at)), np.asarray(marks.field("test"))
            classes = marks.field("y").dictionary_encode()
            label, names = np.asarray(classes.indices), classes.dictionary.to_pylist()
            taught = {}
            for k, y in enumerate(names):
                times = np.bincount(owner[(label == k) & ~test], minlength=len(seqs))
                if times.any():
                    taught[y] = times
                    for j, n in enumerate(sizes):
                        counts.setdefault((j, y), np.zeros(n + 1, np.int64))[-1] += times.sum()
            asked = np.flatnonzero(test)
            asked = asked[np.argsort(owner[asked], kind="stable")]
            a = 0
            while a < len(seqs):
                b, size = a, 0
                while b < len(seqs) and (b == a or size + len(seqs[b]) <= most):
                    size, b = size + len(seqs[b]), b + 1
                own = asked[(owner[asked] >= a) & (owner[asked] < b)]
                for j, (ids, of) in enumerate(cut.each(keys[a:b], seqs[a:b]) if hasattr(cut, "each") else [cut(keys[a:b], seqs[a:b])]):
                    for y, times in taught.items():
                        n = times[a:b]
                        if n.any():
                            counts[j, y][:-1] += np.bincount(ids, n[of], sizes[j]).astype(np.int64)
                    if len(own):
                        found, nth = np.unique(owner[own] - a, return_inverse=True)
                        place = np.full(b - a, -1)
                        place[found] = np.arange(len(found))
                        keep = place[of] >= 0
                        fields = marks.take(pa.array(own))
                        said = pa.StructArray.from_arrays([fields.field("id"), fields.field("y")], ["id", "y"])
                        yield _filled(len(found), cut=pa.array([j] * len(found)), marks=_lists(said, nth, len(found)), ids=_lists(pa.array(ids[keep], pa.int32()), place[of[keep]], len(found)))
                a = b
        for (j, y), n in counts.items():
            token = np.flatnonzero(n)
            yield _filled(len(token), cut=pa.array([j] * len(token)), y=pa.array([y] * len(token), pa.string()), token=pa.array(np.where(token == sizes[j], -1, token)), n=pa.array(n[token]))

    cores = rows.sparkSession.sparkContext.defaultParallelism
    # A task's counts are as many whatever it reads, so there are a few tasks a core at most.
    return rows.select("key", "seq", "marks").coalesce(4 * cores).mapInArrow(run, PARTS)


@dataclass
class Model:
    """weight[c, t], prior[c] of classes c, named "task|label"; a token that no training sequence has weighs nothing."""

    names: list[str]
    weight: np.ndarray
    prior: np.ndarray


def learn(cells: DataFrame, size: int) -> Model:
    """Of (y, token, n): logs of smoothed token shares and of class shares, tokens and sequences of all classes taken together for the number of known tokens and the total."""
    got = cells.groupBy("y", "token").agg(F.sum("n").alias("n")).toArrow()
    y = got["y"].combine_chunks().dictionary_encode() if got.num_rows else pa.array([], pa.string()).dictionary_encode()
    found = y.dictionary.to_pylist()
    names = sorted(found)
    order = np.array([names.index(x) for x in found], np.int64)
    counts = np.zeros((len(names), size + 1), np.int64)
    # Token -1 is the last column.
    counts[order[np.asarray(y.indices)] if found else [], got["token"].to_numpy()] = got["n"].to_numpy()
    rows, counts = counts[:, -1], counts[:, :-1]
    known, total = counts.any(axis=0), counts.sum(axis=1, keepdims=True)
    weight = np.where(known & (total > 0), np.log((counts + 1.0) / np.maximum(1, total + known.sum())), 0.0)
    return Model(names, weight, np.log(rows / max(1, rows.sum())))


def predicted(asked: DataFrame, model: Model) -> DataFrame:
    """(id, task, y, yhat) of (marks, ids): the best of the classes of a mark's own task, of equals the one of the greater name. Marks of a task without a class go."""
    shared = asked.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        tasks: dict[str, list[int]] = {}
        for c, name in enumerate(m.names):
            tasks.setdefault(name.rpartition("|")[0], []).append(c)
        for batch in batches:
            for start in range(0, batch.num_rows, 1000):
                part = batch.slice(start, 1000)
                sizes = [np.diff(np.asarray(part[x].offsets)) for x in ("marks", "ids")]
                owner, of = (np.repeat(np.arange(part.num_rows), n) for n in sizes)
                ids, marks = np.asarray(part["ids"].flatten()), part["marks"].flatten()
                key = np.asarray(marks.field("id"))
                coded = marks.field("y").dictionary_encode()
                label, said = np.asarray(coded.indices), [x.rpartition("|") for x in coded.dictionary.to_pylist()]
                for task in dict.fromkeys(x[0] for x in said):
                    if task not in tasks:
                        continue
                    own = np.flatnonzero(np.isin(label, [k for k, x in enumerate(said) if x[0] == task]))
                    best, yhat = np.full(len(own), -np.inf), np.zeros(len(own), np.int32)
                    for c in tasks[task]:
                        score = (np.bincount(of, m.weight[c][ids], part.num_rows) + m.prior[c])[owner[own]]
                        better = score >= best
                        best[better], yhat[better] = score[better], int(m.names[c].rpartition("|")[2])
                    y = np.array([int(x[2]) for x in said], np.int32)[label[own]]
                    yield pa.RecordBatch.from_arrays([pa.array(key[own]), pa.array([task] * len(own), pa.string()), pa.array(y), pa.array(yhat)], ["id", "task", "y", "yhat"])

    return asked.select("marks", "ids").mapInArrow(run, "id long, task string, y int, yhat int")


def tried_each(rows: DataFrame, cutter: Callable) -> list[DataFrame]:
    """For each vocabulary of the cutter (id, task, y, yhat) of the test marks of rows, as parts() takes them, by the model of the others. Marks of one id are one."""
    kept, out = stored(parts(rows, cutter)), []
    for j, size in enumerate(sizes_of(cutter)):
        own = kept.where(F.col("cut") == j)
        out.append(predicted(own.where("marks IS NOT NULL"), learn(own.where("marks IS NULL"), size)).distinct())
    return out


def tried(rows: DataFrame, cutter: Callable) -> DataFrame:
    """tried_each() of a cutter of one vocabulary."""
    return tried_each(rows, cutter)[0]
