"""Language identification: averaged hashed subword embeddings under a linear softmax, with calibrated rejection.

Training runs in numpy on the driver over a bounded sample of labelled rows: at most `sample_rows` rows and about `sample_bytes` bytes, as many of each
language, chosen by a hash of id and text, whole texts, those of over `LONG` bytes last. A model's size is that of its languages, so at most `languages` of them are
learnt, those with the most rows (1,000 by default, or 262 MB of weights). The trained embedding and output matrices are multiplied once, so that a prediction is a
mean of rows of one table of `BUCKETS` x languages: constant in size, whatever the corpus.

Defined results: a null text, or one without any letter, is `und` with score 0 and rejected. Without any labelled row every
text is `und`. Repeated rows are predicted alike, and ids that are null or repeat change neither the bounds of the sample nor that each language has a row in it;
only `doc_id`, `text` and `lang` are read, so other columns cannot clash.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import bound_batches, give_back, id_crc, slices, utf8

BUCKETS, LONG = 1 << 16, 1 << 20
#: Bytes that a worker cuts into grams at once; some 60 bytes of arrays each.
PIECE = 1 << 17
GAP = b"    "

_fold = np.full(256, 32, np.uint8)
_fold[97:123] = _fold[65:91] = np.arange(97, 123)
_fold[128:] = np.arange(128, 256)


def gram_ids(data: np.ndarray) -> list[np.ndarray]:
    """Bucket of the 3-byte and of the 4-byte gram that starts at each place; 0 where the gram has no letter. Other characters count as spaces."""
    b = _fold[data].astype(np.uint32)
    b = np.concatenate([b, np.full(3, 32, np.uint32)])
    three = b[:-3] | b[1:-2] << 8 | b[2:-1] << 16
    four = three | b[3:] << 24
    out = []
    for gram, blank, salt in ((three, 0x202020, 0x9E3779B1), (four, 0x20202020, 0x85EBCA77)):
        h = gram * np.uint32(salt)
        h = (h ^ (h >> np.uint32(15))) * np.uint32(0x2C1B3C6D)
        out.append(np.where(gram == blank, 0, 1 + ((h ^ (h >> np.uint32(16))) % np.uint32(BUCKETS - 1))))
    return out


@dataclass
class LanguageModel:
    labels: list[str]
    table: np.ndarray
    bias: np.ndarray
    temperature: float
    threshold: float

    def logits(self, texts: list[bytes]) -> np.ndarray:
        """A row for each text. The texts stand in one buffer with gaps, so no gram holds letters of two of them."""
        sizes = np.array([len(t) + len(GAP) for t in texts])
        buffer = np.frombuffer(GAP[:3] + GAP.join(texts) + GAP, np.uint8)
        starts = np.concatenate([[0], np.cumsum(sizes)])
        total, count = np.zeros((len(texts), len(self.labels))), np.zeros(len(texts), np.int64)
        for a in range(0, len(buffer), PIECE):
            # The sums of a piece go to the texts that its places belong to; a gram may end in the next piece.
            b = min(a + PIECE, len(buffer))
            first, last = (int(np.searchsorted(starts, x, "right")) - 1 for x in (a, b - 1))
            first, last = min(first, len(texts) - 1), min(last, len(texts) - 1)
            cuts = np.maximum(starts[first : last + 1] - a, 0)
            for ids in gram_ids(buffer[a : b + 3]):
                total[first : last + 1] += np.add.reduceat(self.table[ids[: b - a]], cuts, axis=0, dtype=np.float64)
                count[first : last + 1] += np.add.reduceat(ids[: b - a] > 0, cuts, dtype=np.int64)
        return total / np.maximum(count, 1)[:, None] + self.bias

    def probabilities(self, texts: list[bytes]) -> np.ndarray:
        return softmax(self.logits(texts) / self.temperature)


def softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(-1, keepdims=True))
    return e / e.sum(-1, keepdims=True)


def train(rows: list[tuple[str, str]], *, dims: int = 8, epochs: int = 6, rate: float = 0.5, reject: float = 0.001, seed: int = 1) -> LanguageModel | None:
    """Fit on (text, language) rows. Every fifth row is kept for calibration: the temperature is the one of least log loss, the
    threshold the score below which `reject` of its rightly classified rows fall, 0.5 at most."""
    labels = sorted({lang for _, lang in rows})
    if not labels:
        return None
    rng = np.random.default_rng(seed)
    k = len(labels)
    embed, out, bias = rng.normal(0, 0.1, (BUCKETS, dims)), rng.normal(0, 0.3, (dims, k)), np.zeros(k)
    embed[0] = 0
    known, features = {lang: i for i, lang in enumerate(labels)}, []
    for text, lang in rows:
        ids = np.concatenate(gram_ids(np.frombuffer(GAP[:3] + text.encode() + GAP, np.uint8)))
        ids, counts = np.unique(ids[ids > 0], return_counts=True)
        if len(ids):
            features.append((ids, counts / counts.sum(), known[lang]))
    held, fit = features[::5], [f for i, f in enumerate(features) if i % 5 or len(features) < 10]
    for epoch in range(epochs):
        step = rate * (1 - epoch / epochs)
        for i in rng.permutation(len(fit)):
            ids, share, y = fit[i]
            hidden = share @ embed[ids]
            error = softmax(hidden @ out + bias)
            error[y] -= 1
            back = out @ error
            out -= step * np.outer(hidden, error)
            bias -= 0.1 * step * error
            embed[ids] -= step * np.outer(share / share.max(), back) * 0.2
    model = LanguageModel(labels, (embed @ out).astype(np.float32), bias, 1.0, 0.0)
    model.table[0] = 0
    if held:
        z = np.array([s @ model.table[i] + bias for i, s, _ in held])
        y = np.array([y for *_, y in held])
        loss = {t: -np.log(np.maximum(softmax(z / t)[np.arange(len(y)), y], 1e-12)).mean() for t in 2.0 ** np.arange(-3, 4, 0.5)}
        model.temperature = float(min(loss, key=loss.get))
        p = softmax(z / model.temperature)
        right = p.max(1)[p.argmax(1) == y]
        model.threshold = float(min(0.5, np.quantile(right, reject))) if len(right) else 0.0
    del features, held, fit
    # The driver lives on; what training held goes back.
    give_back()
    return model


def sample(docs: DataFrame, sample_rows: int, *, sample_bytes: int = 64 << 20, languages: int = 1000) -> list[tuple[str, str]]:
    """(text, language) of labelled whole texts outside the held-out fold, within the bounds that the module states, at least one of each learnt language."""
    space = 1_000_003
    h = F.pmod(F.xxhash64(F.coalesce(F.col("doc_id").cast("string"), F.lit("")), "text", F.lit("langid")), F.lit(space)).cast("int")
    labelled = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & (id_crc("doc_id", 4) != 2)).select("doc_id", "text", "lang", h.alias("h"))
    sizes = labelled.groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.min("h").alias("least")).orderBy(F.desc("n"), "lang").limit(languages).collect()
    if not sizes:
        return []
    quota, share = max(1, sample_rows // len(sizes)), max(1, sample_bytes // len(sizes))
    # Twice the quota by the hash, and the row of the least one; the exact choice is then made among few.
    below = [(r["lang"], max(int(min(1.0, (2 * quota + 50) / r["n"]) * space), r["least"] + 1)) for r in sizes]
    limits = docs.sparkSession.createDataFrame(below, "lang string, below int")
    drawn = labelled.withColumn("lang", F.col("lang").cast("string")).join(F.broadcast(limits), "lang").where("h < below")
    drawn = drawn.withColumn("size", F.octet_length("text").cast("long"))
    order = Window.partitionBy("lang").orderBy(F.col("size") > LONG, "h", "text")
    chosen = drawn.withColumn("nth", F.row_number().over(order)).where(F.col("nth") <= quota)
    chosen = chosen.withColumn("before", F.sum("size").over(order.rowsBetween(Window.unboundedPreceding, 0)) - F.col("size")).where(F.col("before") < share)
    got = chosen.select("doc_id", "text", "lang").collect()
    return [(r["text"], r["lang"]) for r in sorted(got, key=lambda r: (str(r["doc_id"]), r["text"]))]


def predict(docs: DataFrame, model: LanguageModel | None) -> DataFrame:
    """doc_id, held_out, lang_pred, score, rejected for each document."""
    schema = "doc_id long, held_out boolean, lang_pred string, score double, rejected boolean"

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = batch.num_rows
            pred, best = np.full(n, "und", object), np.zeros(n)
            offsets, data = utf8(batch["text"])
            lettered = np.asarray(batch["lettered"].fill_null(False))
            for a, b in slices(offsets, PIECE) if model else ():
                rows = [i for i in range(a, b) if lettered[i]]
                if rows:
                    p = model.probabilities([data[offsets[i] : offsets[i + 1]].tobytes() for i in rows])
                    pred[rows] = np.array(model.labels, object)[p.argmax(1)]
                    best[rows] = np.minimum(p.max(1), 1.0)
            rejected = (pred == "und") | (best < (model.threshold if model else 1))
            yield pa.RecordBatch.from_arrays([batch["doc_id"], batch["held_out"], pa.array(pred, pa.string()), pa.array(best), pa.array(rejected)], ["doc_id", "held_out", "lang_pred", "score", "rejected"])
        give_back()

    bound_batches(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long"), (id_crc("doc_id", 4) == 2).alias("held_out"), "text", F.col("text").rlike(r"\p{L}").alias("lettered")).mapInArrow(score, schema)


def identify(docs: DataFrame, *, sample_rows: int = 4000) -> DataFrame:
    """Train on docs and predict every row of docs."""
    return predict(docs, train(sample(docs, sample_rows)))


def keep_recognised(docs: DataFrame, model: LanguageModel | None) -> DataFrame:
    """The rows of docs that the model does not reject; all columns pass through the workers unchanged."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            offsets, data = utf8(batch["text"])
            for a, b in slices(offsets, PIECE) if model else ():
                p = model.probabilities([data[offsets[i] : offsets[i + 1]].tobytes() for i in range(a, b)])
                yield batch.slice(a, b - a).filter(pa.array(p.max(1) >= model.threshold))
        give_back()

    bound_batches(docs.sparkSession)
    return docs.where(F.col("text").rlike(r"\p{L}")).mapInArrow(run, docs.schema)
