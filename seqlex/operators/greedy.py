"""Greedy dictionary tokenisation with a small look-ahead, vectorised, and exact in parallel over chunks of a contig.

At a place, the dictionary words of 4 to 12 bases that start there are its candidates; a pick rule (random by key, longest,
shortest) takes one, else a 3-mer serves, else a single base. Of the place and the next two, the longest offer wins, the earliest of
equals, and the scan goes on behind it. All places' offers are computed at once from rolling two-bit codes; only the chain of
jumps is walked. A jump is at most 14 bases, so a chunk is a map from 14 entries to exits (`transfer`); composing the maps of
a contig gives each chunk its true entry, and chunks are then walked independently (`greedy_chunked`).
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqlex.functions.bases import bases

REACH = 14
#: Bases that a worker scans at once.
SCANNED = 1 << 20
TOKENS = "array<struct<pos:int,len:int,token:string,kind:string>>"
KINDS = np.array(["one", "three", "motif"], object)

_code = np.full(256, 4, np.uint8)
for _i, _b in enumerate(b"ACGT"):
    _code[_b] = _i


@dataclass
class PackedDict:
    """Dictionary words by length, as sorted two-bit codes. Its size is that of the vocabulary, whatever the data."""

    words: list[str]
    min_len: int = 4
    max_len: int = 12
    codes: dict[int, np.ndarray] = field(default_factory=dict)

    def __post_init__(self) -> None:
        for n in range(self.min_len, self.max_len + 1):
            own = [w for w in self.words if len(w) == n and set(w) <= set("ACGT")]
            self.codes[n] = np.sort(np.array([sum(int(_code[ord(c)]) << 2 * (n - 1 - k) for k, c in enumerate(w)) for w in own], np.int64))

    @cached_property
    def tables(self) -> dict[int, np.ndarray]:
        """By length, for each code whether it is a word: 22 MB in all, for words of 12 bases at most."""
        out = {}
        for n, words in self.codes.items():
            if len(words) and n <= 12:
                out[n] = np.zeros(4**n, bool)
                out[n][words] = True
        return out

    def matches(self, seq: bytes) -> np.ndarray:
        """Bit n of place i is set if a word of n bases starts at i."""
        c = _code[np.frombuffer(seq, np.uint8)].astype(np.int64)
        size = len(c)
        out = np.zeros(size, np.int32)
        blocked = np.concatenate([[0], np.cumsum(c == 4)])
        rolled = np.zeros(size, np.int64)
        base = np.where(c == 4, 0, c)
        for n in range(1, self.max_len + 1):
            if size < n:
                break
            rolled = rolled[: size - n + 1] * 4 + base[n - 1 :]
            words = self.codes.get(n)
            if words is not None and len(words):
                known = self.tables[n][rolled] if n in self.tables else words[np.minimum(np.searchsorted(words, rolled), len(words) - 1)] == rolled
                hit = known & (blocked[n:] == blocked[: size - n + 1])
                out[: size - n + 1] |= hit.astype(np.int32) << n
        return out


def draw(seed: int, contig, pos: int, n: int) -> int:
    """The keyed draw: independent of partitioning and retries."""
    return int(hashlib.md5(f"{seed}|{contig}|{pos}".encode()).hexdigest()[:8], 16) % n


def offers(words: PackedDict, seq: bytes, contig, start: int, total: int, pick: str, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """(length, kind) offered at each place of seq, which begins at place start of a contig of total bases."""
    mask = words.matches(seq)
    n = len(seq)
    c = _code[np.frombuffer(seq, np.uint8)]
    clean = np.zeros(n, bool)
    if n > 2:
        clean[: n - 2] = (c[:-2] < 4) & (c[1:-1] < 4) & (c[2:] < 4)
    length = np.where(clean, 3, 1)
    kind = np.where(clean, 1, 0)
    has = np.flatnonzero(mask)
    kind[has] = 2
    low = np.log2(mask[has] & -mask[has]).astype(np.int64)
    high = np.floor(np.log2(mask[has])).astype(np.int64)
    if pick == "random":
        chosen = low.copy()
        for k in np.flatnonzero(low != high):
            m = int(mask[has[k]])
            lens = [b for b in range(words.min_len, words.max_len + 1) if m >> b & 1]
            chosen[k] = lens[draw(seed, contig, start + int(has[k]), len(lens))]
        length[has] = chosen
    else:
        length[has] = high if pick == "longest" else low
    return length, kind


def winners(length: np.ndarray, max_offset: int) -> np.ndarray:
    """Offset of the winning place among each place and the next max_offset ones."""
    best, offset = length.copy(), np.zeros(len(length), np.int64)
    for o in range(1, max_offset + 1):
        if o < len(length):
            better = np.zeros(len(length), bool)
            better[:-o] = length[o:] > best[:-o]
            best[better] = length[np.flatnonzero(better) + o]
            offset[better] = o
    return offset


def walk(length: np.ndarray, offset: np.ndarray, entry: int, end: int) -> tuple[list[int], int]:
    """(winning places, exit) from entry until end."""
    at, places = entry, []
    off, size = offset.tolist(), length.tolist()
    while at < end:
        p = at + off[at]
        places.append(p)
        at = p + size[p]
    return places, at


def exits(length: np.ndarray, offset: np.ndarray, end: int) -> tuple[list[int], list[int]]:
    """(exit, tokens on the way) for each of REACH entries. Walks merge soon, so only the first goes all the way; the others stop where they meet one that is done."""
    off, size = offset.tolist(), length.tolist()
    left: dict[int, int] = {}
    out: dict[int, int] = {}
    for entry in range(REACH):
        at, path = entry, []
        while at < end and at not in left:
            path.append(at)
            p = at + off[at]
            at = p + size[p]
        to, n = (at, 0) if at >= end else (out[at], left[at])
        for k, x in enumerate(reversed(path), 1):
            left[x], out[x] = n + k, to
        if not path and at == entry:
            left.setdefault(entry, n)
            out.setdefault(entry, to)
    return [out[e] for e in range(REACH)], [left[e] for e in range(REACH)]


def _arrays(rows: list[tuple[list[int], list[int], list[str], list[str]]]) -> pa.Array:
    ends = np.cumsum([0] + [len(r[0]) for r in rows]).astype(np.int32)
    flat = [[x for r in rows for x in r[k]] for k in range(4)]
    items = pa.StructArray.from_arrays([pa.array(flat[0], pa.int32()), pa.array(flat[1], pa.int32()), pa.array(flat[2], pa.string()), pa.array(flat[3], pa.string())], ["pos", "len", "token", "kind"])
    return pa.ListArray.from_arrays(pa.array(ends), items)


def _emit(seq: str, places: list[int], length: np.ndarray, kind: np.ndarray, start: int, skip: str, since: int, end: int) -> tuple[list, list, list, list]:
    pos, lens, kinds, at = [], [], [], since
    for p in places:
        if skip == "emit":
            pos += [start + x for x in range(at, p)]
            lens += [1] * (p - at)
            kinds += ["one"] * (p - at)
        pos.append(start + p)
        lens.append(int(length[p]))
        kinds.append(KINDS[kind[p]])
        at = p + int(length[p])
    return pos, lens, [seq[p - start : p - start + n] for p, n in zip(pos, lens, strict=True)], kinds


def greedy_tokenize(df: DataFrame, words: list[str], *, pick: str = "random", seed: int = 7, max_offset: int = 2, skip: str = "drop", min_len: int = 4, max_len: int = 12) -> DataFrame:
    """(contig, n_bases, tokens) for (contig, seq), and lang where there is one. Sequences are handled one by one; cut very long ones and use greedy_chunked."""
    more = ["lang"] if "lang" in df.columns else []
    packed = df.sparkSession.sparkContext.broadcast(PackedDict(words, min_len, max_len))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, batch.num_rows, 256):
                part, rows, sizes = batch.slice(a, 256), [], []
                for contig, seq in zip(part["contig"].to_pylist(), part["seq"].to_pylist(), strict=True):
                    seq = seq or ""
                    raw = seq.encode()
                    length, kind = offers(packed.value, raw, contig, 0, len(raw), pick, seed) if raw else (np.zeros(0, int),) * 2
                    places, _ = walk(length, winners(length, max_offset), 0, len(raw))
                    rows.append(_emit(seq, places, length, kind, 0, skip, 0, len(raw)))
                    sizes.append(len(raw))
                yield pa.RecordBatch.from_arrays([part["contig"], pa.array(sizes, pa.int64()), _arrays(rows), *(part[c] for c in more)], ["contig", "n_bases", "tokens", *more])

    return df.select("contig", "seq", *more).mapInArrow(run, f"contig long, n_bases long, tokens {TOKENS}" + "".join(f", {c} string" for c in more))


def n_tokens(words: PackedDict, keys: list, seqs: list[str], pick: str = "random", seed: int = 7, max_offset: int = 2, size: int = SCANNED // 8) -> list[int]:
    """The number of greedy_tokenize's tokens of each sequence. Pieces of size bases at most are matched at once, short sequences together with Ns between them that offer nothing; a
    walk enters the next piece of a long sequence where it left the one before."""
    gap, halo = max(1, max_offset), max_offset + words.max_len
    lens: dict[int, list[int]] = {}
    parts = [(k, s) for k, seq in enumerate(seqs) for s in range(0, len(seq), size)]
    at, counts, a = [0] * len(seqs), [0] * len(seqs), 0
    while a < len(parts):
        texts, starts, total, b = [], [], 0, a
        while b < len(parts) and (b == a or total + len(seqs[parts[b][0]]) - parts[b][1] <= size):
            k, s = parts[b]
            texts.append(seqs[k][s : s + size + halo])
            starts.append(total)
            total, b = total + len(texts[-1]) + gap, b + 1
        raw = "".join(t + "N" * gap for t in texts).encode()
        mask, clean = words.matches(raw), _code[np.frombuffer(raw, np.uint8)] < 4
        length = np.ones(len(raw), np.int64)
        length[:-2][clean[:-2] & clean[1:-1] & clean[2:]] = 3
        has = np.flatnonzero(mask)
        low, high = np.log2(mask[has] & -mask[has]).astype(np.int64), np.floor(np.log2(mask[has])).astype(np.int64)
        length[has] = high if pick == "longest" else low
        if pick == "random":
            several = has[low != high]
            part = np.searchsorted(starts, several, "right") - 1
            for i, p in zip(several.tolist(), part.tolist(), strict=True):
                m, (k, s) = int(mask[i]), parts[a + p]
                if m not in lens:
                    lens[m] = [n for n in range(words.min_len, words.max_len + 1) if m >> n & 1]
                length[i] = lens[m][draw(seed, keys[k], s + i - starts[p], len(lens[m]))]
        for start, text in zip(starts, texts, strict=True):
            length[start + len(text) : start + len(text) + gap] = 0
        won = np.arange(len(raw)) + winners(length, max_offset)
        behind = (won + length[won]).tolist()
        for (k, s), start in zip(parts[a:b], starts, strict=True):
            i, end, n = start + at[k] - s, start + min(size, len(seqs[k]) - s), 0
            while i < end:
                i, n = behind[i], n + 1
            at[k], counts[k] = s + i - start, counts[k] + n
        a = b
    return counts


def token_counts(df: DataFrame, words: list[str], *, pick: str = "random", seed: int = 7, max_offset: int = 2, column: str = "seq") -> DataFrame:
    """(contig, n_bases, n_tokens): the numbers of greedy_tokenize, without its tokens. A column `text` is turned to bases in the workers."""
    packed = df.sparkSession.sparkContext.broadcast(PackedDict(words))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, batch.num_rows, 256):
                part = batch.slice(a, 256)
                seqs = [s or "" for s in part[column].to_pylist()]
                seqs = [bases(s) for s in seqs] if column == "text" else seqs
                found = n_tokens(packed.value, part["contig"].to_pylist(), seqs, pick, seed, max_offset)
                yield pa.RecordBatch.from_arrays([part["contig"], pa.array([len(s) for s in seqs], pa.int64()), pa.array(found, pa.int64())], ["contig", "n_bases", "n_tokens"])

    return df.select("contig", column).mapInArrow(run, "contig long, n_bases long, n_tokens long")


class Cutter:
    """The tokens of greedy_tokenize as numbers, for sequences with their keys: words first, then 3-mers and bases. All sequences are matched in one scan, with an N between them that no
    word and no 3-mer holds, and a draw is made where the walk comes by and the longest word there would win."""

    def __init__(self, words: list[str], pick: str = "random", seed: int = 7) -> None:
        self.packed, self.pick, self.seed = PackedDict(words), pick, seed
        known = [w for w in dict.fromkeys(words) if self.packed.min_len <= len(w) <= self.packed.max_len and set(w) <= set("ACGT")]
        threes = [a + b + c for a in "ACGT" for b in "ACGT" for c in "ACGT"]
        self.number = {t: i for i, t in enumerate([*known, *threes, *"ACGTN"])}
        self.size = len(self.number)

    def __call__(self, keys: np.ndarray, seqs: list[str]) -> tuple[np.ndarray, np.ndarray]:
        text = "N".join(seqs) + "NNN"
        raw = text.encode()
        mask = self.packed.matches(raw)
        clean = _code[np.frombuffer(raw, np.uint8)] < 4
        fixed = np.ones(len(raw), np.int64)
        fixed[:-2][clean[:-2] & clean[1:-1] & clean[2:]] = 3
        has = np.flatnonzero(mask)
        low, high = np.log2(mask[has] & -mask[has]).astype(np.int64), np.floor(np.log2(mask[has])).astype(np.int64)
        top = fixed.copy()
        fixed[has] = {"random": np.where(low == high, low, 0), "longest": high, "shortest": low}[self.pick]
        top[has] = low if self.pick == "shortest" else high
        lens = {m: [n for n in range(self.packed.min_len, self.packed.max_len + 1) if m >> n & 1] for m in np.unique(mask[has]).tolist()}
        fixed, top, mask, number, md5 = fixed.tolist(), top.tolist(), mask.tolist(), self.number, hashlib.md5
        ids: list[int] = []
        sizes, start = [], 0
        for key, seq in zip(keys.tolist(), seqs, strict=True):
            at, end, before, said = start, start + len(seq), len(ids), f"{self.seed}|{key}|"
            while at < end:
                best, place = 0, at
                for p in range(at, min(at + 3, end)):
                    if top[p] > best:
                        n = fixed[p]
                        if not n:
                            own = lens[mask[p]]
                            n = own[int.from_bytes(md5(f"{said}{p - start}".encode()).digest()[:4], "big") % len(own)]
                        if n > best:
                            best, place = n, p
                at = place + best
                ids.append(number[text[place:at]])
            sizes.append(len(ids) - before)
            start = end + 1
        return np.array(ids, np.int64), np.repeat(np.arange(len(seqs)), sizes)


def transfer(chunks: DataFrame, words: list[str], *, size: int, pick: str = "random", seed: int = 7, max_offset: int = 2) -> DataFrame:
    """(contig, chunk_no, exits, counts): where a scan that enters a chunk at offset 0..13 enters the next one, and the tokens on the way."""
    packed = chunks.sparkSession.sparkContext.broadcast(PackedDict(words))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            exits_, counts = [], []
            for contig, start, n, bases in zip(*(batch[c].to_pylist() for c in ("contig", "start", "n", "bases")), strict=True):
                raw = bases.encode()
                length, _ = offers(packed.value, raw, contig, start, n, pick, seed) if raw else (np.zeros(0, int),) * 2
                offset, end = winners(length, max_offset), min(size, n - start)
                to, n_tokens = exits(length, offset, end)
                exits_.append([x - size for x in to])
                counts.append(n_tokens)
            yield pa.RecordBatch.from_arrays([batch["contig"], batch["chunk_no"], pa.array(exits_, pa.list_(pa.int32())), pa.array(counts, pa.list_(pa.int64()))], ["contig", "chunk_no", "exits", "counts"])

    return chunks.mapInArrow(run, "contig long, chunk_no int, exits array<int>, counts array<long>")


def compose(maps: DataFrame) -> DataFrame:
    """(contig, chunk_no, entry, token_offset): a walk over the small maps of a contig, in Arrow; C rows of 28 numbers for C chunks."""

    def run(rows: pa.Table) -> pa.Table:
        rows = rows.sort_by("chunk_no")
        entry, done, out, before = 0, 0, [], []
        for exits, counts in zip(rows["exits"].to_pylist(), rows["counts"].to_pylist(), strict=True):
            out.append(entry)
            before.append(done)
            done, entry = done + counts[entry], max(0, exits[entry])
        return pa.table({"contig": rows["contig"], "chunk_no": rows["chunk_no"], "entry": pa.array(out, pa.int32()), "token_offset": pa.array(before, pa.int64())})

    return maps.groupBy("contig").applyInArrow(run, "contig long, chunk_no int, entry int, token_offset long")


def greedy_chunked(chunks: DataFrame, words: list[str], *, size: int, pick: str = "random", seed: int = 7, max_offset: int = 2) -> DataFrame:
    """(contig, chunk_no, token_offset, tokens): the same tokens as of the whole contig, each chunk on its own."""
    entries = compose(transfer(chunks, words, size=size, pick=pick, seed=seed, max_offset=max_offset))
    packed = chunks.sparkSession.sparkContext.broadcast(PackedDict(words))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for contig, start, n, bases, entry in zip(*(batch[c].to_pylist() for c in ("contig", "start", "n", "bases", "entry")), strict=True):
                raw = bases.encode()
                length, kind = offers(packed.value, raw, contig, start, n, pick, seed) if raw else (np.zeros(0, int),) * 2
                places, _ = walk(length, winners(length, max_offset), entry, min(size, n - start))
                rows.append(_emit(bases, places, length, kind, start, "drop", entry, size))
            yield pa.RecordBatch.from_arrays([batch["contig"], batch["chunk_no"], batch["token_offset"], _arrays(rows)], ["contig", "chunk_no", "token_offset", "tokens"])

    return chunks.join(entries, ["contig", "chunk_no"]).mapInArrow(run, f"contig long, chunk_no int, token_offset long, tokens {TOKENS}")


def scan_motifs(df: DataFrame, words: list[str], min_len: int = 4, max_len: int = 12) -> DataFrame:
    """(contig, start, end) of all occurrences of all words, overlapping ones included."""
    packed = df.sparkSession.sparkContext.broadcast(PackedDict(words, min_len, max_len))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for contig, seq in zip(batch["contig"].to_pylist(), batch["seq"].to_pylist(), strict=True):
                mask = packed.value.matches((seq or "").encode())
                at = [np.flatnonzero(mask >> n & 1) for n in range(min_len, max_len + 1)]
                start = np.concatenate(at)
                size = np.repeat(np.arange(min_len, max_len + 1), [len(x) for x in at])
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(start), contig, np.int64)), pa.array(start, pa.int64()), pa.array(start + size, pa.int64())], ["contig", "start", "end"])

    return df.select("contig", "seq").mapInArrow(run, "contig long, start long, end long")


def covered_seqs(df: DataFrame, words: list[str], column: str = "seq") -> DataFrame:
    """(seq, n): the bases under occurrences of words, a row for each different stretch (overlapping or touching occurrences are one) and batch, with its number. Each
    sequence is taken by itself in the workers, some together in one scan, so no occurrence is a row. A column `text` is turned to bases there."""
    packed = df.sparkSession.sparkContext.broadcast(PackedDict(words))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            seqs, a = [s or "" for s in batch[column].to_pylist()], 0
            while a < len(seqs):
                b, size = a, 0
                while b < len(seqs) and (b == a or size + len(seqs[b]) <= SCANNED):
                    size, b = size + len(seqs[b]) + 1, b + 1
                own = [bases(s) for s in seqs[a:b]] if column == "text" else seqs[a:b]
                # An N between sequences belongs to no word.
                raw = np.frombuffer(f"N{'N'.join(own)}N".encode(), np.uint8)
                mask, ends = packed.value.matches(raw.tobytes()), np.zeros(len(raw) + 1, np.int32)
                for n in range(packed.value.min_len, packed.value.max_len + 1):
                    at = np.flatnonzero(mask >> n & 1)
                    ends[at] += 1
                    ends[at + n] -= 1
                under = np.cumsum(ends[:-1]) > 0
                edges = np.flatnonzero(under[1:] != under[:-1])
                sizes = edges[1::2] - edges[::2]
                offsets = np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)
                found = pa.StringArray.from_buffers(len(sizes), pa.py_buffer(offsets.tobytes()), pa.py_buffer(raw[under].tobytes())).value_counts()
                yield pa.RecordBatch.from_arrays([found.field("values"), found.field("counts")], ["seq", "n"])
                a = b

    return df.select(column).mapInArrow(run, "seq string, n long")


def token_rows(tokenised: DataFrame, *keys: str) -> DataFrame:
    return tokenised.select(*(keys or ("contig",)), F.posexplode("tokens").alias("idx", "t")).select(*(keys or ("contig",)), "idx", "t.*")


def detokenize(tokens) -> F.Column:
    return F.array_join(F.transform(tokens, lambda t: t["token"]), "")
