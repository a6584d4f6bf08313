"""SentencePiece encoding and decoding: unigram Viterbi over a double-array trie of pieces.

The pieces and their scores come from a vocabulary file (a parameter). The public file holds merge ranks as scores, so
`scores="zipf"` (default) reads a rank r as the log-frequency -log(1 + r); `scores="file"` takes the file's numbers as they are.

A text gets one leading space, spaces become the whitespace marker, and the path of the highest summed score over the pieces
is kept; of equal ones the one whose last piece is longer. A character that is no piece costs ten less than the worst score and is
written as its UTF-8 bytes. No piece holds a marker after another character (checked when the vocabulary is read), so the
best path of a text is the chain of the best paths of its words, cut before punctuation where no piece holds it after another character; these are kept in a memo of bounded size. Decoding joins pieces and bytes and
takes the leading space off. A marker character that stands in a text is written by bytes, so every text comes back exactly.

Defined results: a null text has null ids; an empty text none. Very long texts are encoded whole. Repeated rows are encoded alike;
only `doc_id` and `text` are read, so other columns cannot clash.
"""

from __future__ import annotations

import math
import re
import string
from array import array
from collections.abc import Iterator
from dataclasses import dataclass, field
from itertools import pairwise

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import give_back, slices, utf8

MARK = "▁"
DEFAULT_VOCABULARY = "/opt/tokenizers/piece_bpe_32k.model"
MEMO = 50_000
#: Chunks of fewer characters are kept in the memo and solved side by side, so many at a time; longer ones are walked one by one.
SHORT, BLOCK = 64, 8192


def double_array(keys: list[bytes], values: list[int]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(base, check, value) of the trie of the keys. From state s, byte c leads to t = base[s] + c + 1 if check[t] is s; value[t] is the key's
    value or -1. Built level by level: each state takes the first base at which all its children are free."""
    order = sorted(range(len(keys)), key=lambda i: keys[i])
    size = 1 << 12
    base, check, value = [0] * size, [-1] * size, [-1] * size
    check[0] = 0
    open_ = [(0, 0, len(order), 0)]
    low, family = 1, 1
    for state, a, b, depth in open_:
        if a < b and len(keys[order[a]]) == depth:
            value[state] = values[order[a]]
            a += 1
        groups, i = [], a
        while i < b:
            c, j = keys[order[i]][depth], i
            while j < b and keys[order[j]][depth] == c:
                j += 1
            groups.append((c, i, j))
            i = j
        if not groups:
            continue
        # Lone children fill the gaps from below; families start near the last family, so that no search walks over all of the array again.
        at = max(1, (low - groups[0][0] - 1) if len(groups) == 1 else family - 64)
        while True:
            if at + 300 > size:
                base += [0] * size
                check += [-1] * size
                value += [-1] * size
                size *= 2
            if all(check[at + c + 1] < 0 for c, _, _ in groups):
                break
            at += 1
        if len(groups) > 1:
            family = max(family, at)
        else:
            low = max(low, at + groups[0][0] + 1)
        base[state] = at
        for c, i, j in groups:
            check[at + c + 1] = state
            open_.append((at + c + 1, i, j, depth + 1))
    return np.array(base, np.int32), np.array(check, np.int32), np.array(value, np.int32)


@dataclass
class Pieces:
    pieces: list[str]
    scores: list[float]
    first_byte: int
    base: list = field(default_factory=list)
    check: list = field(default_factory=list)
    value: list = field(default_factory=list)
    memo: dict = field(default_factory=dict)
    old: dict = field(default_factory=dict)

    def __post_init__(self) -> None:
        special = {i for i, p in enumerate(self.pieces) if i < 3 or self.first_byte <= i < self.first_byte + 256}
        usable = [i for i in range(len(self.pieces)) if i not in special]
        self.unknown = min((self.scores[i] for i in usable), default=0.0) - 10
        if not len(self.base):
            base, check, value = double_array([self.pieces[i].encode() for i in usable], usable)
            # The one that follows the base is added here, not at each step.
            self.base, self.check, self.value = (base + 1).tolist(), check.tolist(), value.tolist()
        whole = [self.pieces[i] for i in usable]
        if any(MARK in p.lstrip(MARK) for p in whole):
            raise ValueError("a piece holds a marker after another character; words are not separable")
        alone = "\n" if not any("\n" in p and len(p) > 1 for p in whole) else ""
        # Marks of punctuation that no piece holds right after a character that is neither a marker nor punctuation: no path spans a cut there.
        every = set(string.punctuation)
        marks = every - {p[k] for p in whole for k in range(1, len(p)) if p[k] in every and p[k - 1] != MARK and p[k - 1] not in every}
        plain, stop = re.escape("".join(sorted(every))), re.escape("".join(sorted(marks)))
        word = f" *[^ {alone}{MARK}{plain}]++(?=[ {alone}{MARK}{stop}]|$)|" if marks else ""
        self.cut = re.compile(f"[{alone}{MARK}]|{word} *[^ {alone}{MARK}]+| +")
        spelled = [bytes([i - self.first_byte]) if self.first_byte <= i < self.first_byte + 256 else b"" if i < 3 else p.replace(MARK, " ").encode() for i, p in enumerate(self.pieces)]
        self.spelled = np.frombuffer(b"".join(spelled), np.uint8)
        self.spelled_size = np.array([len(x) for x in spelled], np.int64)
        self.spelled_at = np.concatenate([[0], np.cumsum(self.spelled_size)[:-1]])
        self.sizes = [len(p.encode()) for p in self.pieces]
        self.piece_size = np.array(self.sizes, np.int32)
        # A character spelled by bytes costs once, at its first byte.
        self.gain = np.array(self.scores, np.float64)
        self.gain[self.first_byte : self.first_byte + 256] = [0.0 if 0x80 <= c < 0xC0 else self.unknown for c in range(256)]
        self.trie = tuple(np.asarray(x, np.int32) for x in (self.base, self.check, self.value))

    def __getstate__(self) -> dict:
        return {k: np.asarray(v, np.int32) if k in ("base", "check", "value") else v for k, v in self.__dict__.items() if k not in ("memo", "old", "cut", "trie")} | {"alone": self.cut.pattern}

    def __setstate__(self, state: dict) -> None:
        self.__dict__ |= state
        self.trie = tuple(state[k] for k in ("base", "check", "value"))
        self.base, self.check, self.value = (x.tolist() for x in self.trie)
        self.memo, self.old, self.cut = {}, {}, re.compile(state["alone"])

    def viterbi(self, chunk: bytes) -> tuple[float, bytes]:
        """Best (score, ids as int32 bytes) of UTF-8 bytes whose spaces are markers already."""
        base, check, value, scores, sizes, unknown = self.base, self.check, self.value, self.scores, self.sizes, self.unknown
        n = len(chunk)
        # back: the piece that ends at a place, or minus the bytes of an unknown character.
        best, back = [-math.inf] * (n + 1), [0] * (n + 1)
        best[0] = 0.0
        i = 0
        while i < n:
            c = chunk[i]
            step = 1 if c < 0x80 else 2 if c < 0xE0 else 3 if c < 0xF0 else 4
            here, state, j, single = best[i], 0, i, False
            while j < n:
                t = base[state] + chunk[j]
                if check[t] != state:
                    break
                state = t
                j += 1
                v = value[t]
                if v >= 0:
                    if j - i == step:
                        single = True
                    s = here + scores[v]
                    if s > best[j]:
                        best[j] = s
                        back[j] = v
            if not single and here + unknown > best[i + step]:
                best[i + step] = here + unknown
                back[i + step] = -step
            i += step
        ids, j = [], n
        while j:
            v = back[j]
            if v >= 0:
                ids.append(v)
                j -= sizes[v]
            else:
                ids += [self.first_byte + x for x in reversed(chunk[j + v : j])]
                j += v
        ids.reverse()
        return best[n], array("i", ids).tobytes()

    def viterbi_many(self, chunks: list[bytes]) -> list[bytes]:
        """The ids that `viterbi` gives for each of many short chunks, found side by side. The chunks stand in one array, each with an end mark
        that no piece crosses. The trie is walked from all characters at once; then the pieces are taken by the place in the chunk at which they
        begin. Of one place no two pieces end at the same byte, so each round is one comparison, with the ties of the lone walk."""
        base, check, value = self.trie
        size = np.fromiter(map(len, chunks), np.int32, len(chunks)) + 1
        end = np.cumsum(size, dtype=np.int32) - 1
        first = end + 1 - size
        code = np.frombuffer(b" ".join(chunks) + b" ", np.uint8).astype(np.int32)
        code[end] = 256
        lead = np.flatnonzero((code < 0x80) | (code >= 0xC0) & (code < 256)).astype(np.int32)
        width = 1 + (code >= 0xC0).astype(np.int32) + (code >= 0xE0) + (code >= 0xF0)
        found, begin, at, state = [], lead, lead, np.zeros(len(lead), np.int32)
        while len(at):
            to = base[state] + code[at]
            on = check[to] == state
            state, begin, at = to[on], begin[on], at[on] + 1
            v = value[state]
            on = v >= 0
            found.append((begin[on], at[on], v[on]))
        begin, at, piece = (np.concatenate(x) for x in zip(*found, strict=True))
        single = np.zeros(len(code), bool)
        single[begin[at - begin == width[begin]]] = True
        lone = lead[~single[lead]]
        begin, at, piece = np.concatenate([begin, lone]), np.concatenate([at, lone + width[lone]]), np.concatenate([piece, -width[lone]])
        place = (np.arange(len(code), dtype=np.int32) - np.repeat(first, size))[begin].astype(np.int16)
        order = np.argsort(place, kind="stable")
        begin, at, piece = begin[order], at[order], piece[order]
        gain = np.where(piece >= 0, self.gain[piece], self.unknown)
        best, back = np.full(len(code), -math.inf), np.zeros(len(code), np.int32)
        best[first] = 0.0
        bounds = np.searchsorted(place[order], np.arange(int(size.max()) + 1, dtype=np.int16))
        for a, b in pairwise(bounds.tolist()):
            s, j = best[begin[a:b]] + gain[a:b], at[a:b]
            on = s > best[j]
            j = j[on]
            best[j], back[j] = s[on], piece[a:b][on]
        last, j, start = np.zeros(len(code), bool), end, first
        while len(j):
            last[j] = True
            v = back[j]
            j = j - np.where(v >= 0, self.piece_size[v], -v)
            on = j > start
            j, start = j[on], start[on]
        node = np.flatnonzero(last)
        v = back[node]
        many = np.where(v >= 0, 1, -v)
        upto = np.cumsum(many)
        ids = np.repeat(v, many)
        spelled = np.flatnonzero(ids < 0)
        ids[spelled] = self.first_byte + code[spelled + np.repeat(node - upto, many)[spelled]]
        data, cuts = ids.astype(np.int32).tobytes(), (4 * upto[np.searchsorted(node, end)]).tolist()
        return [data[a:b] for a, b in pairwise([0, *cuts])]

    def encode_many(self, texts: list[str]) -> list[tuple[float, np.ndarray]]:
        """(score, ids) of each text. Chunks come from the young memo, the old one, or are solved in blocks. A full young memo becomes the old one,
        so chunks in use survive and at most 2 * MEMO are held besides those of the texts in hand; long chunks are not kept."""
        cut = [self.cut.findall(" " + text) if text else [] for text in texts]
        memo, old = self.memo, self.old
        new = set().union(*cut).difference(memo)
        memo.update({c: old[c] for c in new & old.keys()})
        new -= old.keys()
        apart = {c for c in new if len(c) >= SHORT or c == MARK}
        fresh = list(new - apart)
        for a in range(0, len(fresh), BLOCK):
            block = fresh[a : a + BLOCK]
            memo.update(zip(block, self.viterbi_many([c.replace(" ", MARK).encode() for c in block]), strict=True))
        for c in apart:
            memo[c] = array("i", [self.first_byte + x for x in MARK.encode()]).tobytes() if c == MARK else self.viterbi(c.replace(" ", MARK).encode())[1]
        every = [np.frombuffer(b"".join(map(memo.__getitem__, chunks)), np.int32) for chunks in cut]
        for c in apart:
            del memo[c]
        if len(memo) >= MEMO:
            self.old, self.memo = memo, {}
        return [(float(self.gain[ids].sum()), ids) for ids in every]

    def encode(self, text: str) -> tuple[float, np.ndarray]:
        return self.encode_many([text])[0]

    def decode(self, ids) -> str:
        """Gathered from one buffer of all pieces' bytes."""
        ids = np.asarray(ids, np.int32)
        size = self.spelled_size[ids]
        at = np.repeat(self.spelled_at[ids] - np.concatenate([[0], np.cumsum(size)[:-1]]), size) if len(ids) else np.zeros(0, np.int64)
        return self.spelled[at + np.arange(len(at))].tobytes()[1:].decode("utf-8", "replace")


def load(path: str = DEFAULT_VOCABULARY, scores: str = "zipf") -> Pieces:
    """Pieces of a SentencePiece vocabulary file. It is read once, on the driver, and travels with the tasks: its size is fixed."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    ids = range(model.vocab_size())
    got = [model.get_score(i) for i in ids]
    return Pieces([model.id_to_piece(i) for i in ids], [-math.log1p(max(0.0, -s)) for s in got] if scores == "zipf" else got, model.piece_to_id("<0x00>"))


def encode_documents(docs: DataFrame, pieces: Pieces) -> DataFrame:
    """doc_id, n_pieces, n_bytes_fallback, score, ids, round_trip (the ids, decoded, are the text)."""
    schema = "doc_id long, n_pieces long, n_byte_pieces long, score double, ids array<int>, round_trip boolean"
    shared = docs.sparkSession.sparkContext.broadcast(pieces)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        low, high = own.first_byte, own.first_byte + 256
        for batch in batches:
            for a, b in slices(utf8(batch["text"])[0]):
                part = batch.slice(a, b - a)
                texts = part["text"].to_pylist()
                ids, ends, scores, ok, null = [], [0], [], [], []
                for text, (score, got) in zip(texts, own.encode_many([t or "" for t in texts]), strict=True):
                    ids.append(got)
                    ends.append(ends[-1] + len(got))
                    scores.append(score)
                    null.append(text is None)
                    ok.append(own.decode(got) == (text or ""))
                flat = np.concatenate(ids)
                offsets = np.array(ends, np.int32)
                bytes_ = np.concatenate([[0], np.cumsum((flat >= low) & (flat < high))])[offsets]
                lists = pa.ListArray.from_arrays(pa.array(offsets, mask=np.array([*null, False])), pa.array(flat))
                yield pa.RecordBatch.from_arrays([part["doc_id"], pa.array(np.diff(offsets), pa.int64()), pa.array(np.diff(bytes_), pa.int64()), pa.array(scores, pa.float64()), lists, pa.array(ok)], ["doc_id", "n_pieces", "n_byte_pieces", "score", "ids", "round_trip"])
        give_back()

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, schema)
