"""Multisets of word shingles of whole texts, hashed in numpy straight from Arrow buffers."""

from __future__ import annotations

import numpy as np

from .common import SLICE_BYTES, mix

WORDS = 5

_space = np.zeros(256, bool)
_space[[32, *range(9, 14)]] = True
_lower = np.arange(256, dtype=np.uint8)
_lower[65:91] += 32
_noise = np.random.default_rng(20).integers(1, 2**63, 256, dtype=np.uint64)
_ODD = np.uint64(0x9E3779B97F4A7C15)
_INVERSE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 2**64))
_powers: dict[str, np.ndarray] = {}


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """The first n powers of an odd number modulo 2**64, and of its inverse."""
    if len(_powers.get("up", ())) < n:
        size = max(n, SLICE_BYTES + 1)
        for name, x in (("up", _ODD), ("down", _INVERSE)):
            p = np.full(size, x, np.uint64)
            p[0] = 1
            _powers[name] = np.multiply.accumulate(p)
    return _powers["up"][:n], _powers["down"][:n]


def word_hashes(data: np.ndarray, *, fold: bool = True, newline_only: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """(start, hash) of each word [^ \\t-\\r]+ of the bytes (or each run without a line break), A-Z in lower case if fold is set:
    differences of one prefix sum, moved to a common origin."""
    if not len(data):
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    up, down = powers(len(data))
    prefix = np.concatenate([np.zeros(1, np.uint64), np.cumsum(_noise[_lower[data] if fold else data] * up, dtype=np.uint64)])
    edge = np.diff(np.concatenate([[True], data == 10 if newline_only else _space[data], [True]]).astype(np.int8))
    start, end = np.flatnonzero(edge == -1), np.flatnonzero(edge == 1)
    return start, mix((prefix[end] - prefix[start]) * down[start] + (end - start).astype(np.uint64))


def multisets(offsets: np.ndarray, data: np.ndarray, words: int = WORDS) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, shingle, count), sorted by row and shingle. Fewer words than a shingle has make one shingle of them all; no word makes none.
    The rows are offsets' ranges of data; a word never spans two of them, as each row is hashed after a break."""
    base = int(offsets[0])
    own = data[base : int(offsets[-1])]
    cut = np.asarray(offsets) - base
    # A space before each row keeps the last word of one apart from the first of the next.
    spaced = np.insert(own, cut[:-1], 32)
    cut = cut + np.arange(len(cut))
    start, h = word_hashes(spaced)
    row = np.searchsorted(cut, start, "right") - 1
    n = np.bincount(row, minlength=len(cut) - 1) if len(row) else np.zeros(len(cut) - 1, np.int64)
    first = np.concatenate([[0], np.cumsum(n)[:-1]])
    made = np.where(n >= words, n - words + 1, (n > 0).astype(np.int64))
    rows = np.repeat(np.arange(len(n)), made)
    at = np.arange(made.sum()) - np.repeat(np.cumsum(made) - made, made) + first[rows]
    padded = np.concatenate([h, np.zeros(words, np.uint64)])
    left = n[rows]
    total = np.zeros(len(at), np.uint64)
    for j in range(words):
        total = mix(total * _ODD + np.where(j < left, padded[at + j], np.uint64(j)))
    order = np.lexsort((total, rows))
    rows, total = rows[order], total[order]
    new = np.ones(len(rows), bool)
    new[1:] = (rows[1:] != rows[:-1]) | (total[1:] != total[:-1])
    where = np.flatnonzero(new)
    return rows[where], total[where], np.diff(np.append(where, len(rows)))


def overlap(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> float:
    """Weighted Jaccard of two multisets given as (sorted shingles, counts)."""
    _, i, j = np.intersect1d(a[0], b[0], assume_unique=True, return_indices=True)
    both = int(np.minimum(a[1][i], b[1][j]).sum())
    union = int(a[1].sum() + b[1].sum()) - both
    return both / union if union else 0.0
