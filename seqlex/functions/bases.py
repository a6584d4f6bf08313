"""Text to bases, and column functions over sequences of A, C, G, T, N."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

# The letter map of the projection, a to z.
LETTERS = "abcdefghijklmnopqrstuvwxyz"
BASES = "TTCAAGAGATTGATGAGCTCTGCCTC"
ALPHABET = ("A", "C", "G", "T", "N")


def to_bases(text: Column | str) -> Column:
    """White space goes, letters map to bases whatever their case, every other character is N."""
    text = F.col(text) if isinstance(text, str) else text
    return F.regexp_replace(F.translate(F.regexp_replace(text, "[ \t\r\n]", ""), LETTERS + LETTERS.upper(), BASES * 2), "[^ACGT]", "N")


def first_bases(text: Column | str, length: int) -> Column:
    """The first `length` bases of to_bases: every letter left by the white space is one base. A text is read on behind its first 2 * length letters only where these give too few."""
    text = F.col(text) if isinstance(text, str) else text
    head, whole = (F.regexp_replace(t, "[ \t\r\n]+", "") for t in (F.substring(text, 1, 2 * length), text))
    return to_bases(F.substring(F.when(F.length(head) >= length, head).otherwise(whole), 1, length))


def n_bases(text: Column | str) -> Column:
    """The length of to_bases."""
    return F.length(F.regexp_replace(text, "[ \t\r\n]+", ""))


_map = bytearray(b"N" * 256)
for _letter, _base in zip(LETTERS + LETTERS.upper() + "\n", BASES * 2 + "\n", strict=True):
    _map[ord(_letter)] = ord(_base)
_map = bytes(_map)


def bases(text: str, keep: str = "") -> str:
    """to_bases of a string in a worker; line breaks stay where keep has them. A character beyond one byte becomes one that is no letter."""
    return text.encode("latin-1", "replace").translate(_map, b" \t\r" if keep else b" \t\r\n").decode("ascii")


def revcomp(seq: Column | str) -> Column:
    return F.reverse(F.translate(seq, "ACGT", "TGCA"))


def canonical(seq: Column) -> Column:
    return F.least(seq, revcomp(seq))


def count_of(seq: Column, base: str) -> Column:
    return F.length(seq) - F.length(F.replace(seq, F.lit(base), F.lit("")))


def n_share(seq: Column) -> Column:
    return F.when(F.length(seq) > 0, count_of(seq, "N") / F.length(seq)).otherwise(F.lit(0.0))


def token_entropy(token: Column) -> Column:
    """Bits of the base composition of a token."""
    parts = [F.when(count_of(token, b) > 0, -(count_of(token, b) / F.length(token)) * F.log2(count_of(token, b) / F.length(token))).otherwise(0.0) for b in ALPHABET]
    total = parts[0]
    for p in parts[1:]:
        total = total + p
    return total


# Coefficients of a rational Chebyshev fit of the complementary error function (relative error under 1.2e-7), constant term first.
ERFC_TERMS = (-1.26551223, 1.00002368, 0.37409196, 0.09678418, -0.18628806, 0.27886807, -1.13520398, 1.48851587, -0.82215223, 0.17087277)
_t = "(1.0::DOUBLE / (1.0::DOUBLE + 0.5::DOUBLE * {x}))"
ERFC = f"({_t} * exp(-{{x}} * {{x}} + " + " + ".join(f"({c}::DOUBLE) * pow({_t}, {k})" for k, c in enumerate(ERFC_TERMS)) + "))"


def erfc(x: Column) -> Column:
    """Complementary error function of x >= 0."""
    t = 1.0 / (1.0 + 0.5 * x)
    poly = F.lit(0.0)
    for c in reversed(ERFC_TERMS):
        poly = poly * t + c
    return t * F.exp(-x * x + poly)


def mcc(tp: Column, tn: Column, fp: Column, fn: Column) -> Column:
    """Matthews correlation in doubles; 0 where a margin is empty."""
    tp, tn, fp, fn = (c.cast("double") for c in (tp, tn, fp, fn))
    below = (tp + fp) * (tp + fn) * (tn + fp) * (tn + fn)
    return F.when(below > 0, (tp * tn - fp * fn) / F.sqrt(below)).otherwise(0.0)


def keyed_fold(task: str, key: Column, folds: int = 10) -> Column:
    """A fold by md5 of task and id: the same on any engine and any partitioning."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{task}|"), key.cast("string"))), 1, 8), 16, 10).cast("long") % folds


def page_text(html) -> Column:
    """The text of a page: scripts, styles, comments and tags become blanks, and runs of blanks one. Entities stay as they are written."""
    gone = F.regexp_replace(html, "(?is)<script.*?</script>|<style.*?</style>|<!--.*?-->", " ")
    return F.trim(F.regexp_replace(F.regexp_replace(gone, "<[^>]*>", " "), "[ \\t\\r\\n]+", " "))
