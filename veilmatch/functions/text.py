"""Strings of the linkage alphabet and their bigram sets."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

# The 30 symbols, in rank order, and the folding of accents.
ALPHABET = "abcdefghijklmnopqrstuvwxyz-. *"
FOLD_FROM = "äöüàáâãåçèéêëìíîïñòóôõùúûýÿ"
FOLD_TO = "aouaaaaaceeeeiiiinoooouuuyy"
SIZE = len(ALPHABET)
MAP = SIZE * SIZE
WORDS = 15  # 64-bit words that hold 900 bits


def normalise(text: Column) -> Column:
    """Lower case, accents folded, every other symbol a star, outer blanks gone."""
    low = F.replace(F.translate(F.lower(text), FOLD_FROM, FOLD_TO), F.lit("ß"), F.lit("ss"))
    return F.trim(F.regexp_replace(low, r"[^a-z. *-]", "*"))


def grams(text: Column, q: int = 2) -> Column:
    """Distinct q-grams of a string; none if it is shorter."""
    n = F.length(text)
    some = F.array_distinct(F.transform(F.sequence(F.lit(1), n - (q - 1)), lambda i: F.substring(text, i, F.lit(q))))
    return F.when(n >= q, some).when(text.isNotNull(), F.array().cast("array<string>"))


def positions(text: Column, q: int = 2) -> Column:
    """Sorted distinct positions of the q-grams in the map of 30**q places."""

    def place(gram: Column) -> Column:
        out = F.lit(0)
        for k in range(1, q + 1):
            out = out * SIZE + F.call_function("instr", F.lit(ALPHABET), F.substring(gram, k, 1)) - 1
        return out.cast("int")

    return F.array_sort(F.transform(grams(text, q), place))


def long_positions(text: Column, q: int = 2) -> Column:
    """``positions`` of long texts: neighbouring ranks are zipped, so work grows with the length and not with its square."""
    ranks = F.transform(F.split(text, ""), lambda c: F.call_function("instr", F.lit(ALPHABET), c) - 1)
    n = F.length(text)
    out = F.slice(ranks, F.lit(1), F.greatest(n - (q - 1), F.lit(0)))
    for k in range(1, q):
        out = F.zip_with(out, F.slice(ranks, F.lit(k + 1), F.greatest(n - (q - 1), F.lit(0))), lambda a, b: a * SIZE + b)
    return F.when(n >= q, F.array_sort(F.array_distinct(out))).when(text.isNotNull(), F.array().cast("array<int>"))


def _once(value: Column, build: Callable[[Column], Column]) -> Column:
    """``build(value)`` with the value computed once a row: an expression that stands in a lambda is computed for each element."""
    return F.transform(F.array(value), build)[0]


def pack(pos: Column, words: int = WORDS) -> Column:
    """Positions as an array of 64-bit words."""
    bit = lambda p: F.call_function("shiftleft", F.lit(1).cast("long"), p % 64)

    def word(held: Column, w: Column) -> Column:
        return F.aggregate(F.filter(held, lambda p: F.floor(p / 64) == w), F.lit(0).cast("long"), lambda a, p: a.bitwiseOR(bit(p)))

    return _once(pos, lambda held: F.transform(F.sequence(F.lit(0), F.lit(words - 1)), lambda w: word(held, w)))


def dense(pos: Column) -> Column:
    """A 0 or 1 for each place of the map, in one walk over the sorted positions: each adds the zeros before it."""

    def runs(held: Column) -> Column:
        before, at = F.concat(F.array(F.lit(-1)), held), F.concat(held, F.array(F.lit(MAP)))
        return F.flatten(F.zip_with(before, at, lambda a, b: F.concat(F.array_repeat(F.lit(0), b - a - 1), F.array_repeat(F.lit(1), F.when(b < MAP, 1).otherwise(0)))))

    return _once(F.array_sort(F.array_distinct(F.filter(pos, lambda p: (p >= 0) & (p < MAP)))), runs)


def cardinality(pos: Column) -> Column:
    return F.size(F.coalesce(pos, F.array().cast("array<int>")))
