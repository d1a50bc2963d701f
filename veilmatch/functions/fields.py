"""Similarities of two field values, as fractions of whole numbers where they are exact."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def equal_bit(a: Column, b: Column) -> Column:
    """1 if both are present and equal."""
    return (a.eqNullSafe(b) & a.isNotNull()).cast("long")


def shared(a: Column, b: Column) -> Column:
    return F.size(F.array_intersect(a, b)).cast("long")


def dice_fraction(a: Column, b: Column) -> Column:
    """(2 |A and B|, |A| + |B|), the denominator at least 1."""
    return F.struct((2 * shared(a, b)).alias("num"), F.greatest(F.size(a) + F.size(b), F.lit(1)).cast("long").alias("den"))


def ratio(fraction: Column) -> Column:
    return fraction["num"] / fraction["den"]


def jaccard_fraction(a: Column, b: Column) -> Column:
    return F.struct(shared(a, b).alias("num"), F.greatest(F.size(F.array_union(a, b)), F.lit(1)).cast("long").alias("den"))


def overlap_fraction(a: Column, b: Column) -> Column:
    return F.struct(shared(a, b).alias("num"), F.greatest(F.least(F.size(a), F.size(b)), F.lit(1)).cast("long").alias("den"))


def packed_shared(x: list[Column], y: list[Column]) -> Column:
    """|A and B| of packed maps, one term a word so that code generation fuses them."""
    out = F.lit(0).cast("long")
    for a, b in zip(x, y):
        out = out + F.bit_count(a.bitwiseAND(b)).cast("long")
    return out
