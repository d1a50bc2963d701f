"""The comparison method: bigrams hashed into a filter of m bits by k functions (double hashing of an MD5)."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from veilmatch.functions import fields
from veilmatch.operators import match, score

BITS, HASHES = 500, 15


def filter_positions(pos: Column, m: int = BITS, k: int = HASHES) -> Column:
    """Sorted distinct bits of all bigram positions: (h1 + i * h2) mod m."""
    half = lambda p, at: F.conv(F.substring(F.md5(p.cast("string")), at, 8), 16, 10).cast("long")
    # The two halves once a position and not for each function.
    halves = F.transform(pos, lambda p: F.struct(half(p, 1).alias("a"), half(p, 9).alias("b")))
    bits = F.transform(halves, lambda h: F.transform(F.sequence(F.lit(0), F.lit(k - 1)), lambda i: ((h["a"] + i * h["b"]) % m).cast("int")))
    return F.array_sort(F.array_distinct(F.flatten(bits)))


def encode(encoded: DataFrame, m: int = BITS, k: int = HASHES) -> DataFrame:
    """The encoded registry with filters in place of maps, so that everything else runs as it is."""
    from veilmatch.functions.text import pack

    words = -(-m // 64)
    out = encoded.drop(*[c for c in encoded.columns if c[1:].isdigit()])
    empty = F.array().cast("array<int>")
    out = out.withColumn("name_pos", filter_positions(F.coalesce("name_pos", empty), m, k)).withColumn("city_pos", filter_positions(F.coalesce("city_pos", empty), m, k))
    out = out.withColumn("name_card", F.size("name_pos").cast("long")).withColumn("city_card", F.size("city_pos").cast("long"))
    out = out.withColumn("_n", pack(F.col("name_pos"), words)).withColumn("_c", pack(F.col("city_pos"), words))
    return out.select("*", *[F.col("_n")[i].alias(f"n{i}") for i in range(words)], *[F.col("_c")[i].alias(f"c{i}") for i in range(words)]).drop("_n", "_c")


#: The default weights by their common divisor: the same scores, and denominators that stay below 2**31 with counts of filter bits.
WEIGHTS = {f: w // math.gcd(*score.WEIGHTS.values()) for f, w in score.WEIGHTS.items()}


def best_partners(x: DataFrame, y: DataFrame, m: int = BITS, k: int = HASHES, weights: dict[str, int] = WEIGHTS, **how) -> DataFrame:
    """(x_id, y_id, num, den, score_ppm): best partners by filters, in exact order."""
    words = -(-m // 64)
    return match.best_partners(encode(x, m, k), encode(y, m, k), weights=weights, parts=score.fractions((words, words)), **how)


def distortion(pairs: DataFrame, m: int = BITS, k: int = HASHES) -> DataFrame:
    """(n, mean_diff, max_diff): Dice of filters less Dice of bigrams over pairs of position arrays (a, b)."""
    value = lambda a, b: fields.ratio(fields.dice_fraction(a, b))
    gap = value(filter_positions(F.col("a"), m, k), filter_positions(F.col("b"), m, k)) - value(F.col("a"), F.col("b"))
    return pairs.select(gap.alias("gap")).agg(F.count("*").alias("n"), F.round(F.avg("gap"), 6).alias("mean_diff"), F.round(F.max(F.abs("gap")), 6).alias("max_diff"))


def exposure(encoded: DataFrame, m: int = BITS, k: int = HASHES) -> DataFrame:
    """(same, filters): how many name filters are shared by how many records."""
    bits = encoded.where("name_pos is not null").select(F.to_json(F.struct(filter_positions(F.col("name_pos"), m, k).alias("b"))).alias("f"))
    return bits.groupBy("f").agg(F.count("*").alias("same")).groupBy("same").agg(F.count("*").alias("filters"))
