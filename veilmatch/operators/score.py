"""Encoding of registries and the weighted score of a pair as one fraction of whole numbers.

Text fields: a combined name and the city, as packed bigram maps. Coded fields: postcode, birth
year, month and day. A field weighs by its integer weight times its completeness in hundredths.
Scores travel as (num, den); they are ordered exactly by ``key``, the first 62 binary places of
the quotient, because two different fractions with denominators below 2**31 differ by more than that.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from veilmatch.functions import fields, text

TEXTS, CODES = ("name", "city"), ("postcode", "birth_year", "birth_month", "birth_day")
WEIGHTS = {"name": 480, "city": 180, "postcode": 200, "birth_year": 160, "birth_month": 110, "birth_day": 170}
MOST_WEIGHT = 1310  # keeps den under 2**31 with 64 bigrams a text field
PPM = 1_000_000


def combined_name(sep: str = "") -> Column:
    """First, birth and last name as one string; null if none is present."""
    parts = [text.normalise(F.col(c)) for c in ("first_name", "birth_name", "last_name")]
    whole = F.concat_ws(sep, *parts)
    return F.when(F.coalesce(*parts).isNotNull(), whole)


def completeness(mode: str = "components") -> dict[str, Column]:
    """In hundredths; of the name by components (100, 66, 33, 0) or 100 if any is present."""
    present = sum((F.col(c).isNotNull().cast("int") for c in ("first_name", "birth_name", "last_name")), F.lit(0))
    name = F.when(present == 3, 100).when(present == 2, 66).when(present == 1, 33).otherwise(0)
    if mode == "binary":
        name = F.when(present > 0, 100).otherwise(0)
    return {"name": name, **{c: F.when(F.col(c).isNotNull(), 100).otherwise(0) for c in ("city", *CODES)}}


def encode(registry: DataFrame, mode: str = "components", sep: str = "") -> DataFrame:
    """rec_id, owner, the maps as arrays of positions and as words n0.., c0.., cardinalities, codes and completeness."""
    delta = completeness(mode)
    base = registry.select(
        "rec_id", "owner", *CODES, text.positions(combined_name(sep)).alias("name_pos"), text.positions(text.normalise(F.col("city"))).alias("city_pos"),
        *[delta[f].alias(f"{f}_delta") for f in (*TEXTS, *CODES)],
    )
    packed = base.withColumn("_n", text.pack(F.coalesce("name_pos", F.array().cast("array<int>")))).withColumn("_c", text.pack(F.coalesce("city_pos", F.array().cast("array<int>"))))
    return packed.select(
        *base.columns,
        text.cardinality(F.col("name_pos")).cast("long").alias("name_card"),
        text.cardinality(F.col("city_pos")).cast("long").alias("city_card"),
        *[F.col("_n")[i].alias(f"n{i}") for i in range(text.WORDS)],
        *[F.col("_c")[i].alias(f"c{i}") for i in range(text.WORDS)],
    )


def check_weights(weights: dict[str, int]) -> None:
    if sum(weights.values()) > MOST_WEIGHT:
        raise ValueError(f"weights sum to more than {MOST_WEIGHT}; scale them")


def side(encoded: DataFrame, prefix: str) -> DataFrame:
    return encoded.drop("name_pos", "city_pos").select(*[F.col(c).alias(f"{prefix}_{c}") for c in encoded.columns if c not in ("name_pos", "city_pos")])


def pair_delta(field: str, rule: str) -> Column:
    x, y = F.col(f"x_{field}_delta").cast("long"), F.col(f"y_{field}_delta").cast("long")
    return {"min": F.least(x, y), "product": F.floor(x * y / 100), "left": x, "mean": F.floor((x + y) / 2)}[rule]


def fractions(bits: tuple[int, int] = (text.WORDS, text.WORDS)) -> dict[str, tuple[Column, Column]]:
    """Dice of each text field; a map without bigrams counts as one so that no denominator is zero."""
    out = {}
    for f, p, n in zip(TEXTS, "nc", bits):
        common = fields.packed_shared([F.col(f"x_{p}{i}") for i in range(n)], [F.col(f"y_{p}{i}") for i in range(n)])
        out[f] = (2 * common, F.greatest(F.col(f"x_{f}_card"), F.lit(1)) + F.greatest(F.col(f"y_{f}_card"), F.lit(1)))
    return out


def score_fraction(weights: dict[str, int] = WEIGHTS, rule: str = "min", parts: dict[str, tuple[Column, Column]] | None = None) -> tuple[Column, Column]:
    """(num, den) of a pair with x_ and y_ columns; both null where nothing can be compared."""
    check_weights(weights)
    (a, b), (c, e) = ((parts or fractions())[f] for f in TEXTS)
    dn, dc = pair_delta("name", rule) * weights["name"], pair_delta("city", "product") * weights["city"]
    agree, have = F.lit(0).cast("long"), F.lit(0).cast("long")
    for f in CODES:
        both = (F.col(f"x_{f}_delta") * F.col(f"y_{f}_delta") > 0).cast("long")
        have = have + both * (100 * weights[f])
        agree = agree + fields.equal_bit(F.col(f"x_{f}"), F.col(f"y_{f}")) * (100 * weights[f])
    num = dn * a * e + dc * c * b + agree * b * e
    den = (dn + dc + have) * b * e
    return F.when(den > 0, num).cast("long"), F.when(den > 0, den).cast("long")


def key(num: Column, den: Column) -> Column:
    """floor(2**62 * num / den), in two steps of 31 bits."""
    up = lambda c: F.call_function("shiftleft", c, F.lit(31))
    quotient = lambda a, b: F.call_function("div", a, b)
    first = quotient(up(num), den)
    return up(first).bitwiseOR(quotient(up(up(num) % den), den))


def ppm(num: Column, den: Column) -> Column:
    return F.call_function("div", num * PPM, den)
