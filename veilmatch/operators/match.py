"""All-pairs scores, best partners, threshold gate, and links of several holders.

Best partners come from ``blocks``. For all scores of pairs, and other completeness rules, a small side is broadcast after its rows are counted; otherwise both sides are dealt over a grid of blocks: a row of X
goes to every block of its grid row, a row of Y to every block of its grid column, so each pair meets once
and no key is hot. The best partner is one hash aggregate, combined before the exchange.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from veilmatch.operators import blocks, score

BROADCAST_ROWS = 100_000  # of about 400 bytes each
BIG = 10**18


def pairs(x: DataFrame, y: DataFrame, grid: tuple[int, int] | None = None) -> DataFrame:
    """Every row of x with every row of y (columns x_.., y_..)."""
    left, right = score.side(x, "x"), score.side(y, "y")
    if grid is None and y.count() <= BROADCAST_ROWS:
        return left.crossJoin(F.broadcast(right))
    rows, cols = grid or (16, 16)
    left = left.withColumn("_r", F.pmod(F.xxhash64("x_rec_id"), F.lit(rows)).cast("int")).withColumn("_c", F.explode(F.sequence(F.lit(0), F.lit(cols - 1))))
    right = right.withColumn("_c", F.pmod(F.xxhash64("y_rec_id"), F.lit(cols)).cast("int")).withColumn("_r", F.explode(F.sequence(F.lit(0), F.lit(rows - 1))))
    return left.repartition(rows * cols, "_r", "_c").hint("shuffle_hash").join(right.repartition(rows * cols, "_r", "_c"), ["_r", "_c"]).drop("_r", "_c")


def scored(paired: DataFrame, weights: dict[str, int] = score.WEIGHTS, rule: str = "min", parts: dict | None = None) -> DataFrame:
    """(x_id, y_id, num, den) of pairs that can be compared."""
    num, den = score.score_fraction(weights, rule, parts)
    return paired.select(F.col("x_rec_id").alias("x_id"), F.col("y_rec_id").alias("y_id"), num.alias("num"), den.alias("den")).where("den is not null")


def best(pair_scores: DataFrame) -> DataFrame:
    """(x_id, y_id, score_key): the largest score of each x, ties to the smallest y."""
    packed = score.key(F.col("num"), F.col("den")).cast("decimal(19,0)") * F.lit(BIG).cast("decimal(19,0)") + (F.lit(BIG - 1) - F.col("y_id")).cast("decimal(19,0)")
    top = pair_scores.groupBy("x_id").agg(F.max(packed.cast("decimal(38,0)")).alias("top"))
    low = F.col("top") % F.lit(BIG).cast("decimal(19,0)")
    return top.select("x_id", (F.lit(BIG - 1) - low.cast("long")).alias("y_id"))


def rescored(links: DataFrame, x: DataFrame, y: DataFrame, **how) -> DataFrame:
    """num and den of given links (x_id, y_id), by joins on the ids."""
    both = links.join(score.side(x, "x"), F.col("x_id") == F.col("x_rec_id")).join(score.side(y, "y"), F.col("y_id") == F.col("y_rec_id"))
    return scored(both, **how)


def best_partners(x: DataFrame, y: DataFrame, grid: tuple[int, int] | None = None, **how) -> DataFrame:
    """(x_id, y_id, num, den, score_ppm) of the best partner of every x."""
    if how.get("rule", "min") == "min":
        found = best_window(blocks.top(x, y, weights=how.get("weights", score.WEIGHTS), blocks=grid and grid[1])).drop("rank")
    else:
        found = rescored(best(scored(pairs(x, y, grid), **how)), x, y, **how)
    return found.withColumn("score_ppm", score.ppm(F.col("num"), F.col("den")))


def best_window(pair_scores: DataFrame, k: int = 1) -> DataFrame:
    """The k best partners by ranks in a window."""
    order = Window.partitionBy("x_id").orderBy(F.desc(score.key(F.col("num"), F.col("den"))), "y_id")
    return pair_scores.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def above(num: Column, den: Column, tau_bp: int, strict: bool = True) -> Column:
    left, right = num * 10_000, den * tau_bp
    return left > right if strict else left >= right


def accept(found: DataFrame, tau_bp: int | None, strict: bool = True) -> DataFrame:
    """Adds ``accepted``; y_id is null where the score does not pass. No threshold keeps all."""
    if tau_bp is None:
        return found.withColumn("accepted", F.lit(True))
    ok = above(F.col("num"), F.col("den"), tau_bp, strict)
    return found.withColumn("accepted", ok).withColumn("y_id", F.when(ok, F.col("y_id")))


def link_all(x: DataFrame, y: DataFrame, tau_bp: int | None, grid: tuple[int, int] | None = None, **how) -> DataFrame:
    return accept(best_partners(x, y, grid, **how), tau_bp)


def link_many(frames: list[DataFrame], tau_bp: int, mode: str = "pairs", **how) -> DataFrame:
    """Links among several holders: every unordered pair of them, or the first against each other one."""
    couples = [(0, j) for j in range(1, len(frames))] if mode == "query" else [(i, j) for i in range(len(frames)) for j in range(i + 1, len(frames))]
    out = []
    for i, j in couples:
        found = link_all(frames[i], frames[j], tau_bp, **how).where("accepted")
        out.append(found.select(F.lit(i).alias("left_holder"), F.lit(j).alias("right_holder"), "x_id", "y_id", "score_ppm"))
    return reduce(DataFrame.unionAll, out)


def pad(encoded: DataFrame, to: int, first_id: int) -> DataFrame:
    """Dummy rows up to a public size; their completeness is zero everywhere, so no pair with them can be compared."""
    missing = max(0, to - encoded.count())
    ids = encoded.sparkSession.range(first_id, first_id + missing)
    columns = []
    for f in encoded.schema.fields:
        kind = f.dataType.simpleString()
        zero = f.name.endswith(("_delta", "_card")) or f.name[1:].isdigit()
        columns.append((F.col("id") if f.name == "rec_id" else F.lit("pad") if f.name == "owner" else F.lit(0) if zero else F.lit(None)).cast(kind).alias(f.name))
    return encoded.unionByName(ids.select(*columns))


def explain(x: DataFrame, y: DataFrame, links: DataFrame, weights: dict[str, int] = score.WEIGHTS, rule: str = "min") -> DataFrame:
    """Each field's similarity and weight for given links, in millionths."""
    both = links.select("x_id", "y_id").join(score.side(x, "x"), F.col("x_id") == F.col("x_rec_id")).join(score.side(y, "y"), F.col("y_id") == F.col("y_rec_id"))
    dice = score.fractions()
    out = [F.col("x_id"), F.col("y_id")]
    for f in score.TEXTS:
        out += [score.ppm(*dice[f]).alias(f"{f}_ppm"), (score.pair_delta(f, rule if f == "name" else "product") * weights[f]).alias(f"{f}_weight")]
    for f in score.CODES:
        both_have = (F.col(f"x_{f}_delta") * F.col(f"y_{f}_delta") > 0).cast("long")
        out += [(F.col(f"x_{f}").eqNullSafe(F.col(f"y_{f}")) & F.col(f"x_{f}").isNotNull()).cast("long").alias(f"{f}_equal"), (both_have * 100 * weights[f]).alias(f"{f}_weight")]
    return both.select(*out)


def required_sets(weights: dict[str, int], tau_bp: int, pattern: tuple[str, ...], text_weight: int) -> list[tuple[str, ...]]:
    """Minimal sets of coded fields, among those present in a pattern, one of which must agree wholly in any pair above the threshold."""
    total = text_weight + sum(weights[f] for f in pattern)
    subsets = [tuple(f for i, f in enumerate(pattern) if mask >> i & 1) for mask in range(1 << len(pattern))]
    good = [s for s in subsets if (text_weight + sum(weights[f] for f in s)) * 10_000 > tau_bp * total]
    return [s for s in good if not any(set(t) < set(s) for t in good)]


def lossless_links(x: DataFrame, y: DataFrame, tau_bp: int, weights: dict[str, int] = score.WEIGHTS, rule: str = "min") -> DataFrame:
    """Accepted best links by equality joins that cover every pair above the threshold.

    Even with perfect texts a pair cannot pass unless enough coded fields agree. The least sets of fields
    that must agree follow from the weights, once for each pattern of present fields on both
    sides, with the texts at their full weight. A pattern that needs no agreement meets in the grid.
    """
    best_text = weights["name"] + weights["city"]
    codes = score.CODES

    def with_pattern(df: DataFrame) -> DataFrame:
        mask = reduce(lambda a, b: a + b, [F.when(F.col(f).isNotNull(), 1 << i).otherwise(0) for i, f in enumerate(codes)])
        return df.withColumn("_mask", mask)

    a, b = with_pattern(x), with_pattern(y)
    masks = {(r[0], r[1]) for r in a.select("_mask").distinct().crossJoin(b.select(F.col("_mask").alias("m")).distinct()).collect()}  # at most 256 rows
    needed: set[tuple[str, ...]] = set()
    free = []
    for p, q in masks:
        pattern = tuple(f for i, f in enumerate(codes) if (p & q) >> i & 1)
        sets = required_sets(weights, tau_bp, pattern, best_text)
        needed |= {s for s in sets if s}
        if () in sets:
            free.append((p, q))
    # A join on fewer fields holds all that one on more fields finds; the score is checked on what is found.
    least = [s for s in needed if not any(set(t) < set(s) for t in needed)]
    ids = []
    for s in sorted(least):
        left = a.select(F.col("rec_id").alias("x_id"), *s)
        ids.append(left.join(b.select(F.col("rec_id").alias("y_id"), *s), list(s)).select("x_id", "y_id"))
    for p in sorted({p for p, _ in free}):
        left = a.where(F.col("_mask") == p).select(F.col("rec_id").alias("x_id"), F.pmod(F.xxhash64("rec_id"), F.lit(8)).alias("_r"), F.explode(F.sequence(F.lit(0), F.lit(7))).alias("_c"))
        right = b.where(F.col("_mask").isin([q for o, q in free if o == p])).select(F.col("rec_id").alias("y_id"), F.pmod(F.xxhash64("rec_id"), F.lit(8)).cast("int").alias("_c"), F.explode(F.sequence(F.lit(0), F.lit(7))).alias("_r"))
        ids.append(left.join(right, ["_r", "_c"]).select("x_id", "y_id"))
    if not ids:
        return best_partners(x, y, weights=weights, rule=rule).where("false")
    candidates = reduce(DataFrame.unionAll, ids).distinct()
    found = rescored(candidates, x, y, weights=weights, rule=rule).where(above(F.col("num"), F.col("den"), tau_bp))
    top = rescored(best(found), x, y, weights=weights, rule=rule)
    return top.withColumn("score_ppm", score.ppm(F.col("num"), F.col("den")))


