"""Errors of a linkage against known pairs, by threshold."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from veilmatch.operators import score

TAUS = (6000, 6500, 7000, 7500, 8000, 8500)


def judged(found: DataFrame, truth: DataFrame) -> DataFrame:
    """Best partners with is_true (the partner is the right one) and has_partner (there is a right one)."""
    known = truth.select("x_id", F.col("y_id").alias("true_id"))
    return found.join(known, "x_id", "left").select("x_id", "num", "den", score.key(F.col("num"), F.col("den")).alias("k"), F.coalesce(F.col("y_id") == F.col("true_id"), F.lit(False)).alias("is_true"), F.col("true_id").isNotNull().alias("has_partner"))


def sweep(found: DataFrame, truth: DataFrame, taus: tuple[int, ...] = TAUS, strict_fn: bool = False) -> DataFrame:
    """(tau_bp, fp, fn, total, tp, tn): one aggregation, all thresholds at once."""
    rows = judged(found, truth).withColumn("tau_bp", F.explode(F.array(*[F.lit(t) for t in taus])))
    ok = F.col("num") * 10_000 > F.col("den") * F.col("tau_bp")
    missed = F.col("has_partner") & (~ok if not strict_fn else ~(ok & F.col("is_true")))
    count = lambda c: F.sum(c.cast("long"))
    out = rows.groupBy("tau_bp").agg(count(ok & ~F.col("is_true")).alias("fp"), count(missed).alias("fn"), count(ok & F.col("is_true")).alias("tp"), count(~ok & ~F.col("has_partner")).alias("tn"))
    return out.select("tau_bp", "fp", "fn", (F.col("fp") + F.col("fn")).alias("total"), "tp", "tn")


def by_score(found: DataFrame, truth: DataFrame) -> DataFrame:
    """Counts of true and other best partners and of partnered x at each distinct score in millionths: at most 10**6 + 1 rows."""
    rows = judged(found, truth).withColumn("ppm", score.ppm(F.col("num"), F.col("den")))
    return rows.groupBy("ppm").agg(F.sum(F.col("is_true").cast("long")).alias("pos"), F.sum((~F.col("is_true")).cast("long")).alias("neg"), F.sum(F.col("has_partner").cast("long")).alias("partnered"))


def best_threshold(found: DataFrame, truth: DataFrame) -> DataFrame:
    """(tau_bp, fp, fn, total): the least total error over thresholds in ten-thousandths, the smallest on ties."""
    counts = by_score(found, truth)
    # A score passes tau (in hundreds of millionths) if it is above; candidates are the scores cut to four places, and zero.
    cut = counts.select(F.call_function("div", F.col("ppm"), F.lit(100)).cast("int").alias("tau_bp"), "ppm", "neg", "partnered")
    grid = cut.groupBy("tau_bp").agg(F.sum("neg").alias("neg"), F.sum("partnered").alias("partnered"))
    order = Window.orderBy("tau_bp").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    all_neg = Window.partitionBy()
    # Scores whose first four places equal tau count as not above it.
    rows = grid.select("tau_bp", (F.sum("neg").over(all_neg) - F.sum("neg").over(order)).alias("fp"), F.sum("partnered").over(order).alias("fn"))
    return rows.withColumn("total", F.col("fp") + F.col("fn")).orderBy("total", "tau_bp").limit(1)


def roc(found: DataFrame, truth: DataFrame) -> DataFrame:
    """(ppm, tp, fp): accepted true and other best partners at or above each score."""
    order = Window.orderBy(F.desc("ppm")).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return by_score(found, truth).select("ppm", F.sum("pos").over(order).alias("tp"), F.sum("neg").over(order).alias("fp"))


def auc(found: DataFrame, truth: DataFrame) -> DataFrame:
    """(auc, positives, negatives): share of (true, other) couples in right order, ties one half."""
    below = Window.orderBy("ppm").rowsBetween(Window.unboundedPreceding, -1)
    rows = by_score(found, truth).withColumn("lower", F.coalesce(F.sum("neg").over(below), F.lit(0)))
    sums = rows.agg(F.sum(F.col("pos") * (2 * F.col("lower") + F.col("neg"))).alias("twice"), F.sum("pos").alias("positives"), F.sum("neg").alias("negatives"))
    return sums.select(F.round(F.col("twice") / (2.0 * F.col("positives") * F.col("negatives")), 6).alias("auc"), "positives", "negatives")


def precision_recall(swept: DataFrame) -> DataFrame:
    p, r = F.col("tp") / (F.col("tp") + F.col("fp")), F.col("tp") / (F.col("tp") + F.col("fn"))
    return swept.select("tau_bp", F.round(p, 6).alias("precision"), F.round(r, 6).alias("recall"), F.round(2 * F.col("tp") / (2 * F.col("tp") + F.col("fp") + F.col("fn")), 6).alias("f1"))
