"""Deterministic, probabilistic and learned linkage, and weights from frequencies and errors."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from veilmatch.operators import blocks, match, score
from veilmatch.operators.registry import ATTRIBUTES


def deterministic(x: DataFrame, y: DataFrame, keys: tuple[str, ...]) -> DataFrame:
    """Pairs equal and present in all keys: one equality join."""
    a = x.select(F.col("rec_id").alias("x_id"), *keys)
    b = y.select(F.col("rec_id").alias("y_id"), *keys)
    return a.join(b, list(keys)).select("x_id", "y_id")


def agreements(paired: DataFrame, dice_ppm: int = 800_000) -> list[Column]:
    """One 0/1 column a field: text fields agree from a Dice of 0.8 on, codes if equal."""
    out = []
    for f, (num, den) in score.fractions().items():
        out.append((num * 1_000_000 >= den * dice_ppm).cast("int").alias(f))
    for f in score.CODES:
        out.append((F.col(f"x_{f}").eqNullSafe(F.col(f"y_{f}")) & F.col(f"x_{f}").isNotNull()).cast("int").alias(f))
    return out


FIELDS = (*score.TEXTS, *score.CODES)


def patterns(x: DataFrame, y: DataFrame) -> DataFrame:
    """Counts of agreement patterns over all pairs: at most 64 rows."""
    return blocks.pattern_counts(x, y)


def em(counts: list[dict], rounds: int = 50) -> dict[str, tuple[float, float]]:
    """(m, u) of each field by expectation-maximisation over pattern counts."""
    m, u, p = {f: 0.9 for f in FIELDS}, {f: 0.1 for f in FIELDS}, 0.01
    for _ in range(rounds):
        hit, all_, weight = dict.fromkeys(FIELDS, 0.0), dict.fromkeys(FIELDS, 0.0), 0.0
        total = 0
        for r in counts:
            a, b = p, 1 - p
            for f in FIELDS:
                a *= m[f] if r[f] else 1 - m[f]
                b *= u[f] if r[f] else 1 - u[f]
            g = a / (a + b) if a + b else 0.0
            weight += g * r["n"]
            total += r["n"]
            for f in FIELDS:
                hit[f] += g * r["n"] * r[f]
                all_[f] += r["n"] * r[f]
        p = min(max(weight / total, 1e-9), 1 - 1e-9)
        keep = lambda v: min(max(v, 1e-6), 1 - 1e-6)
        m = {f: keep(hit[f] / max(weight, 1e-12)) for f in FIELDS}
        u = {f: keep((all_[f] - hit[f]) / max(total - weight, 1e-12)) for f in FIELDS}
    return {f: (m[f], u[f]) for f in FIELDS}


def fellegi(x: DataFrame, y: DataFrame, mu: dict[str, tuple[float, float]], low: float, high: float) -> DataFrame:
    """(x_id, y_id, weight, decision): sums of log ratios, in thousandths, and two cut-offs."""
    rows = match.pairs(x, y).select(F.col("x_rec_id").alias("x_id"), F.col("y_rec_id").alias("y_id"), *agreements(None))
    total = sum((F.when(F.col(f) == 1, round(1000 * math.log2(m / u))).otherwise(round(1000 * math.log2((1 - m) / (1 - u)))) for f, (m, u) in mu.items()), F.lit(0))
    out = rows.select("x_id", "y_id", total.cast("long").alias("weight"))
    return out.withColumn("decision", F.when(F.col("weight") >= high * 1000, "link").when(F.col("weight") >= low * 1000, "review").otherwise("no"))


def learned(x: DataFrame, y: DataFrame, truth: DataFrame, kind: str) -> DataFrame:
    """(accuracy, f1) on held-out pairs of a classifier over field similarities; missing values are -1 with an indicator.

    Pairs: all true ones and as many best wrong partners as there are; half of the x train.
    """
    from pyspark.ml import Pipeline
    from pyspark.ml.classification import GBTClassifier, LinearSVC, MultilayerPerceptronClassifier, NaiveBayes, RandomForestClassifier
    from pyspark.ml.evaluation import MulticlassClassificationEvaluator
    from pyspark.ml.feature import VectorAssembler

    wrong = match.best_window(match.scored(match.pairs(x, y)), 2).join(truth, ["x_id", "y_id"], "left_anti").select("x_id", "y_id", F.lit(0.0).alias("label"))
    pairs = truth.select("x_id", "y_id", F.lit(1.0).alias("label")).unionByName(wrong)
    both = pairs.join(score.side(x, "x"), F.col("x_id") == F.col("x_rec_id")).join(score.side(y, "y"), F.col("y_id") == F.col("y_rec_id"))
    values = []
    for f, (num, den) in score.fractions().items():
        have = score.pair_delta(f, "min") > 0
        values += [F.when(have, num / den).otherwise(0.0).alias(f), have.cast("double").alias(f"{f}_has")]
    for f in score.CODES:
        have = F.col(f"x_{f}").isNotNull() & F.col(f"y_{f}").isNotNull()
        values += [(F.col(f"x_{f}") == F.col(f"y_{f}")).cast("double").alias(f"_{f}"), have.cast("double").alias(f"{f}_has")]
    table_ = both.select("x_id", "label", *values).fillna(0.0)
    names = [c for c in table_.columns if c not in ("x_id", "label")]
    model = {
        "svm": lambda: LinearSVC(maxIter=20),
        "forest": lambda: RandomForestClassifier(numTrees=20, seed=1),
        "boosted": lambda: GBTClassifier(maxIter=10, seed=1),
        "bayes": lambda: NaiveBayes(),
        "mlp": lambda: MultilayerPerceptronClassifier(layers=[len(names), 8, 2], maxIter=50, seed=1),
    }[kind]()
    fit = Pipeline(stages=[VectorAssembler(inputCols=names, outputCol="features"), model]).fit(table_.where("x_id % 2 = 0"))
    scored = fit.transform(table_.where("x_id % 2 = 1"))
    measure = lambda m: MulticlassClassificationEvaluator(metricName=m).evaluate(scored)
    return x.sparkSession.createDataFrame([(kind, round(measure("accuracy"), 4), round(measure("f1"), 4))], "kind string, accuracy double, f1 double")


def field_error_rates(left: DataFrame, right: DataFrame, truth: DataFrame) -> DataFrame:
    """(field, n, differ): true pairs with both values present, and those that differ."""
    a = left.select(F.col("rec_id").alias("x_id"), *[F.col(c).cast("string").alias(f"x_{c}") for c in ATTRIBUTES])
    b = right.select(F.col("rec_id").alias("y_id"), *[F.col(c).cast("string").alias(f"y_{c}") for c in ATTRIBUTES])
    rows = truth.join(a, "x_id").join(b, "y_id").select(F.explode(F.array(*[F.struct(F.lit(c).alias("field"), F.col(f"x_{c}").alias("x"), F.col(f"y_{c}").alias("y")) for c in ATTRIBUTES])).alias("v"))
    return rows.where("v.x is not null and v.y is not null").groupBy("v.field").agg(F.count("*").alias("n"), F.sum((F.col("v.x") != F.col("v.y")).cast("long")).alias("differ"))


def value_frequencies(registry: DataFrame) -> DataFrame:
    """(field, distinct_values, collision): 1 / distinct is the uniform frequency, collision the sum of squared shares."""
    rows = registry.select(F.explode(F.array(*[F.struct(F.lit(c).alias("field"), F.col(c).cast("string").alias("v")) for c in ATTRIBUTES])).alias("f")).select("f.*").where("v is not null")
    counts = rows.groupBy("field", "v").agg(F.count("*").alias("n"))
    return counts.groupBy("field").agg(F.count("*").alias("distinct_values"), F.round(F.sum(F.col("n").cast("double") * F.col("n")) / (F.sum("n") * F.sum("n")), 6).alias("collision"))


def frequency_weights(frequencies: DataFrame, errors: DataFrame, total: int = 1300) -> DataFrame:
    """(field, weight, scaled): log2((1 - e) / q), and its share of ``total`` as a whole number."""
    e = F.least(F.greatest(F.col("differ") / F.col("n"), F.lit(0.001)), F.lit(0.999))
    rows = frequencies.join(errors, "field").select("field", F.round(F.log2((1 - e) * F.col("distinct_values")), 6).alias("weight"))
    return rows.crossJoin(F.broadcast(rows.agg(F.sum("weight").alias("s")))).select("field", "weight", F.floor(F.col("weight") * total / F.col("s") + 0.5).cast("long").alias("scaled"))
