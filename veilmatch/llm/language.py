"""Language identification by fusing evidence after Bayes.

Four kinds of evidence meet in one posterior: the text's likelihood under byte-trigram models, the
language that the markup (or a column) declares, the suffix of the address and its host. Host
priors are smoothed along a hierarchy, host to suffix to all documents, and come from grouped
counts over all documents. What a declaration is worth is counted, too: how often each
declared value goes with each language that the text shows.

Every label of the table is a language. The trigram models are fitted on at most ``TRAIN_ROWS`` labelled rows of each, chosen by a hash
of the id; every other count covers all rows. A further model, uniform over trigrams, stands for
texts of no known language. A document is accepted if it has a letter, its text is more likely
under the chosen language than under the uniform model, its posterior reaches ``LEAST``, and more than one document is labelled with
that language: a model made from one text alone would always accept that text.

Defined cases: a null or empty text has no language evidence and is rejected; null declarations
and addresses are values of their own; repeated rows and equal ids are judged like any others; an
empty table, or one without labelled rows, gives no models, and then nothing is accepted; columns of the input
pass through ``identify`` and the added names replace equal ones.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from veilmatch.llm.common import durable, table, tidy

TRAIN_ROWS = 2000  # labelled rows a language that the text models are fitted on, at most
BINS = 1 << 15  # hashed byte trigrams
WEIGHT = 5000  # trigrams that one training text counts for, at most
TEMPER = 0.25  # neighbouring trigrams are not independent
SMOOTH = 20.0  # rows that a parent of the host hierarchy counts as
LEAST = 0.5
HOSTS_SENT = 200_000  # hosts up to which their priors are broadcast
SALTS = 32
ADDED = ("text_scores", "letters", "text_lang", "predicted", "posterior", "accepted")

_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_LETTER = np.zeros(256, np.int64)
_LETTER[97:123] = 1
_LETTER[128:] = 1


def _bins(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bins of all trigrams of a string column, first and end of each text in bytes; and letters before each byte."""
    column = column.cast(pa.large_string()).fill_null("")
    offsets = np.frombuffer(column.buffers()[1], np.int64, len(column) + 1, column.offset * 8)
    raw = np.frombuffer(column.buffers()[2], np.uint8)[offsets[0] : offsets[-1]] if column.buffers()[2] else np.zeros(0, np.uint8)
    low = _LOWER[raw]
    wide = low.astype(np.uint32)
    grams = (wide[:-2] << 16 | wide[1:-1] << 8 | wide[2:]) if len(wide) > 2 else np.zeros(0, np.uint32)
    bins = (grams * np.uint32(2654435761)) >> np.uint32(17)
    return bins, offsets - offsets[0], np.concatenate(([0], np.cumsum(_LETTER[low])))


def known_languages(docs: DataFrame, label: str) -> list[tuple[str, int]]:
    """All labels and their counts; each costs a model of BINS numbers in every task."""
    counts = docs.where(F.col(label).isNotNull()).groupBy(F.col(label).alias("label")).count()
    return sorted((r["label"], r["count"]) for r in counts.collect())


def lone_languages(docs: DataFrame, doc: str, label: str) -> list[str]:
    """Labels that one document alone carries: only its own words speak for such a language."""
    ends = docs.where(F.col(label).isNotNull()).groupBy(F.col(label).alias("label")).agg(F.min(doc).alias("a"), F.max(doc).alias("b"))
    return [r["label"] for r in ends.where("a <=> b").select("label").collect()]


def fit(docs: DataFrame, doc: str, text: str, label: str) -> tuple[list[str], np.ndarray]:
    """Languages and the log-probabilities of bins, one row a language."""
    found = known_languages(docs, label)
    names = [n for n, _ in found]
    if not names:
        return [], np.zeros((0, BINS), np.float32)
    share = F.create_map(*[x for n, c in found for x in (F.lit(n), F.lit(min(1.0, TRAIN_ROWS / c)))])
    chosen = F.pmod(F.xxhash64(F.col(doc).cast("long"), F.lit(7)), F.lit(1_000_000)) < share[F.col(label)] * 1_000_000
    sample = docs.where(F.col(label).isin(names) & chosen).select(F.col(label).alias("label"), F.col(text).cast("string").alias("text")).repartition(8)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts: dict[str, np.ndarray] = {}
        for batch in batches:
            for lo in range(0, batch.num_rows, 500):
                part = batch.slice(lo, 500)
                bins, at, _ = _bins(part.column(1))
                for i, name in enumerate(part.column(0).to_pylist()):
                    held = counts.setdefault(name, np.zeros(BINS))
                    own = bins[at[i] : max(at[i], at[i + 1] - 2)]
                    # A very long text weighs as much as one of WEIGHT trigrams.
                    held += np.bincount(own, minlength=BINS) * min(1.0, WEIGHT / max(1, len(own)))
        yield pa.RecordBatch.from_arrays([pa.array(counts, pa.string()), pa.array([c.tobytes() for c in counts.values()], pa.binary())], names=["label", "counts"])

    totals = np.full((len(names), BINS), 0.1)
    for r in sample.mapInArrow(tidy(count), "label string, counts binary").collect():  # 8 tasks, one row a language
        totals[names.index(r["label"])] += np.frombuffer(r["counts"], np.float64)
    return names, np.log(totals / totals.sum(axis=1, keepdims=True)).astype(np.float32)


def text_scores(docs: DataFrame, text: str, model: tuple[list[str], np.ndarray]) -> DataFrame:
    """Adds text_scores (log-likelihood of each language and, last, of the uniform model) and letters."""
    names, logs = model
    held = docs.drop(*ADDED)
    schema = T.StructType([*held.schema.fields]).add("text_scores", T.ArrayType(T.DoubleType())).add("letters", T.LongType())
    at = held.columns.index(text)
    sent = held.sparkSession.sparkContext.broadcast(logs)  # languages x BINS numbers
    none = -math.log(BINS)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        logs = sent.value
        for batch in batches:
            for lo in range(0, batch.num_rows, 500):
                part = batch.slice(lo, 500)
                bins, offsets, letters = _bins(part.column(at))
                first, end = offsets[:-1], np.maximum(offsets[:-1], offsets[1:] - 2)
                scores = np.empty((part.num_rows, len(logs) + 1))
                for k, own in enumerate(logs):
                    sums = np.concatenate(([0.0], np.cumsum(own[bins], dtype=np.float64)))
                    scores[:, k] = sums[np.minimum(end, len(bins))] - sums[np.minimum(first, len(bins))]
                scores[:, -1] = (end - first) * none
                lists = pa.ListArray.from_arrays(pa.array(np.arange(len(scores) + 1) * scores.shape[1], pa.int32()), pa.array(scores.ravel()))
                yield pa.RecordBatch.from_arrays([*part.columns, lists, pa.array(letters[offsets[1:]] - letters[offsets[:-1]])], names=schema.names)

    return held.mapInArrow(tidy(run), schema)


def host_of(address: Column) -> Column:
    """Host of a URL; any other string is its own host."""
    host = F.regexp_extract(F.lower(address), r"^[a-z][a-z0-9+.-]*://(?:[^/@]*@)?([^/:?#]+)", 1)
    return F.coalesce(F.when(host != "", host).otherwise(address), F.lit(""))


def suffix_of(host: Column) -> Column:
    return F.when(F.contains(host, F.lit(".")), F.substring_index(host, ".", -1)).otherwise("")


def code_of(declared: Column, names: list[str]) -> Column:
    """The known language that a declaration names (``en-US`` names ``en``), else empty."""
    low = F.regexp_extract(F.lower(declared), r"^\s*([a-z]+)", 1)
    return F.when(low.isin([n.lower() for n in names]), low).otherwise("")


def _argmax(scores: Column, names: list[str]) -> Column:
    return F.element_at(F.array(*[F.lit(n) for n in names]), F.array_position(scores, F.array_max(scores)).cast("int"))


def text_language(names: list[str]) -> Column:
    return _argmax(F.slice("text_scores", 1, len(names)), names)


def evidence(scored: DataFrame, names: list[str], declared: str | None, address: str | None) -> tuple[DataFrame, dict[str, list[float]]]:
    """Host priors (host, prior array) and the log-odds of each declared code, from counts over all rows."""
    spoken = scored.where(F.col("letters") > 0).select(
        text_language(names).alias("spoken"),
        (host_of(F.col(address)) if address else F.lit("")).alias("host"),
        (code_of(F.coalesce(F.col(declared), F.lit("")), names) if declared else F.lit("")).alias("code"),
    )
    each = lambda: [F.sum((F.col("spoken") == n).cast("double")) for n in names]
    pairs = spoken.groupBy("code", "spoken").count().collect()  # at most (languages + 1) x languages rows
    table_ = {c: [1.0] * len(names) for c in ["", *[n.lower() for n in names]]}
    for r in pairs:
        table_[r["code"]][names.index(r["spoken"])] += r["count"]
    totals = [sum(v[i] for v in table_.values()) for i in range(len(names))]
    odds = {c: [math.log(x / t) for x, t in zip(v, totals)] for c, v in table_.items()}
    hosts = spoken.groupBy("host").agg(F.array(*each()).alias("n")).withColumn("suffix", suffix_of(F.col("host")))
    suffixes = hosts.groupBy("suffix").agg(F.array(*[F.sum(F.col("n")[i]) for i in range(len(names))]).alias("n"))
    every = suffixes.agg(F.array(*[F.coalesce(F.sum(F.col("n")[i]), F.lit(0.0)) for i in range(len(names))]).alias("n")).first()["n"]
    base = [(x + 1.0) / (sum(every) + len(names)) for x in every]

    def smoothed(n: Column, parent: Column) -> Column:
        total = F.aggregate(n, F.lit(0.0), lambda a, x: a + x)
        return F.transform(F.arrays_zip(n.alias("n"), parent.alias("p")), lambda x: (x["n"] + SMOOTH * x["p"]) / (total + SMOOTH))

    by_suffix = suffixes.select("suffix", smoothed(F.col("n"), F.array(*[F.lit(b) for b in base])).alias("parent"))
    return hosts.join(by_suffix, "suffix").select("host", smoothed(F.col("n"), F.col("parent")).alias("prior")), odds


def fuse(scored: DataFrame, names: list[str], priors: DataFrame, odds: dict[str, list[float]], declared: str | None, address: str | None, least: float = LEAST) -> DataFrame:
    """Adds text_lang, predicted, posterior and accepted."""
    row = scored.withColumn("_host", host_of(F.col(address)) if address else F.lit(""))
    priors = priors.select(F.col("host").alias("_host"), F.col("prior").alias("_prior"))
    if priors.count() <= HOSTS_SENT:
        row = row.join(F.broadcast(priors), "_host", "left")
    else:  # a host may hold a third of all rows: its rows are dealt over salts
        salted = priors.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        row = row.withColumn("_salt", F.pmod(F.monotonically_increasing_id(), F.lit(SALTS)).cast("int")).join(salted, ["_host", "_salt"], "left").drop("_salt")
    code = code_of(F.coalesce(F.col(declared), F.lit("")), names) if declared else F.lit("")
    of_code = F.create_map(*[x for c, v in odds.items() for x in (F.lit(c), F.array(*[F.lit(o) for o in v]))])
    even = F.array(*[F.lit(1.0 / len(names))] * len(names))
    row = row.withColumn("_odds", of_code[code]).withColumn("_prior", F.coalesce("_prior", even))
    logits = F.array(*[F.col("text_scores")[i] * TEMPER + F.col("_odds")[i] + F.log(F.col("_prior")[i]) for i in range(len(names))])
    row = row.withColumn("_logits", logits)
    row = row.withColumn("predicted", _argmax(F.col("_logits"), names))
    total = F.aggregate("_logits", F.lit(0.0), lambda a, x: a + F.exp(x - F.array_max("_logits")))
    row = row.withColumn("posterior", 1.0 / total).withColumn("text_lang", text_language(names))
    chosen = F.element_at("text_scores", F.array_position(F.array(*[F.lit(n) for n in names]), F.col("predicted")).cast("int"))
    accepted = (F.col("letters") > 0) & (chosen >= F.element_at("text_scores", -1)) & (F.col("posterior") >= least)
    return row.withColumn("accepted", accepted).drop("_host", "_prior", "_odds", "_logits")


def identify(docs: DataFrame, doc: str = "doc_id", text: str = "text", label: str = "lang", declared: str | None = "lang", address: str | None = "source", keep_text: bool = True) -> DataFrame:
    """The rows of ``docs`` with the added columns; without ``keep_text`` the text goes."""
    docs = docs.drop(*ADDED)
    model = fit(docs, doc, text, label)
    names = model[0]
    if not names:
        out = docs.select("*", F.lit(None).cast("array<double>").alias("text_scores"), F.lit(0).cast("long").alias("letters"), *[F.lit(None).cast("string").alias(c) for c in ("text_lang", "predicted")], F.lit(0.0).alias("posterior"), F.lit(False).alias("accepted"))
        return out if keep_text else out.drop(text)
    lone = lone_languages(docs, doc, label)
    scored = text_scores(docs, text, model)
    # Texts are scored once; counts and the posterior read what that left.
    scored = durable(scored if keep_text else scored.drop(text))
    priors, odds = evidence(scored, names, declared, address)
    found = fuse(scored, names, durable(priors), odds, declared, address)
    return found.withColumn("accepted", F.col("accepted") & ~F.col("predicted").isin(lone)) if lone else found


def op5_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row for every document: its languages after each evidence and whether it is accepted."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source")
    found = identify(docs, keep_text=False)
    return found.select("doc_id", F.col("lang").alias("declared"), "text_lang", "predicted", F.round("posterior", 6).alias("posterior"), "letters", "accepted")
