"""From raw documents to packed sequences, in five stages.

Each stage is a function of (spark, docs, sf_dir); its result is written as Parquet and read
again as the next stage's docs. The first four return the columns of documents.

1. language: documents without an accepted language go; ``lang`` becomes the language found.
2. near_duplicates: one document of each group of near copies (SimHash fingerprints within op7's distance, or Jaccard
   similarity of five-word shingles 0.8 or more) stays, the one of smallest id.
3. decontamination: documents that hold a benchmark item go.
4. secrets: every reported span is replaced in the text; all documents stay.
5. packing: the pieces of each document and their places in sequences.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from veilmatch.llm import contamination, language, packing, secrets, shingles
from veilmatch.llm.common import durable, heaps_back, released, removed, shared_folder, short_batches, table

#: Groups of near copies, learned models and token ids are not SQL; the stages are tested against brute force.
ORACLE_SQL = None


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    found = language.identify(docs).where("accepted")
    return found.withColumn("lang", F.col("predicted")).select(*docs.columns)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows of one id count as one document, of which one row stays; rows without an id stay unless a group names them."""
    groups = shingles.near_copies(docs)
    gone = released(durable(groups.where("doc_id <> component_id").select("doc_id").distinct()))
    once = docs.join(gone, "doc_id", "left_anti").select(*docs.columns)
    # Ids are few enough to repeat only by accident: those that do keep their least row.
    again = once.where("doc_id is not null").groupBy("doc_id").count().where("count > 1").select("doc_id")
    again = durable(again)
    if again.isEmpty():
        return once
    twice = once.join(again, "doc_id", "left_semi").groupBy("doc_id").agg(F.min(F.struct(*[c for c in docs.columns if c != "doc_id"])).alias("row")).select("doc_id", "row.*")
    return once.join(again, "doc_id", "left_anti").select(*docs.columns).unionByName(twice)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    heaps_back(spark)  # what the stages before have grown
    with short_batches(spark):  # whole texts
        leaks = released(durable(contamination.contaminated(docs, table(spark, sf_dir, "benchmark")).select("doc_id").distinct()))
    return docs.join(leaks, "doc_id", "left_anti").select(*docs.columns)


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    heaps_back(spark)
    return secrets.redact(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    import public_tokenizers

    heaps_back(spark)
    return packing.pack(packing.pieces(docs, public_tokenizers.path("word_bpe_49k.json")))


STAGES = [
    ("language", identify_language),
    ("near_duplicates", drop_near_duplicates),
    ("decontamination", drop_contaminated),
    ("secrets", redact_secrets),
    ("packing", pack_sequences),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; what a stage leaves is written to the shared folder until the next has read it."""
    base = f"{shared_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    docs = table(spark, sf_dir, "documents")
    before = None
    for name, stage in STAGES[:-1]:
        stage(spark, docs, sf_dir).write.parquet(f"{base}/{name}")
        docs = spark.read.parquet(f"{base}/{name}")
        if before:
            removed(spark, before)
        before = f"{base}/{name}"
    return STAGES[-1][1](spark, docs, sf_dir)
