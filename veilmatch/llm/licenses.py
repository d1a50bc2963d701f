"""License scans by a positional rare-token index (native expressions only).

Templates are short license sentences. Their words make an index: word to (template, position).
A text keeps only the words that the index knows, with their positions; those words are weighted by
their inverse document frequency over all documents. All of them are looked up in
the index; postings that agree on the relative position of text and template form an
alignment. An alignment counts when the template's mandatory key phrase stands whole in the text, all of its
words in a row, at that place. The score is the largest share of a template's weight that an alignment covers.

Scale: texts are read once, each document leaves a row of its few index words in the
shared checkpoint folder, and everything after works on these. Document frequencies are grouped
counts over at most as many keys as the index has words. Defined cases: a null text is empty (no words, score 0);
repeated rows and equal ids are scanned like any others; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from veilmatch.llm.common import ascii_lower, durable, table

# What is no word, and the base phrases with their labels.
NO_WORD = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
BASE = (("gnu general public license", "gpl"), ("apache license", "apache"), ("cc by", "cc-by"), ("mit license", "mit"))

# (label, sentence, mandatory key phrase within it)
TEMPLATES = (
    ("gpl", "gnu general public license", "gnu general public license"),
    ("apache", "apache license", "apache license"),
    ("cc-by", "cc by", "cc by"),
    ("mit", "mit license", "mit license"),
    ("apache", "licensed under the apache license version 2 0", "licensed under the apache license"),
    ("mit", "released under the mit license", "under the mit license"),
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software", "permission is hereby granted free of charge"),
    ("gpl", "you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation", "terms of the gnu general public license"),
    ("lgpl", "gnu lesser general public license", "gnu lesser general public license"),
    ("agpl", "gnu affero general public license", "gnu affero general public license"),
    ("mpl", "subject to the terms of the mozilla public license", "mozilla public license"),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted", "redistribution and use in source and binary forms"),
    ("bsd", "bsd 3 clause license", "bsd 3 clause"),
    ("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", "for any purpose with or without fee"),
    ("cc-by", "licensed under a creative commons attribution license", "creative commons attribution"),
    ("cc-by", "licensed under cc by 4 0", "cc by 4 0"),
    ("cc0", "creative commons zero public domain dedication", "creative commons zero"),
    ("unlicense", "free and unencumbered software released into the public domain", "free and unencumbered software"),
    ("epl", "made available under the terms of the eclipse public license", "eclipse public license"),
)
# Function words say little: they are in the index only where they follow another index word.
COMMON = frozenset("a and any as at by can copy for from in is it of on or the this to under with without you".split())


def indexed(sentence: str) -> list[int]:
    """Positions of a sentence's words that the index has."""
    words = sentence.split()
    return [i for i, w in enumerate(words) if w not in COMMON or i and words[i - 1] not in COMMON]


def vocabulary() -> list[str]:
    return sorted({w for sentence in [t[1] for t in TEMPLATES] + [p for p, _ in BASE] for w in sentence.split()})


def key_place(sentence: str, phrase: str) -> int:
    """Position of the key phrase in its sentence."""
    s, p = sentence.split(), phrase.split()
    return next(i for i in range(len(s)) if s[i : i + len(p)] == p)


def whole_keys(hits: Column) -> Column:
    """array<struct<template, place>>: where a template's key phrase stands in the column ``words``, with the place of the template."""
    def places(t: int, sentence: str, p: list[str]) -> Column:
        anchor = next(i for i, w in enumerate(p) if w not in COMMON)  # always among the hits
        shift = anchor + key_place(sentence, " ".join(p))

        def at(h: Column) -> Column:
            ok = h["word"] == p[anchor]
            for k, w in enumerate(p):
                if k != anchor:
                    ok = ok & F.coalesce(F.get("words", h["pos"].cast("int") + (k - anchor)) == w, F.lit(False))
            return F.when(ok, F.struct(F.lit(t).alias("template"), (h["pos"] - shift).alias("place")))

        return F.filter(F.transform(hits, at), lambda x: x.isNotNull())

    return F.concat(*[places(t, sentence, phrase.split()) for t, (_, sentence, phrase) in enumerate(TEMPLATES)])


def words_of(text: Column) -> Column:
    return F.filter(F.split(ascii_lower(text), NO_WORD), lambda w: w != "")


def index_words(docs: DataFrame, doc: str = "doc_id", text: str = "text") -> DataFrame:
    """(rid, doc_id, n_words, hits, keys), written durably: hits are array<struct<pos, word>> of index words in text order, keys of whole_keys."""
    plain = docs.select(F.col(doc).cast("long").alias("doc_id"), words_of(F.coalesce(F.col(text).cast("string"), F.lit(""))).alias("words"))
    known = vocabulary()
    rare, common = [w for w in known if w not in COMMON], [w for w in known if w in COMMON]
    behind = lambda i: F.coalesce(F.get("words", i - 1).isin(rare), F.lit(False))
    taken = lambda w, i: F.when(w.isin(rare) | (w.isin(common) & behind(i)), F.struct(i.cast("long").alias("pos"), w.alias("word")))
    hits = F.filter(F.transform("words", taken), lambda x: x.isNotNull())
    held = plain.select("doc_id", "words", hits.alias("hits"))
    return durable(held.select(F.monotonically_increasing_id().alias("rid"), "doc_id", F.size("words").cast("long").alias("n_words"), "hits", whole_keys(F.col("hits")).alias("keys")))


def phrase_starts(hits: Column, phrase: str) -> Column:
    """Positions at which the words of a phrase stand consecutively; hits holds every word of it."""
    words = phrase.split()

    def at(x: Column, i: Column) -> Column:
        ok = x["word"] == words[0]
        for k, w in enumerate(words[1:], 1):
            y = F.get(hits, i + k)
            ok = ok & F.coalesce((y["word"] == w) & (y["pos"] == x["pos"] + k), F.lit(False))
        return F.when(ok, x["pos"])

    return F.filter(F.transform(hits, at), lambda p: p.isNotNull())


def alignments(facts: DataFrame, documents: int) -> DataFrame:
    """(rid, labels, score): verified alignments of each document that has any."""
    spark = facts.sparkSession
    # Documents that hold each word: at most as many rows as the index has words.
    df = facts.select(F.explode(F.array_distinct("hits.word")).alias("word")).groupBy("word").agg(F.count("*").alias("df"))
    counts = {r["word"]: r["df"] for r in df.collect()}
    idf = {w: math.log((documents + 1) / (counts.get(w, 0) + 1)) + 1e-3 for w in vocabulary()}
    postings = [
        (w, t, p, idf[w], sum(idf[sentence.split()[x]] for x in indexed(sentence)))
        for t, (_, sentence, _) in enumerate(TEMPLATES)
        for p, w in enumerate(sentence.split())
        if p in indexed(sentence)
    ]
    index = spark.createDataFrame(postings, "word string, template int, tpos int, idf double, weight double")
    hit = facts.where(F.size("keys") > 0).select("rid", "keys", F.explode("hits").alias("h")).select("rid", "keys", "h.pos", "h.word")
    looked = hit.join(F.broadcast(index), "word").withColumn("place", F.col("pos") - F.col("tpos"))
    verified = looked.where(F.array_contains("keys", F.struct("template", "place")))
    found = verified.groupBy("rid", "template", "place").agg((F.sum("idf") / F.max("weight")).alias("share"))
    label = F.element_at(F.array(*[F.lit(t[0]) for t in TEMPLATES]), F.col("template") + 1)
    return found.groupBy("rid").agg(F.collect_set(label).alias("found"), F.max("share").alias("share"))


def scan_licenses(docs: DataFrame, doc: str = "doc_id", text: str = "text") -> DataFrame:
    facts = index_words(docs, doc, text)
    starts = {label: phrase_starts(F.col("hits"), phrase) for phrase, label in BASE}
    base = facts.select("rid", "doc_id", "n_words", F.array(*[F.struct(F.lit(k).alias("label"), v.alias("at")) for k, v in starts.items()]).alias("base"))
    places = F.flatten(F.col("base.at"))
    labels = F.filter(F.col("base"), lambda b: F.size(b["at"]) > 0)["label"]
    shares = alignments(facts, facts.count())
    out = base.join(shares, "rid", "left")
    return out.select(
        "doc_id",
        "n_words",
        F.size(places).cast("long").alias("n_base"),
        F.array_min(places).alias("first_word"),
        F.array_max(places).alias("last_word"),
        F.array_join(F.array_sort(labels), ",").alias("base_labels"),
        F.array_join(F.array_sort(F.array_union(labels, F.coalesce("found", F.array().cast("array<string>")))), ",").alias("labels"),
        F.least(F.coalesce("share", F.lit(0.0)), F.lit(1.0)).alias("score"),
    )


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_licenses(table(spark, sf_dir, "documents"))
