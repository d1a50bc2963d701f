"""Substring deduplication on words by super-k-mer partitioning.

A window of 35 consecutive words whose word sequence also starts anywhere else is repeated, and
every word that a repeated window covers goes. Windows are judged on the input. Super-k-mers
bring equal windows to one bucket, where sorting their fingerprints counts them; neighbours in that
order are compared word by word, so a chance collision changes nothing.

Defined cases: a null or empty text, or one of fewer words than a window, keeps all it has; rows
equal in id and text are one document; other rows of one id are documents of their own; an
empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from veilmatch.llm.common import table
from veilmatch.llm.superkmers import Bucket, equal_windows, mixed, repeated_spans, with_spans

WORDS, GRAM = 35, 7


def classes(held: Bucket, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Windows in the order of their content, and where a new content begins in that order."""
    prints = mixed(held.s.hashes(held.windows, k))
    order = np.argsort(prints, kind="stable")
    new = np.ones(len(order), bool)
    new[1:] = prints[order[1:]] != prints[order[:-1]]
    rest = np.flatnonzero(~new)
    lead = order[np.maximum.accumulate(np.where(new, np.arange(len(order)), 0))]
    by_place = rest[np.argsort(order[rest], kind="stable")]  # chains of neighbours are checked by their last words
    wrong = by_place[~equal_windows(held.s, held.windows[order[by_place]], held.windows[lead[by_place]], k)]
    if len(wrong):  # different content under one fingerprint: tell it apart by the bytes themselves
        text = held.s.raw.tobytes()
        number = np.cumsum(new) - 1
        for c in np.unique(number[wrong]).tolist():
            at = np.flatnonzero(number == c)
            content = [text[held.s.first[w] : held.s.last[w + k - 1]] for w in held.windows[order[at]].tolist()]
            own = sorted(range(len(at)), key=lambda i: (content[i], i))
            order[at] = order[at][own]
            new[at] = [i == 0 or content[own[i]] != content[own[i - 1]] for i in range(len(own))]
    return order, new


def repeated(held: Bucket, k: int) -> np.ndarray:
    """Windows whose content has another place, or is known to have one."""
    if not len(held.windows):
        return np.zeros(0, bool)
    order, new = classes(held, k)
    heads = np.flatnonzero(new)
    several = np.zeros(len(heads), bool)
    for column in (held.ids, held.hashes, held.places):
        values = column(order)
        several |= np.minimum.reduceat(values, heads) != np.maximum.reduceat(values, heads)
    known = held.many(order)
    several |= np.logical_or.reduceat(known, heads)
    out = np.zeros(len(order), bool)
    out[order] = several[np.cumsum(new) - 1] & ~known
    return out


def dedup_words(docs: DataFrame, doc: str = "doc_id", text: str = "text", k: int = WORDS, m: int = GRAM, keep_text: bool = True) -> DataFrame:
    """(doc_id, n_words, n_removed, kept_sha256, kept) of every row; kept is the text that is left."""
    spans = repeated_spans(docs, F.col(doc), F.col(text), k, m, True, repeated, False)

    def cut(raw: bytes, begins: np.ndarray | None, ends: np.ndarray | None) -> tuple:
        held = raw.split()
        n, gone = len(held), 0
        if begins is not None:
            kept, at = [], 0
            for a, b in zip(begins.tolist(), ends.tolist()):
                kept += held[at:a]
                gone += b - a
                at = b
            held = kept + held[at:]
        left = b" ".join(held)
        return n, gone, hashlib.sha256(left).hexdigest(), left.decode() if keep_text else None

    return with_spans(docs, F.col(doc), F.col(text), spans, cut, "n_words long, n_removed long, kept_sha256 string, kept string")


def op3_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup_words(table(spark, sf_dir, "documents"), keep_text=False).drop("kept")
