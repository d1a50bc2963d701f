"""SimHash near-duplicates by deletion-variant signatures.

Fingerprints of 64 bits that differ in at most 3 bits are linked. Cut into two halves, one
half differs in at most one bit. So each half is indexed once per wildcard position (that bit
cleared), equal index keys meet, and candidates are verified on all 64 bits. Components
of the links name the groups.

Scale: equal fingerprints collapse to one row before anything is indexed. The members of one
index key are linked by a spanning forest, never by all pairs: a key with many members is cut
again by the bytes of its other half, of which at least one byte is equal in any link.

Defined cases: a null or empty text has fingerprint zero and is linked like any other; texts
of fewer words than a shingle are one shingle; repeated rows and equal ids keep their rows;
an empty table gives no rows; a null id takes no part in naming a component unless alone.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from veilmatch.llm.common import durable, table, tidy
from veilmatch.llm.components import components

BITS, HALVES, MOST = 64, 2, 3
DIRECT = 512  # members of one index key that are compared directly


def fingerprints_of(texts: list[str | None], words: int = 3, seed: int = 42) -> np.ndarray:
    """Majority bits of the XXH64 of all word shingles, repeats included."""
    digest = xxhash.xxh64_intdigest
    hashes: list[int] = []
    counts = np.zeros(len(texts), np.int64)
    out = np.zeros(len(texts), np.uint64)

    def flush(first: int, last: int) -> None:
        n = counts[first:last]
        if not hashes:
            return
        at = np.concatenate(([0], np.cumsum(n)))
        h = np.array(hashes, np.uint64)
        hashes.clear()
        for lo in range(0, last - first):
            if n[lo]:
                part = h[at[lo] : at[lo + 1]]
                ones = np.zeros(BITS, np.int64)
                for cut in range(0, len(part), 65536):
                    piece = part[cut : cut + 65536]
                    ones += np.unpackbits(piece.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
                out[first + lo] = np.packbits(ones * 2 > n[lo], bitorder="little").view(np.uint64)[0]

    begun = 0
    for i, text in enumerate(texts):
        parts = text.encode().lower().split() if text else []
        if parts:
            joined = b" ".join(parts)
            if len(parts) <= words:
                hashes.append(digest(joined, seed))
                counts[i] = 1
            else:
                ends = np.cumsum(np.fromiter(map(len, parts), np.int64, len(parts)) + 1) - 1
                starts = np.concatenate(([0], ends[: len(parts) - words] + 1)).tolist()
                hashes += [digest(joined[s:e], seed) for s, e in zip(starts, ends[words - 1 :].tolist())]
                counts[i] = len(starts)
        if len(hashes) > 200_000:
            flush(begun, i + 1)
            begun = i + 1
    flush(begun, len(texts))
    return out


def fingerprint_column(docs: DataFrame, text: str = "text", words: int = 3) -> DataFrame:
    """The given columns and ``fingerprint`` (signed 64 bits)."""
    schema = T.StructType([*docs.drop("fingerprint").schema.fields])
    name = text

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = batch.schema.get_field_index(name)
            for lo in range(0, batch.num_rows, 1000):
                part = batch.slice(lo, 1000)
                prints = fingerprints_of(part.column(at).to_pylist(), words)
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(prints.view(np.int64))], names=[*part.schema.names, "fingerprint"])

    return docs.drop("fingerprint").mapInArrow(tidy(run), schema.add("fingerprint", T.LongType(), False))


def index_key(fingerprint: Column, place: Column) -> Column:
    """place 0..63: half place // 32 with its bit place % 32 cleared, and the place above it, in one long."""
    value = F.call_function("shiftrightunsigned", fingerprint, F.when(place < 32, 0).otherwise(32)).bitwiseAND(F.lit(0xFFFFFFFF))
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), place % 32)
    return F.call_function("shiftleft", place.cast("long"), F.lit(32)).bitwiseOR(value - value.bitwiseAND(bit))


def _forest(values: np.ndarray, half: int, most: int) -> list[tuple[int, int]]:
    """Edges that join all members of one index key that lie within reach of each other."""
    parent = list(range(len(values)))

    def root(x: int) -> int:
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    edges: list[tuple[int, int]] = []

    def link(rows: np.ndarray) -> None:
        part = values[rows]
        for i in range(len(rows) - 1):
            near = np.flatnonzero(np.bitwise_count(part[i + 1 :] ^ part[i]) <= most) + i + 1
            for j in near.tolist():
                a, b = root(int(rows[i])), root(int(rows[j]))
                if a != b:
                    parent[a] = b
                    edges.append((int(values[rows[i]]), int(values[rows[j]])))

    if len(values) <= DIRECT:
        link(np.arange(len(values)))
        return edges
    other = (values >> np.uint64(32 * (1 - half))) & np.uint64(0xFFFFFFFF)
    for byte in range(4):  # at most 3 bits differ in these 4 bytes, so one byte is equal
        key = (other >> np.uint64(8 * byte)) & np.uint64(255)
        order = np.argsort(key, kind="stable")
        cuts = np.flatnonzero(np.diff(key[order])) + 1
        for rows in np.split(order, cuts):
            if len(rows) > 1:
                link(rows)
    return edges


def near_links(prints: DataFrame, most: int = MOST) -> DataFrame:
    """Distinct fingerprints to links (a, b) that connect exactly what lies within ``most`` bits."""
    if most > 2 * HALVES - 1:
        raise ValueError("two halves find at most 3 differing bits")
    keyed = prints.select("fingerprint", F.explode(F.sequence(F.lit(0), F.lit(BITS - 1))).alias("place")).select("fingerprint", index_key(F.col("fingerprint"), F.col("place")).alias("key"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held_key, held = None, []

        def close() -> list[tuple[int, int]]:
            if held_key is None:
                return []
            values = np.concatenate(held)
            return _forest(values, int(held_key >> 32) // 32, most) if len(values) > 1 else []

        for batch in batches:
            if not batch.num_rows:
                continue
            keys = batch.column(1).to_numpy()
            values = batch.column(0).to_numpy().view(np.uint64)
            cuts = np.concatenate(([0], np.flatnonzero(np.diff(keys)) + 1, [len(keys)]))
            sizes = np.diff(cuts)
            edges: list[tuple[int, int]] = []
            # Keys of two members that lie inside the batch are the bulk: all at once.
            inner = np.zeros(len(sizes), bool)
            inner[1:-1] = True
            twos = cuts[:-1][inner & (sizes == 2)]
            near = twos[np.bitwise_count(values[twos] ^ values[twos + 1]) <= most]
            edges += zip(values[near].tolist(), values[near + 1].tolist())
            for g in np.flatnonzero(~inner | (sizes > 2)).tolist():
                lo, hi = int(cuts[g]), int(cuts[g + 1])
                if keys[lo] == held_key:
                    held.append(values[lo:hi])
                else:
                    edges += close()
                    held_key, held = keys[lo], [values[lo:hi]]
            pairs = np.array(edges, np.uint64).reshape(-1, 2).view(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], names=["a", "b"])
        pairs = np.array(close(), np.uint64).reshape(-1, 2).view(np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], names=["a", "b"])

    spread = keyed.repartition("key").sortWithinPartitions("key")
    found = spread.mapInArrow(tidy(run), "a long, b long")
    return found.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def near_groups(docs: DataFrame, doc: str = "doc_id", text: str = "text", words: int = 3, most: int = MOST) -> DataFrame:
    """(doc_id, fingerprint, component_id) per row; component_id is the smallest id that can be reached."""
    plain = docs.select(F.col(doc).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text"))
    marked = durable(fingerprint_column(plain, "text", words).select("doc_id", "fingerprint"))
    distinct = marked.groupBy("fingerprint").agg(F.min("doc_id").alias("first"))
    labels = components(near_links(distinct.select("fingerprint"), most))
    # label: the smallest fingerprint of a component; its smallest id names it.
    named = distinct.join(labels.select(F.col("node").alias("fingerprint"), "label"), "fingerprint", "left").withColumn("label", F.coalesce("label", "fingerprint"))
    first = named.groupBy("label").agg(F.min("first").alias("component_id"))
    by_print = named.join(first, "label").select("fingerprint", "component_id")
    return marked.join(by_print, "fingerprint").select("doc_id", "fingerprint", F.coalesce("component_id", "doc_id").alias("component_id"))


def op7_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    groups = near_groups(table(spark, sf_dir, "documents"))
    return groups.select("doc_id", F.lower(F.lpad(F.hex("fingerprint"), 16, "0")).alias("fingerprint"), "component_id")
