"""Best-fit packing by exact-complement hashing.

Texts become token ids and are cut into pieces of at most one sequence. Packing sees only how
many pieces there are of each length (at most ``size`` counts, whatever the table holds), so
the plan is made from that histogram: lengths, pairs and triples of lengths are indexed by
their sums, combinations that fill a gap exactly are consumed as often as their counts allow,
and what is left goes best-fit. A plan line says: this combination of lengths, so many times.
Pieces of one length are interchangeable; each takes the next free place of its length.

Scale: token ids never leave the task that makes them; a piece is a row of a few numbers.
Numbers within a length come from counts per partition and length, so no length meets in one
task. Defined cases: a null or empty text is one piece of one token; repeated rows are packed
like any others; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import re
import unicodedata
import zlib
from collections.abc import Iterator
from itertools import accumulate
from struct import pack as packed

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from veilmatch.llm.common import durable, table, tidy

SIZE = 2048
def byte_letters() -> list[str]:
    """The printable letter that byte-level vocabularies write for each byte."""
    plain = {*range(ord("!"), ord("~") + 1), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    spare = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(spare)) for b in range(256)]


# The split pattern of the vocabulary file, for characters below U+0180 and for lower-case ASCII.
_LETTERS, _DIGITS, _SPACES = "A-Za-zªµºÀ-ÖØ-öø-ſ", "0-9²³¹¼-¾", " \t\n\x0b\x0c\r\x85\xa0"
_LOW_PIECES = re.compile(f"'s|'t|'re|'ve|'m|'ll|'d|[{_LETTERS}]+|[{_DIGITS}]|[^{_SPACES}{_LETTERS}{_DIGITS}]+").findall
_ASCII_PIECES = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-z]+|[0-9]|[^ \t\n\x0b\x0c\rA-Za-z0-9]+").findall
_HIGH = re.compile("[ƀ-\U0010ffff]").search
_SPECIAL = ("<|startoftext|>", "<|endoftext|>")


class PieceIds(dict):
    """Ids of a piece of text, packed as little-endian unsigned 32-bit numbers.

    The memory has two generations: a full one becomes the older, from which pieces in use
    return, and the older one goes.
    """

    def __init__(self, path: str, most: int = 180_000):
        from tokenizers import Tokenizer

        super().__init__()
        self.whole = Tokenizer.from_file(path)
        self.most = most
        self.older: dict[str, bytes] = {}
        self.letters = byte_letters()

    def __missing__(self, piece: str) -> bytes:
        if len(self) >= self.most:
            self.older = dict(self)
            self.clear()
        out = self.older.get(piece)
        if out is None:
            letters = piece if piece.isascii() and piece.isalnum() else "".join([self.letters[b] for b in piece.encode()])
            ids = [t.id for t in self.whole.model.tokenize(letters)]
            out = packed("<%dI" % len(ids), *ids)
        self[piece] = out
        return out

    def of(self, text: str) -> bytes:
        """The vocabulary drops blanks, so ids of a text are those of its pieces in turn.

        Texts of characters below U+0180 are lower-cased and cut here and only pieces go to the model;
        of other texts, the stretches between blanks are told apart in the same way.
        """
        if any(x in text for x in _SPECIAL):
            return self.by_library(text)
        if text.isascii():
            return b"".join(map(self.__getitem__, _ASCII_PIECES(text.lower())))
        text = unicodedata.normalize("NFC", text)
        if not (_HIGH(text) or "İ" in text):
            return b"".join(map(self.__getitem__, _LOW_PIECES(text.lower())))
        return b"".join([self.by_library(x) if _HIGH(x) or "İ" in x else self.of(x) for x in re.split("[ \n]+", text)])

    def by_library(self, text: str) -> bytes:
        return np.array(self.whole.encode(text, add_special_tokens=False).ids, "<u4").tobytes()


def token_bytes(text: str | None, words: PieceIds) -> bytes:
    """Ids of a document, closed by id 0."""
    return (words.of(text) if text else b"") + b"\0\0\0\0"


def pieces(docs: DataFrame, vocabulary: str, doc: str = "doc_id", text: str = "text", size: int = SIZE) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32) of every document."""
    fields = "doc_id long, piece int, start long, length long, ids_crc32 long"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = PieceIds(vocabulary)
        for batch in batches:
            rows: list[tuple] = []
            for lo in range(0, batch.num_rows, 500):
                part = batch.slice(lo, 500)
                for i, t in zip(part.column(0).to_pylist(), part.column(1).to_pylist()):
                    ids = token_bytes(t, words)
                    for k in range(0, len(ids), 4 * size):
                        cut = ids[k : k + 4 * size]
                        rows.append((i, k // (4 * size), k // 4, len(cut) // 4, zlib.crc32(cut)))
            columns = list(zip(*rows)) or [()] * 5
            types = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types)], names=["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select(F.col(doc).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text")).mapInArrow(tidy(run), fields)


def plan(counts: np.ndarray, size: int = SIZE) -> list[tuple[tuple[int, ...], int]]:
    """Counts by length (index 0 unused) to lines (combination of lengths, times)."""
    left = counts.astype(np.int64).copy()
    lines: list[tuple[tuple[int, ...], int]] = []

    def use(*lengths: int) -> int:
        """Consumes a combination as often as its counts allow."""
        need = {x: lengths.count(x) for x in lengths}
        times = min(int(left[x]) // n for x, n in need.items())
        if times > 0:
            for x, n in need.items():
                left[x] -= n * times
            lines.append((tuple(sorted(lengths, reverse=True)), times))
        return times

    def pair_to(total: int, below: int) -> tuple[int, int] | None:
        """An available pair of the given sum, its larger part at most ``below``, larger part first."""
        hi = min(below, total - 1)
        lo = (total + 1) // 2
        if hi < lo:
            return None
        a = np.arange(hi, lo - 1, -1)
        fits = (left[a] > 0) & (left[total - a] > 0) & ((a * 2 != total) | (left[a] > 1))
        hit = np.flatnonzero(fits)
        return (int(a[hit[0]]), int(total - a[hit[0]])) if len(hit) else None

    use(size)
    for a in range(size - 1, size // 2 - 1, -1):  # singles: the exact complement
        use(a, size - a)
    for a in range(size - 1, 0, -1):  # pairs
        while left[a] > 0 and (p := pair_to(size - a, size)) is not None and use(a, *p):
            pass
    for a in range(size - 1, 0, -1):  # triples
        while left[a] > 0:
            done = False
            for b in np.flatnonzero(left[: size - a - 1])[::-1].tolist():
                if left[a] > 0 and (p := pair_to(size - a - b, b)) is not None and use(a, b, *p):
                    done = True
                    break
            if not done:
                break
    # Residuals: the longest first, each gap filled with the longest that fits, as often as counts allow.
    while len(rest := np.flatnonzero(left)):
        chosen = [int(rest[-1])]
        room = size - chosen[0]
        taken = {chosen[0]: 1}
        while room:
            fit = next((x for x in rest[: np.searchsorted(rest, room, "right")][::-1].tolist() if left[x] > taken.get(x, 0)), 0)
            if not fit:
                break
            n = min(room // fit, int(left[fit]) - taken.get(fit, 0))
            chosen += [fit] * n
            taken[fit] = taken.get(fit, 0) + n
            room -= n * fit
        if not use(*chosen):
            raise AssertionError("a chosen combination is available")
    return lines


def places(lines: list[tuple[tuple[int, ...], int]]) -> dict[int, tuple[np.ndarray, ...]]:
    """By length: first number of each run of pieces, the sequence it begins at and the offset there."""
    runs: dict[int, list[tuple[int, int, int]]] = {}
    used: dict[int, int] = {}
    sequence = 0
    for lengths, times in lines:
        for x, offset in zip(lengths, accumulate((0, *lengths[:-1]))):
            runs.setdefault(x, []).append((used.get(x, 0), sequence, offset))
            used[x] = used.get(x, 0) + times
        sequence += times
    return {x: tuple(np.array(c, np.int64) for c in zip(*r)) for x, r in runs.items()}


def numbered(cut: DataFrame, size: int = SIZE) -> DataFrame:
    """Adds the row's partition and its number among the rows of its length there."""
    schema = T.StructType([*cut.schema.fields]).add("part", T.IntegerType()).add("nth", T.LongType())
    at = cut.columns.index("length")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        following = np.zeros(size + 1, np.int64)
        for batch in batches:
            length = batch.column(at).to_numpy()
            order = np.argsort(length, kind="stable")
            ranked = length[order]
            firsts = np.flatnonzero(np.diff(ranked, prepend=-1))
            sizes = np.diff(np.concatenate((firsts, [len(ranked)])))
            nth = np.empty(len(length), np.int64)
            nth[order] = following[ranked] + np.arange(len(ranked)) - np.repeat(firsts, sizes)
            following[ranked[firsts]] += sizes
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(nth)], names=[*batch.schema.names, "nth"])

    return cut.withColumn("part", F.spark_partition_id()).mapInArrow(tidy(run), schema)


def pack(cut: DataFrame, size: int = SIZE) -> DataFrame:
    """Adds sequence_id and offset to pieces; ``cut`` has ``length`` between 1 and size."""
    kept = durable(numbered(cut, size))
    by_part = kept.groupBy("part", "length").agg(F.count("*").alias("n"))
    found = {r["length"]: r["n"] for r in by_part.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # at most ``size`` rows
    counts = np.zeros(size + 1, np.int64)
    for x, n in found.items():
        counts[x] = n
    runs = places(plan(counts, size))
    # Where the numbers of a partition begin within each length: one row for each partition and length.
    before = Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    based = by_part.select("part", "length", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    schema = T.StructType([*cut.schema.fields]).add("sequence_id", T.LongType()).add("offset", T.LongType())
    names = cut.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cols = dict(zip(batch.schema.names, batch.columns))
            length, number = cols["length"].to_numpy(), cols["number"].to_numpy()
            sequence, offset = np.empty_like(number), np.empty_like(number)
            order = np.argsort(length, kind="stable")
            for rows in np.split(order, np.flatnonzero(np.diff(length[order])) + 1) if len(order) else ():
                first, begins, at = runs[int(length[rows[0]])]
                k = np.searchsorted(first, number[rows], "right") - 1
                sequence[rows] = begins[k] + number[rows] - first[k]
                offset[rows] = at[k]
            yield pa.RecordBatch.from_arrays([*(cols[n] for n in names), pa.array(sequence), pa.array(offset)], names=[*names, "sequence_id", "offset"])

    placed = kept.join(based, ["part", "length"]).select(*names, (F.col("base") + F.col("nth")).alias("number"))
    return placed.mapInArrow(tidy(run), schema)


def op9_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return pack(pieces(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json")))
