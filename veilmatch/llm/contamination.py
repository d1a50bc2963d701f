"""Benchmark decontamination by words and latent semantics.

Texts are cut into overlapping passages of words. A passage is a TF-IDF vector over hashed words, and a randomised
singular value decomposition of passages gives latent coordinates, scaled to equal variance. The candidates of
every item are the passages whose cosine with it reaches ``CLOSE``, and beside these all that the word rule below
could accept, by a bound that is never too low: the places of the item whose word stands anywhere in reach, as bits.
A cosine from ``NEAR`` to ``CLOSE`` is searched and reported, but such a passage can pass by the word rule only, so it
is checked where the bound leaves it.

A candidate is checked on the words around it: the longest common subsequence with the item, and with its answer (where a
benchmark has none, its last quarter). The word rule wants much of the item, or less with the answer; so an item with words changed,
dropped or added is found, and passages that only share a topic are not. A passage whose cosine reaches ``CLOSE`` may have little in
the item's order, as sentences that were put in another order do, but must have the answer: the latent rule.
``latent`` tells which rows only that rule finds.

Document frequencies are counted over all documents. The decomposition is fitted once, on the passages of all documents
and all items: sums over the passages of what two words share are made in one reading and multiplied from then on. Every passage of every
document is searched. Items are sent to the tasks in blocks of at most ``ITEMS``;
a larger benchmark takes one pass over the texts for each block.

Defined cases: a null or empty text has no passage; a null or empty item is never found; repeated rows and
equal ids give their rows each; empty tables give no rows; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from veilmatch.llm.common import durable, give_back, table, tidy
from veilmatch.llm.superkmers import as_words

HALF = 16  # a passage is two halves of this many words; neighbours share one
BITS = 13
BINS = 1 << BITS
RANK, EXTRA, ROUNDS = 192, 16, 2
FIT_DOCS = 40_000  # documents for which a task of the fit is worth its BINS x BINS / 2 sums
FIT_WORDS = 1 << 27  # words after which a task writes its sums, as they are single precision
ITEMS = 2_000
TABLE = 2_000_000  # words times lanes of one table of item places
NEAR = 0.5  # cosine that the search reports
LEAST, ENOUGH = 0.45, 0.6  # covered share of an item: with its answer, and without
CLOSE, FEW = 0.8, 0.3  # cosine from which this share is enough, with the answer
ANSWER = 0.8  # covered share of an answer

# Lower case, and every ASCII character but letters and digits a blank.
_PLAIN = bytes(c + 32 if 65 <= c <= 90 else c if c >= 128 or 97 <= c <= 122 or 48 <= c <= 57 else 32 for c in range(256))


@dataclass
class Words:
    ids: np.ndarray  # 64-bit hash of each word
    ends: np.ndarray  # words before each text, and all

    @classmethod
    def of(cls, texts: list[str | None]) -> Words:
        s = as_words([(t or "").encode().translate(_PLAIN) for t in texts])
        return cls(s.hashes(np.arange(len(s.sums) - 1), 1), s.ends)

    @property
    def bins(self) -> np.ndarray:
        return (self.ids >> np.uint64(64 - BITS)).astype(np.int64)

    def halves(self) -> tuple[np.ndarray, np.ndarray]:
        """First word and text of each half passage."""
        n = -(-np.diff(self.ends) // HALF)
        text = np.repeat(np.arange(len(n)), n)
        inside = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
        return self.ends[:-1][text] + inside * HALF, text


def groups(texts: list[str | None], size: int = 400_000) -> Iterator[tuple[int, list[str | None]]]:
    """Runs of texts of about ``size`` characters, with the number of the first."""
    first, held = 0, 0
    for i, t in enumerate(texts):
        held += len(t or "")
        if held >= size:
            yield first, texts[first : i + 1]
            first, held = i + 1, 0
    if first < len(texts):
        yield first, texts[first:]


def passages(words: Words, values: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sums of values[bin] over each passage; its first word and its text. The last row of ``values`` is zero."""
    begins, text = words.halves()
    if not len(begins):
        return np.zeros((0, values.shape[1]), values.dtype), begins, text
    bins = np.append(words.bins, BINS)
    left = words.ends[1:][text] - begins
    half = np.zeros((len(begins), values.shape[1]), values.dtype)
    for j in range(HALF):  # the j-th word of every half at once; behind a text's end the zero row
        half += values[bins[np.where(left > j, begins + j, len(bins) - 1)]]
    joined = np.zeros(len(text), bool)
    joined[:-1] = text[1:] == text[:-1]  # a next half of the same text follows
    alone = np.ones(len(text), bool)
    alone[1:] = text[1:] != text[:-1]
    keep = joined | alone
    out = half.copy()
    out[:-1][joined[:-1]] += half[1:][joined[:-1]]
    return out[keep], begins[keep], text[keep]


def closed(values: np.ndarray) -> np.ndarray:
    """Single precision, with a zero row behind the bins."""
    return np.concatenate((values, np.zeros((1, values.shape[1])))).astype(np.float32)


def document_frequencies(docs: DataFrame) -> tuple[np.ndarray, int]:
    """Documents that hold each bin, and all documents."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        df, n = np.zeros(BINS + 1, np.int64), 0
        for batch in batches:
            for lo in range(0, batch.num_rows, 1000):
                for _, texts in groups(batch.slice(lo, 1000).column(0).to_pylist()):
                    w = Words.of(texts)
                    text = np.repeat(np.arange(len(texts)), np.diff(w.ends))
                    held = np.zeros(len(texts) * BINS if len(texts) * BINS < 1 << 23 else 0, bool)
                    key = text * BINS + w.bins
                    if len(held):
                        held[key] = True
                        df[:-1] += held.reshape(-1, BINS).sum(axis=0)
                    else:
                        df[:-1] += np.bincount(np.unique(key) % BINS, minlength=BINS)
                    df[-1] += len(texts)
        some = np.flatnonzero(df)
        yield pa.RecordBatch.from_arrays([pa.array(some.astype(np.int32)), pa.array(df[some])], names=["bin", "n"])

    rows = docs.select("text").mapInArrow(tidy(count), "bin int, n long").groupBy("bin").agg(F.sum("n").alias("n")).collect()  # at most BINS + 1
    df = np.zeros(BINS + 1, np.int64)
    for r in rows:
        df[r["bin"]] = r["n"]
    return df[:-1], int(df[-1])


def together(w: Words, squares: np.ndarray, out: np.ndarray) -> None:
    """Adds to out[u, v] for every two words of a passage, in either order, one over the passage's squared length; half of it for a word with itself."""
    begins, text = w.halves()
    norm, first, _ = passages(w, squares)
    share = np.zeros(len(begins))  # of the passage that begins at a half
    share[np.searchsorted(begins, first)] = 1.0 / np.maximum(norm[:, 0], 1e-9)
    joined = np.flatnonzero(text[1:] == text[:-1])  # a next half of the same text follows
    own = share.copy()
    own[joined + 1] += share[joined]
    left, flat = w.ends[1:][text] - begins, out.reshape(-1)
    bins = np.append(w.bins, BINS)  # behind a text's end a bin that no word has
    half = bins[np.where(left[:, None] > np.arange(HALF), begins[:, None] + np.arange(HALF), len(bins) - 1)]
    i, j = np.triu_indices(HALF)
    same = np.where(i == j, 0.5, 1.0)
    for lo in range(0, len(half), 4096):
        some = half[lo : lo + 4096]
        np.add.at(flat, (some[:, i] * len(out) + some[:, j]).reshape(-1), (own[lo : lo + 4096, None] * same).astype(np.float32).reshape(-1))
        at = joined[(joined >= lo) & (joined < lo + 4096)]
        np.add.at(flat, (half[at][:, :, None] * len(out) + half[at + 1][:, None, :]).reshape(-1), np.repeat(share[at].astype(np.float32), HALF * HALF))


def shared_passages(texts: DataFrame, idf: np.ndarray, documents: int) -> DataFrame:
    """(bin, part): sums over the passages of all texts, as ``together`` adds them, of each bin with the bins from it on; to be added up."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        squares = closed((idf**2)[:, None])
        sums, words = np.zeros((BINS + 1, BINS + 1), np.float32), 0

        def parts() -> Iterator[pa.RecordBatch]:
            for lo in range(0, BINS, 256):
                rows = sums[lo : lo + 256, :BINS] + sums[:BINS, lo : lo + 256].T
                rows[np.arange(256), np.arange(lo, lo + 256)] /= 2
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(lo, lo + 256, dtype=np.int32)), pa.array([rows[k, lo + k :].tobytes() for k in range(256)], pa.binary())], names=["bin", "part"])

        for batch in batches:
            for lo in range(0, batch.num_rows, 1000):
                for _, own in groups(batch.slice(lo, 1000).column(0).to_pylist()):
                    w = Words.of(own)
                    if len(w.ids):
                        together(w, squares, sums)
                    words += len(w.ids)
            if words >= FIT_WORDS:
                yield from parts()
                sums[:], words = 0, 0
        if words:
            yield from parts()

    tasks = max(1, min(texts.sparkSession.sparkContext.defaultParallelism, documents // FIT_DOCS))
    return durable(texts.coalesce(tasks).mapInArrow(tidy(run), "bin int, part binary"))


def latent(docs: DataFrame, items: DataFrame, idf: np.ndarray, documents: int) -> np.ndarray:
    """One row a bin: what a word of that bin adds to the latent coordinates of a passage."""
    spark = docs.sparkSession
    sums = shared_passages(docs.select("text").union(items.select("text")), idf, documents)

    def product(basis: np.ndarray) -> np.ndarray:
        """A'A times basis, A the unit TF-IDF rows of all passages."""
        weighted = spark.sparkContext.broadcast((idf[:, None] * basis).astype(np.float32))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            own, out = weighted.value, np.zeros(basis_shape, np.float64)
            for batch in batches:
                for lo in range(0, batch.num_rows, 256):
                    part = batch.slice(lo, 256)
                    at = part.column(0).to_numpy()
                    rows = np.zeros((len(at), BINS), np.float32)
                    for k, held in enumerate(part.column(1)):
                        rows[k, at[k] :] = np.frombuffer(held.as_buffer(), np.float32)
                    np.add.at(out, at, rows @ own)
                    out += rows.T @ own[at]
            yield pa.RecordBatch.from_arrays([pa.array([(out * idf[:, None]).astype(np.float32).tobytes()], pa.binary())], names=["part"])

        basis_shape = basis.shape
        total = np.zeros(basis_shape)
        for r in sums.mapInArrow(tidy(run), "part binary").toLocalIterator():
            total += np.frombuffer(r["part"], np.float32).reshape(basis_shape)
        weighted.destroy()
        give_back()
        return total

    rng = np.random.default_rng(17)
    basis = rng.standard_normal((BINS, RANK + EXTRA))
    for _ in range(ROUNDS):
        basis, _ = np.linalg.qr(product(np.linalg.qr(basis)[0]))
    gram = basis.T @ product(basis)
    values, vectors = np.linalg.eigh((gram + gram.T) / 2)
    top = np.argsort(values)[::-1][:RANK]
    top = top[values[top] > 1e-5 * max(1e-12, values.max())]
    # Near-equal variance; the ridge keeps directions of few passages from standing out.
    return closed(idf[:, None] * (basis @ vectors[:, top]) / np.sqrt(values[top] + 0.05 * np.median(values[top])))


def common_words(item: dict[int, int], size: int, words: list[int]) -> int:
    """Length of the longest common subsequence; item: word to a bit for each of its places."""
    row = all_ = (1 << size) - 1
    for w in words:
        m = item.get(w)
        if m:
            u = row & m
            row = ((row + u) | (row - u)) & all_
    return size - row.bit_count()


def places_of(words: list[int]) -> dict[int, int]:
    out: dict[int, int] = {}
    for i, w in enumerate(words):
        out[w] = out.get(w, 0) | 1 << i
    return out


class Places:
    """For some items: each word to the bits of its places in each item and its answer, in lanes of 64 places."""

    def __init__(self, items: list[int], known: list[list[int]], closing: list[list[int]]):
        self.items = np.array(items)
        size = np.array([len(known[k]) for k in items])
        self.size, self.asked = size, np.array([len(closing[k]) for k in items])
        self.reach = -(-size // HALF)  # halves on either side that the words around a passage may touch
        both = [known[k] + closing[k] for k in items]
        lanes = np.array([-(-len(x) // 64) for x in both])
        self.first = np.cumsum(lanes) - lanes  # lane of each item
        word = np.array([x for each in both for x in each], np.uint64)
        place = np.concatenate([np.arange(len(x)) for x in both])
        item = np.repeat(np.arange(len(both)), [len(x) for x in both])
        lane, bit = self.first[item] + place // 64, np.uint64(1) << (place % 64).astype(np.uint64)
        self.words, row = np.unique(word, return_inverse=True)
        self.table = np.zeros((len(self.words) + 1, int(lanes.sum())), np.uint64)  # the last row: a word of no item
        np.bitwise_or.at(self.table, (row, lane), bit)
        self.own = np.zeros(self.table.shape[1], np.uint64)
        inside = place < size[item]
        np.bitwise_or.at(self.own, lane[inside], bit[inside])
        self.lanes = lanes

    def candidates(self, row: np.ndarray, w: Words, begins: np.ndarray, text: np.ndarray, last: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Halves and items (by number) where the word rule is not ruled out; ``row`` is the table's of each word, ``last`` the last half of a half's text."""
        row = np.append(row, len(self.words))
        left = w.ends[1:][text] - begins
        half = np.zeros((len(begins), self.table.shape[1]), np.uint64)
        for j in range(HALF):  # only words of an item; the last row of the table would change nothing
            own = row[np.where(left > j, begins + j, len(row) - 1)]
            hit = np.flatnonzero(own < len(self.words))
            half[hit] |= self.table[own[hit]]
        here = np.arange(len(begins))
        head = np.searchsorted(text, text)  # first half of a half's text
        found = []
        for reach in np.unique(self.reach):
            some = np.flatnonzero(self.reach == reach)
            lane = np.concatenate([np.arange(self.first[k], self.first[k] + self.lanes[k]) for k in some])
            own, cuts = self.own[lane], np.cumsum(self.lanes[some]) - self.lanes[some]
            # Halves of a window by doubling; the first and the last of a text stand for what lies beyond it.
            width, span, wide = 2 * reach + 2, 1, half[:, lane]
            while span * 2 <= width:
                wide = wide | wide[np.minimum(here + span, last)]
                span *= 2
            begin = np.maximum(here - reach, head)
            end = np.minimum(here + reach + 1, last)
            seen = wide[begin] | wide[np.maximum(end - span + 1, head)]
            size, asked = self.size[some], self.asked[some]
            n = _summed(np.bitwise_count(seen & own), cuts, self.lanes[some])
            p, k = np.nonzero(n >= np.maximum(1, np.ceil(LEAST * size)).astype(n.dtype))
            # Fewer than ENOUGH need the answer, whose places are counted for these only.
            few = np.flatnonzero(n[p, k] < ENOUGH * size[k])
            answer = np.zeros(len(few), np.int64)
            for j in range(int(self.lanes[some].max())):
                more = np.flatnonzero(self.lanes[some][k[few]] > j)
                at = cuts[k[few[more]]] + j
                answer[more] += np.bitwise_count(seen[p[few[more]], at] & ~own[at])
            keep = np.ones(len(p), bool)
            keep[few] = answer >= 0.999 * ANSWER * asked[k[few]]
            p, k = p[keep], k[keep]
            found.append((p, self.items[some[k]]))
        return np.concatenate([p for p, _ in found]), np.concatenate([k for _, k in found])


def rows_of(words: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """Where each id stands in ascending words; their number for one that does not."""
    at = np.minimum(np.searchsorted(words, ids), len(words) - 1)
    return np.where(words[at] == ids, at, len(words))


def _summed(counts: np.ndarray, cuts: np.ndarray, lanes: np.ndarray) -> np.ndarray:
    """Sums of the columns of each item, which begin at ``cuts``."""
    most = int(lanes.max())
    out = counts[:, cuts].astype(np.uint8 if most * 64 < 256 else np.int64)
    for j in range(1, most):
        more = np.flatnonzero(lanes > j)
        if len(more) == len(lanes):
            out += counts[:, cuts + j]
        else:
            out[:, more] += counts[:, cuts[more] + j]
    return out


def tables_of(known: list[list[int]], closing: list[list[int]]) -> list[Places]:
    """Items that have words, in runs whose tables hold at most about TABLE numbers."""
    out, run, words, lanes = [], [], 0, 0
    for k in (k for k in range(len(known)) if known[k]):
        n = len(known[k]) + len(closing[k])
        if run and (words + n) * (lanes + n // 64 + 1) > TABLE:
            out.append(Places(run, known, closing))
            run, words, lanes = [], 0, 0
        run.append(k)
        words, lanes = words + n, lanes + n // 64 + 1
    return [*out, Places(run, known, closing)] if run else out


def near_passages(w: Words, projection: np.ndarray, units: np.ndarray, near: float = NEAR) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(passage, item, cosine) of all that reach ``near``; passages in the order of ``passages``."""
    own, _, _ = passages(w, projection)
    own /= np.maximum(np.linalg.norm(own, axis=1, keepdims=True), 1e-9)
    found = [[np.zeros(0, np.int64)] * 2 + [np.zeros(0, np.float32)]]
    for lo in range(0, len(own), 2048):
        cosine = own[lo : lo + 2048] @ units.T
        p, k = np.nonzero(cosine >= near)
        found.append([p + lo, k, cosine[p, k]])
    return tuple(np.concatenate(c) for c in zip(*found))


def find(docs: DataFrame, items: list[tuple[int, str | None, str | None]], projection: np.ndarray) -> DataFrame:
    """Verified pairs of documents (doc_id, text) and items (id, text, answer)."""
    w = Words.of([t for _, t, _ in items])
    known = [w.ids[a:b].tolist() for a, b in zip(w.ends[:-1], w.ends[1:])]
    asked = Words.of([a for _, _, a in items])
    closing = [asked.ids[a:b].tolist() or k[-max(3, len(k) // 4) :] for a, b, k in zip(asked.ends[:-1], asked.ends[1:], known)]
    sums = np.stack([projection[w.bins[a:b]].sum(axis=0) for a, b in zip(w.ends[:-1], w.ends[1:])])
    units = sums / np.maximum(np.linalg.norm(sums, axis=1, keepdims=True), 1e-9)
    sent = docs.sparkSession.sparkContext.broadcast((projection, units.astype(np.float32), [i for i, _, _ in items], known, closing))
    names = ["doc_id", "item_id", "cosine", "common_words", "item_words", "answer_found", "near_word", "latent"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        projection, units, ids, known, closing = sent.value
        places = [places_of(k) for k in known]
        ends = [places_of(k) for k in closing]
        tables = tables_of(known, closing)
        every = np.unique(np.concatenate([np.zeros(0, np.uint64)] + [t.words for t in tables]))
        tables = [(t, np.append(rows_of(t.words, every), len(t.words))) for t in tables]
        for batch in batches:
            for lo in range(0, batch.num_rows, 1000):
                part = batch.slice(lo, 1000)
                docs_ = part.column(0).to_pylist()
                rows = []
                for first, texts in groups(part.column(1).to_pylist(), 200_000):
                    rows += search(first, texts, docs_, projection, units, ids, known, closing, places, ends, tables, every)
                columns = list(zip(*rows)) or [()] * len(names)
                kinds = (pa.int64(), pa.int64(), pa.float64(), pa.int64(), pa.int64(), pa.bool_(), pa.int64(), pa.bool_())
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds)], names=names)

    def search(first, texts, docs_, projection, units, ids, known, closing, places, ends, tables, every) -> list[tuple]:
        w = Words.of(texts)
        begins, text = w.halves()
        if not len(begins):
            return []
        last = np.searchsorted(text, text, "right") - 1
        passage = (np.arange(len(text)) < last) | (np.searchsorted(text, text) == last)  # not a last half that others precede
        at = np.flatnonzero(passage)
        p, k, cosine = near_passages(w, projection, units)
        cosines = {(int(at[i]), j): c for i, j, c in zip(p.tolist(), k.tolist(), cosine.tolist()) if known[j]}
        couples = {c for c, cosine in cosines.items() if cosine >= CLOSE}  # below it the word rule alone decides, and its bound loses nothing
        in_every = rows_of(every, w.ids) if len(every) else np.zeros(len(w.ids), np.int64)
        # The words of any item, and how many of them stand before each word: no others count.
        held = np.flatnonzero(in_every < len(every))
        before = np.searchsorted(held, np.arange(len(w.ids) + 1)).tolist()
        held = w.ids[held].tolist()
        for table_, row in tables:
            near, of = table_.candidates(row[in_every], w, begins, text, last)
            keep = passage[near]
            couples.update(zip(near[keep].tolist(), of[keep].tolist()))
        best: dict[tuple[int, int], tuple] = {}
        for p, k in couples:
            size, d = len(known[k]), int(text[p])
            # The words around the passage: room for the item on either side.
            a, b = max(int(w.ends[d]), int(begins[p]) - size), min(int(w.ends[d + 1]), int(begins[p]) + 2 * HALF + size)
            around = held[before[a] : before[b]]
            n, cosine = common_words(places[k], size, around), cosines.get((p, k))
            close = cosine is not None and cosine >= CLOSE
            if n < max(1, math.ceil((FEW if close else LEAST) * size)):
                continue
            answer = common_words(ends[k], len(closing[k]), around) >= ANSWER * len(closing[k])
            if n < ENOUGH * size and not answer:
                continue
            if cosine is None:
                own = projection[w.bins[int(begins[p]) : min(int(w.ends[d + 1]), int(begins[p]) + 2 * HALF)]].sum(axis=0)
                cosine = float(own @ units[k]) / max(float(np.linalg.norm(own)), 1e-9)
            row = (docs_[first + d], ids[k], round(cosine, 6), n, size, answer, int(begins[p] - w.ends[d]), n < max(1, math.ceil(LEAST * size)))
            old = best.get((d, k))
            # The most common words, then the highest cosine, then the first place.
            if old is None or (row[3], row[2], -row[6]) > (old[3], old[2], -old[6]):
                best[d, k] = row
        return list(best.values())

    return docs.select("doc_id", "text").mapInArrow(tidy(run), "doc_id long, item_id long, cosine double, common_words long, item_words long, answer_found boolean, near_word long, latent boolean")


def contaminated(docs: DataFrame, benchmark: DataFrame, doc: str = "doc_id", text: str = "text", item: str = "item_id", question: str = "text", answer: str | None = None) -> DataFrame:
    """(doc_id, item_id, cosine, common_words, item_words, answer_found, near_word, latent): items that documents hold."""
    plain = docs.select(F.col(doc).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text"))
    asked = benchmark.select(F.col(item).cast("long").alias("item_id"), F.col(question).cast("string").alias("text"), (F.col(answer).cast("string") if answer else F.lit(None).cast("string")).alias("answer"))
    n = asked.count()
    if not n:
        return plain.where("false").selectExpr("doc_id", "doc_id as item_id", "0d as cosine", "0L as common_words", "0L as item_words", "false as answer_found", "0L as near_word", "false as latent")
    df, documents = document_frequencies(plain)
    idf = np.log((documents + 1) / (df + 1)) + 1e-3
    projection = latent(plain, asked, idf, documents)
    blocks, out = -(-n // ITEMS), []
    for b in range(blocks):
        rows = asked.where(F.pmod(F.xxhash64("item_id"), F.lit(blocks)) == b).orderBy("item_id", "text", "answer").collect()
        if rows:
            out.append(find(plain, [tuple(r) for r in rows], projection))
    return reduce(DataFrame.unionAll, out)


def op8_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contaminated(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
