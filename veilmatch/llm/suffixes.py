"""Byte-level substring deduplication by a hash-compared suffix sort.

A byte goes if a 100-byte string that covers it also starts earlier: in a document of smaller id, or
earlier in the same document. Super-k-mers of bytes bring all suffixes that share their
first 100 bytes to one bucket. There suffixes are sorted by merging. Two suffixes are compared
through their longest common extension, found by binary search over prefix polynomial
hashes, so a comparison takes logarithmically many steps; equal ones are ordered by document and
place. Behind the first of each run of equal suffixes all are repeats. Neighbours that the hashes call equal
are verified byte by byte.

Only suffixes whose 100-byte hash occurs twice in the bucket are sorted: others have no equal. Defined cases: a null or empty
text has no byte; rows equal in id and text are one document (neither repeats the other); other rows of one id
are ordered by a hash of their text; a null id comes first; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from veilmatch.llm.common import table
from veilmatch.llm.superkmers import Bucket, Symbols, equal_windows, mixed, repeated_spans, with_spans

BYTES, GRAM, SEED = 100, 18, 16


def common_extension(s: Symbols, a: np.ndarray, b: np.ndarray, most: int) -> np.ndarray:
    """Length of the longest common prefix of the suffixes at a and b, up to ``most``."""
    low, high = np.zeros(len(a), np.int64), np.full(len(a), most)
    while len(open_ := np.flatnonzero(low < high)):
        half = (low[open_] + high[open_] + 1) // 2
        same = s.hashes(a[open_], half) == s.hashes(b[open_], half)
        low[open_[same]] = half[same]
        high[open_[~same]] = half[~same] - 1
    return low


class Suffixes:
    """Suffixes at ``at``, compared on their first k bytes and then by ``rank``."""

    def __init__(self, s: Symbols, at: np.ndarray, rank: np.ndarray, k: int):
        self.s, self.at, self.rank, self.k = s, at, rank, k
        self.whole = s.hashes(at, k)

    def less(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        """Whether suffix x[i] stands before suffix y[i]."""
        out = self.rank[x] < self.rank[y]
        differ = np.flatnonzero(self.whole[x] != self.whole[y])
        if len(differ):
            a, b = self.at[x[differ]], self.at[y[differ]]
            n = common_extension(self.s, a, b, self.k - 1)
            out[differ] = self.s.raw[a + n] < self.s.raw[b + n]
        return out

    def order(self) -> np.ndarray:
        """All suffixes, grouped by their first SEED bytes and sorted in each group by merging."""
        start = self.s.hashes(self.at, min(SEED, self.k))
        order = np.lexsort((self.rank, start))
        cuts = np.flatnonzero(np.diff(start[order])) + 1
        begins = np.concatenate(([0], cuts))
        sizes = np.diff(np.concatenate((begins, [len(order)])))
        run = 1
        while len(begins) and (wide := sizes > run).any():
            begins, sizes = begins[wide], sizes[wide]
            order = self._merge(order, begins, sizes, run)
            run *= 2
        return order

    def _merge(self, order: np.ndarray, begins: np.ndarray, sizes: np.ndarray, run: int) -> np.ndarray:
        """Merges neighbouring sorted runs in every group at once."""
        rows = np.repeat(begins, sizes) + (inside := np.arange(sizes.sum()) - np.repeat(np.cumsum(sizes) - sizes, sizes))
        size = np.repeat(sizes, sizes)
        pair = inside // (2 * run) * (2 * run)
        left = inside - pair < run
        other = np.where(left, pair + run, pair)  # where the partner run begins in the group
        length = np.clip(size - other, 0, run)
        first = rows - inside + other
        low, high = np.zeros(len(rows), np.int64), length.copy()
        while len(open_ := np.flatnonzero(low < high)):
            half = (low[open_] + high[open_]) // 2
            before = self.less(order[first[open_] + half], order[rows[open_]])
            low[open_[before]] = half[before] + 1
            high[open_[~before]] = half[~before]
        own = np.where(left, inside - pair, inside - pair - run)
        out = order.copy()
        out[rows - inside + pair + own + low] = order[rows]
        return out


def later(held: Bucket, k: int) -> np.ndarray:
    """Windows whose content starts earlier, too."""
    out = np.zeros(len(held.windows), bool)
    # Prints above, places below: neighbours in that order with one print are all that can be equal.
    low = np.uint64((1 << max(1, len(out).bit_length())) - 1)
    prints = (mixed(held.s.hashes(held.windows, k)) & ~low) | np.arange(len(out), dtype=np.uint64)
    prints.sort()
    next_ = (prints[1:] ^ prints[:-1]) <= low
    twice = np.zeros(len(out), bool)
    twice[1:] = next_
    twice[:-1] |= next_
    some = np.sort((prints[twice] & low).astype(np.int64))
    del prints, next_, twice
    if not len(some):
        return out
    # Document and place as one number; equal ones are one place met twice.
    keys = (held.ids(some), held.hashes(some), held.places(some))
    by = np.lexsort(keys[::-1])
    step = np.zeros(len(some), bool)
    for c in keys:
        step[1:] |= c[by[1:]] != c[by[:-1]]
    rank = np.empty(len(some), np.int64)
    rank[by] = np.cumsum(step)
    sorted_ = Suffixes(held.s, held.windows[some], rank, k)
    order = sorted_.order()
    equal = sorted_.whole[order[1:]] == sorted_.whole[order[:-1]]
    head = np.maximum.accumulate(np.where(np.concatenate(([True], ~equal)), np.arange(len(order)), 0))
    rest = np.flatnonzero(head != np.arange(len(order)))
    rest = rest[np.argsort(order[rest], kind="stable")]
    mine, first = order[rest], order[head[rest]]
    sure = equal_windows(held.s, held.windows[some[mine]], held.windows[some[first]], k)
    hit = sure & (rank[mine] > rank[first])
    out[some[mine[hit]]] = True
    if not sure.all():  # different bytes under one hash: compare those windows themselves
        text = held.s.raw.tobytes()
        clash = np.unique(sorted_.whole[mine[~sure]])
        rows = np.flatnonzero(np.isin(sorted_.whole, clash))
        least: dict[bytes, int] = {}
        content = [text[w : w + k] for w in held.windows[some[rows]].tolist()]
        for c, r in zip(content, rank[rows].tolist()):
            least[c] = min(r, least.get(c, r))
        out[some[rows]] = [least[c] < r for c, r in zip(content, rank[rows].tolist())]
    return out


def dedup_bytes(docs: DataFrame, doc: str = "doc_id", text: str = "text", k: int = BYTES, m: int = GRAM, keep_bytes: bool = True) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256, kept) of every row; kept is binary, as a cut may split a character."""
    spans = repeated_spans(docs, F.col(doc), F.col(text), k, m, False, later, True)

    def cut(raw: bytes, begins: np.ndarray | None, ends: np.ndarray | None) -> tuple:
        left, gone, runs = raw, 0, 0
        if begins is not None:
            gone, runs = int((ends - begins).sum()), len(begins)
            left = b"".join([raw[a:b] for a, b in zip([0, *ends.tolist()], [*begins.tolist(), len(raw)])])
        return len(raw), gone, runs, hashlib.sha256(left).hexdigest(), left if keep_bytes else None

    return with_spans(docs, F.col(doc), F.col(text), spans, cut, "n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary")


def op6_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup_bytes(table(spark, sf_dir, "documents"), keep_bytes=False).drop("kept")
