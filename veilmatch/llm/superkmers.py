"""Super-k-mer partitioning: windows that share a minimiser travel as one packed string.

A text is a sequence of symbols (words or bytes). A window is ``k`` consecutive symbols of one
text. Its minimiser is the m-gram of least hash in it, the leftmost of equals. Consecutive
windows with one minimiser form a super-k-mer: a stretch of text that is sent once, to
the bucket of its minimiser. Equal windows have equal minimisers, so all places of a window's
content meet in one bucket, which finds equal windows exactly.

Skew is met in three ways. Equal super-k-mers within a task's chunk are sent once; what that
settles is reported at once. Minimisers that many super-k-mers share, found by a grouped count over
all texts, send each window by its own content hash instead. Buckets are many and small. No text
or group is cut short: long texts are read in stretches that overlap by k - 1 symbols.

Rows equal in id and text are one document here; a null id sorts first.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from veilmatch.llm.common import durable, give_back, released, text_bytes, tidy

CHUNK = 1 << 21  # bytes of text that are handled at once
BUCKET = 3 << 19  # bytes of super-k-mers that one bucket is to hold
FINE = 20  # buckets that travel together and are worked through one by one
HOT = 16_384  # super-k-mers of one minimiser from which its windows are sent singly
NO_ID = -(1 << 63)
BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
BASE_INV = np.uint64(pow(int(BASE), -1, 1 << 64))
_POWERS: dict[int, np.ndarray] = {}


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """BASE**i and its inverse mod 2**64 for i < n."""
    if 0 not in _POWERS or len(_POWERS[0]) < n:
        size = max(1 << 16, n * 5 // 4)
        for at, base in enumerate((BASE, BASE_INV)):
            out = np.full(size, base, np.uint64)
            out[0] = 1
            _POWERS[at] = np.multiply.accumulate(out)
    return _POWERS[0][:n], _POWERS[1][:n]


def mixed(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xFF51AFD7ED558CCD)
    x = x ^ (x >> np.uint64(29))
    x = x * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(32))


_BYTE = mixed(np.arange(1, 257, dtype=np.uint64))
_BLANK = np.zeros(256, bool)
_BLANK[[32, 9, 10, 11, 12, 13]] = True


@dataclass
class Symbols:
    """Symbols of several stretches: bytes of each symbol in ``raw``, prefix sums of their hashes, symbols before each stretch."""

    raw: np.ndarray
    first: np.ndarray  # byte at which each symbol begins; one more entry closes the last
    last: np.ndarray  # byte behind each symbol
    sums: np.ndarray
    ends: np.ndarray  # symbols before each stretch, and all

    def hashes(self, at: np.ndarray, n: int | np.ndarray) -> np.ndarray:
        """Of the n symbols from ``at``."""
        return (self.sums[at + n] - self.sums[at]) * powers(len(self.sums))[1][at]


def _prefix(h: np.ndarray) -> np.ndarray:
    sums = np.zeros(len(h) + 1, np.uint64)
    np.cumsum(h * powers(len(h))[0], out=sums[1:])
    return sums


def as_bytes(parts: list[bytes]) -> Symbols:
    raw = np.frombuffer(b"".join(parts), np.uint8)
    ends = np.concatenate(([0], np.cumsum([len(p) for p in parts], dtype=np.int64)))
    at = np.arange(len(raw) + 1)
    return Symbols(raw, at, at[1:], _prefix(_BYTE[raw]), ends)


def as_words(parts: list[bytes]) -> Symbols:
    """Words between blanks; ``raw`` holds them with one space behind each."""
    given = np.frombuffer(b" ".join([*parts, b""]), np.uint8)
    offsets = np.concatenate(([0], np.cumsum([len(p) + 1 for p in parts], dtype=np.int64)))
    blank = _BLANK[given]
    behind = np.concatenate(([True], blank[:-1]))  # the byte before is a blank, or there is none
    begins = np.flatnonzero(~blank & behind)
    kept = ~(blank & behind)
    raw = np.where(blank, np.uint8(32), given)[kept]
    place = np.cumsum(kept) - 1
    first = place[begins]
    last = np.concatenate((first[1:] - 1, [len(raw) - 1])) if len(first) else first
    bytes_ = _prefix(_BYTE[raw])
    words = mixed((bytes_[last] - bytes_[first]) * powers(len(bytes_))[1][first] + (last - first).astype(np.uint64))
    return Symbols(raw, np.concatenate((first, [len(raw)])), last, _prefix(words), np.searchsorted(begins, offsets))


@dataclass
class Runs:
    """Super-k-mers: first and last window of each, and the hash of its minimiser."""

    first: np.ndarray
    last: np.ndarray
    key: np.ndarray


def runs_of(s: Symbols, k: int, m: int) -> Runs:
    n = len(s.sums) - 1
    if n < k:
        none = np.zeros(0, np.int64)
        return Runs(none, none, none.astype(np.uint32))
    grams = mixed(s.hashes(np.arange(n - m + 1), m))
    # Hash above, place below: the least is the leftmost of the least hashes.
    least = (grams & np.uint64(0xFFFFFFFF00000000)) | np.arange(len(grams), dtype=np.uint64)
    span, width = 1, k - m + 1
    while span * 2 <= width:
        least = np.minimum(least[:-span], least[span:])
        span *= 2
    if width > span:
        least = np.minimum(least[: len(least) - (width - span)], least[width - span :])
    ends = np.repeat(s.ends[1:], np.diff(s.ends))
    windows = np.flatnonzero(np.arange(n - k + 1) + k <= ends[: n - k + 1])
    at = least[windows]
    new = np.flatnonzero(at[1:] != at[:-1]) + 1
    head, tail = np.concatenate(([0], new)), np.concatenate((new - 1, [len(at) - 1]))
    if not len(at):
        head = tail = np.zeros(0, np.int64)
    return Runs(windows[head], windows[tail], (at[head] >> np.uint64(32)).astype(np.uint32))


def stretches(texts: list[bytes], k: int, words: bool) -> Iterator[list[tuple[bytes, int, int]]]:
    """(bytes, text number, symbols before) in groups of about CHUNK bytes."""
    group: list[tuple[bytes, int, int]] = []
    size = 0
    for i, text in enumerate(texts):
        if len(text) <= 2 * CHUNK:
            parts = [(text, i, 0)]
        elif words:
            held = text.split()
            step = max(1, CHUNK * len(held) // len(text))
            parts = [(b" ".join(held[a : a + step + k - 1]), i, a) for a in range(0, max(1, len(held) - k + 1), step)]
        else:
            parts = [(text[a : a + CHUNK + k - 1], i, a) for a in range(0, max(1, len(text) - k + 1), CHUNK)]
        for p in parts:
            group.append(p)
            size += len(p[0])
            if size >= CHUNK:
                yield group
                group, size = [], 0
    if group:
        yield group


def sample_text(plain: DataFrame) -> bytes:
    """Some bytes of a few texts, which the compressor of short blobs and texts begins with. It changes sizes only."""
    rows = plain.select(F.substring("text", 1, 2000).alias("t")).where("text <> ''").orderBy(F.xxhash64("t"), "t").limit(56).collect()
    return "\n".join(r["t"] for r in rows).encode()[:110_000]


class Codec:
    """zstd with a shared beginning; made once in each task."""

    LEVEL = 6

    def __init__(self, beginning: bytes):
        held = {"dict_data": zstandard.ZstdCompressionDict(beginning, dict_type=zstandard.DICT_TYPE_RAWCONTENT)} if len(beginning) > 64 else {}
        self.pack = zstandard.ZstdCompressor(level=self.LEVEL, **held).compress
        self.unpack = zstandard.ZstdDecompressor(**held).decompress


def _columns(*arrays: np.ndarray) -> bytes:
    """Numbers byte by byte of their places, which packs well."""
    return b"".join(np.ascontiguousarray(x).view(np.uint8).reshape(len(x), -1).T.tobytes() for x in arrays)


def packed_blob(codec: Codec, number: np.ndarray, ids: np.ndarray, hashes: np.ndarray, places: np.ndarray, many: np.ndarray, fine: np.ndarray, strings: list[bytes]) -> bytes:
    """Super-k-mers of the documents ``number`` (in ids and hashes)."""
    held, own = np.unique(number, return_inverse=True)
    sizes = np.array([len(x) for x in strings], np.uint32)
    head = np.array([len(strings), len(held)], np.int64).tobytes()
    return codec.pack(b"".join([head, _columns(ids[held], hashes[held], own.astype(np.uint32), places, sizes, many.astype(np.uint8), fine.astype(np.uint8)), *strings]))


def unpacked_blob(codec: Codec, blob: bytes) -> tuple[list[np.ndarray], bytes]:
    """ids, hashes, places, sizes, many, fine of each string; the strings."""
    data = codec.unpack(blob)
    n, docs = np.frombuffer(data, np.int64, 2).tolist()
    out, at = [], 16
    for size, kind in ((docs, np.int64), (docs, np.int64), (n, np.uint32), (n, np.int64), (n, np.uint32), (n, np.uint8), (n, np.uint8)):
        width = np.dtype(kind).itemsize
        out.append(np.frombuffer(data, np.uint8, size * width, at).reshape(width, size).T.copy().view(kind).ravel())
        at += size * width
    ids, hashes, own, *rest = out
    return [ids[own], hashes[own], *rest], data[at:]


def _texts(part: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, list[bytes]]:
    """Ids, hashes and texts in the order of (id, hash), equal rows once."""
    ids = part.column(0).fill_null(NO_ID).to_numpy()
    hashes = part.column(1).to_numpy()
    order = np.lexsort((hashes, ids))
    new = np.ones(len(order), bool)
    new[1:] = (np.diff(ids[order]) != 0) | (np.diff(hashes[order]) != 0)
    order = order[new]
    texts = part.column(2).cast(pa.binary()).to_pylist()
    return ids[order], hashes[order], [texts[i] for i in order.tolist()]


def hot_minimisers(plain: DataFrame, k: int, m: int, words: bool) -> np.ndarray:
    """Hashes of minimisers that at least HOT distinct super-k-mers have, sorted.

    Counts cover all texts; a task leaves out what it holds fewer than 8 times. There are at most one in HOT of all super-k-mers.
    """

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys: list[np.ndarray] = []
        for batch in batches:
            for lo in range(0, batch.num_rows, 1000):
                for group in stretches(_texts(batch.slice(lo, 1000))[2], k, words):
                    s = (as_words if words else as_bytes)([p[0] for p in group])
                    r = runs_of(s, k, m)
                    whole = s.hashes(r.first, r.last - r.first + k)
                    _, one = np.unique(whole, return_index=True)
                    keys.append(r.key[one])
        values, counts = np.unique(np.concatenate(keys) if keys else np.zeros(0, np.uint32), return_counts=True)
        often = counts >= 8
        yield pa.RecordBatch.from_arrays([pa.array(values[often].astype(np.int64)), pa.array(counts[often])], names=["key", "n"])

    found = plain.mapInArrow(tidy(count), "key long, n long").groupBy("key").agg(F.sum("n").alias("n")).where(F.col("n") >= HOT)
    return np.array(sorted(r["key"] for r in found.select("key").collect()), np.uint32)


def spread(plain: DataFrame, k: int, m: int, words: bool, buckets: int, hot: np.ndarray, first_stays: bool, beginning: bytes) -> DataFrame:
    """(bucket, blob): packed super-k-mers for buckets 0 and up, settled spans below 0.

    first_stays: of equal super-k-mers in a chunk the earliest is open and the others are settled; else all are settled.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = Codec(beginning)
        for batch in batches:
            for lo in range(0, batch.num_rows, 1000):
                ids, hashes, texts = _texts(batch.slice(lo, 1000))
                for group in stretches(texts, k, words):
                    yield from chunk(codec, ids, hashes, group)

    def chunk(codec: Codec, ids: np.ndarray, hashes: np.ndarray, group: list[tuple[bytes, int, int]]) -> Iterator[pa.RecordBatch]:
        s = (as_words if words else as_bytes)([p[0] for p in group])
        r = runs_of(s, k, m)
        first, last, key = r.first, r.last, mixed(r.key.astype(np.uint64))
        if len(hot) and (often := np.isin(r.key, hot)).any():
            # Each window of a frequent minimiser travels alone, by its own content.
            n = (last - first + 1)[often]
            alone = np.repeat(first[often], n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
            first, last = np.concatenate((first[~often], alone)), np.concatenate((last[~often], alone))
            key = np.concatenate((key[~often], mixed(s.hashes(alone, k))))
            order = np.argsort(first, kind="stable")
            first, last, key = first[order], last[order], key[order]
        if not len(first):
            return
        piece = np.searchsorted(s.ends, first, "right") - 1
        number = np.array([p[1] for p in group])[piece]
        place = first - s.ends[piece] + np.array([p[2] for p in group])[piece]
        raw = s.raw.tobytes()
        seen: dict[bytes, int] = {}
        same = np.zeros(len(first), np.int64)  # the first super-k-mer of equal content
        strings = []
        for i, (a, b) in enumerate(zip(s.first[first].tolist(), s.last[last + k - 1].tolist())):
            x = raw[a:b]
            same[i] = seen.setdefault(x, i)
            strings.append(x)
        lead = same == np.arange(len(first))
        many = np.bincount(same, minlength=len(first)) > 1
        settled = ~lead if first_stays else many[same]
        bucket = (key % np.uint64(buckets)).astype(np.int64)
        out_bucket, out_blob = [], []
        rows = np.flatnonzero(lead)
        rows = rows[np.argsort(bucket[rows], kind="stable")]
        group_of = bucket[rows] // FINE
        for part in np.split(rows, np.flatnonzero(np.diff(group_of)) + 1):
            out_bucket.append(int(bucket[part[0]]) // FINE)
            out_blob.append(packed_blob(codec, number[part], ids, hashes, place[part], many[part] & (not first_stays), bucket[part] % FINE, [strings[i] for i in part.tolist()]))
        done = np.flatnonzero(settled)
        if len(done):
            out_bucket.append(-1 - int(key[done[0]] % np.uint64(buckets)))
            spans = np.stack((ids[number[done]], hashes[number[done]], place[done], place[done] + last[done] - first[done] + k))
            out_blob.append(codec.pack(spans.tobytes()))
        yield pa.RecordBatch.from_arrays([pa.array(out_bucket, pa.int32()), pa.array(out_blob, pa.binary())], names=["bucket", "blob"])

    return plain.mapInArrow(tidy(run), "bucket int, blob binary")


@dataclass
class Bucket:
    """What has met in a bucket; windows are numbered by their first symbol in ``s``."""

    s: Symbols
    windows: np.ndarray
    string: np.ndarray  # super-k-mer of each window; the columns below have a row for each of those
    doc: np.ndarray
    text_hash: np.ndarray
    place: np.ndarray
    repeated: np.ndarray  # known to be repeated

    def ids(self, at: np.ndarray) -> np.ndarray:
        return self.doc[self.string[at]]

    def hashes(self, at: np.ndarray) -> np.ndarray:
        return self.text_hash[self.string[at]]

    def places(self, at: np.ndarray) -> np.ndarray:
        of = self.string[at]
        return self.place[of] + self.windows[at] - self.s.ends[of]

    def many(self, at: np.ndarray) -> np.ndarray:
        return self.repeated[self.string[at]]


def meet(codec: Codec, blobs: list[bytes], k: int, words: bool) -> Iterator[Bucket]:
    """The buckets of a group, one by one."""
    parts = [unpacked_blob(codec, b) for b in blobs]
    ids, hashes, places, sizes, many, fine = (np.concatenate([p[0][i] for p in parts]) for i in range(6))
    ends = np.concatenate(([0], np.cumsum(sizes.astype(np.int64))))
    joined = b"".join([p[1] for p in parts])
    del parts
    for f in range(FINE):
        own = np.flatnonzero(fine == f)
        if not len(own):
            continue
        s = (as_words if words else as_bytes)([joined[a:b] for a, b in zip(ends[own].tolist(), ends[own + 1].tolist())])
        n = np.diff(s.ends) - k + 1
        string = np.repeat(np.arange(len(own), dtype=np.int32), n)
        windows = np.arange(len(string)) + (s.ends[:-1] - np.cumsum(n) + n)[string]
        yield Bucket(s, windows, string, ids[own], hashes[own], places[own], many[own].astype(bool))


def equal_windows(s: Symbols, a: np.ndarray, b: np.ndarray, k: int) -> np.ndarray:
    """Whether the windows at a[i] and b[i] have the same bytes.

    Only where the pair before is not (a - 1, b - 1) are whole windows compared; else the last symbols are.
    """
    chained = np.zeros(len(a), bool)
    chained[1:] = (np.diff(a) == 1) & (np.diff(b) == 1)
    out = np.zeros(len(a), bool)

    def same(x: np.ndarray, y: np.ndarray, n: int) -> np.ndarray:
        x0, x1, y0, y1 = s.first[x], s.last[x + n - 1], s.first[y], s.last[y + n - 1]
        ok = (x1 - x0) == (y1 - y0)
        for lo in range(0, len(ok), 4_000):
            rows = np.flatnonzero(ok[lo : lo + 4_000]) + lo
            size = (x1 - x0)[rows]
            step = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
            differs = s.raw[np.repeat(x0[rows], size) + step] != s.raw[np.repeat(y0[rows], size) + step]
            ok[rows[np.repeat(np.arange(len(rows)), size)[differs]]] = False
        return ok

    heads = np.flatnonzero(~chained)
    out[heads] = same(a[heads], b[heads], k)
    rest = np.flatnonzero(chained)
    out[rest] = same(a[rest] + k - 1, b[rest] + k - 1, 1)
    # A pair in a chain is equal only if all before it in the chain are.
    chain = np.cumsum(~chained) - 1
    bad = np.flatnonzero(~out)
    if len(bad):
        for c in np.unique(chain[bad]).tolist():
            rows = np.flatnonzero(chain == c)
            out[rows] = same(a[rows], b[rows], k)
    return out


def repeated_spans(
    docs: DataFrame, doc: Column, text: Column, k: int, m: int, words: bool, settle: Callable[[Bucket, int], np.ndarray], first_stays: bool
) -> DataFrame:
    """(doc_id, text_hash, spans): spans of symbols that repeated windows cover, for each document that has any."""
    plain = docs.select(doc.cast("long").alias("doc_id"), F.coalesce(text.cast("string"), F.lit("")).alias("text"))
    plain = plain.select("doc_id", F.xxhash64("text").alias("text_hash"), "text")
    buckets = max(1, -(-4 * text_bytes(plain, "text") // BUCKET))
    beginning = sample_text(plain)
    sent = spread(plain, k, m, words, buckets, hot_minimisers(plain, k, m, words), first_stays, beginning)

    def spans_of(held: Bucket) -> np.ndarray:
        hit = np.flatnonzero(settle(held, k))
        ids, hashes, places = held.ids(hit), held.hashes(hit), held.places(hit)
        new = np.ones(len(hit), bool)
        new[1:] = (np.diff(hit) != 1) | (np.diff(places) != 1) | (np.diff(ids) != 0) | (np.diff(hashes) != 0)
        head = np.flatnonzero(new)
        tail = np.concatenate((head[1:] - 1, [len(hit) - 1])) if len(hit) else head
        return np.stack((ids[head], hashes[head], places[head], places[tail] + k))

    def run(group: pa.Table) -> pa.Table:
        codec = Codec(beginning)
        met = group["bucket"][0].as_py() >= 0
        if met:
            spans = np.concatenate([spans_of(held) for held in meet(codec, group["blob"].to_pylist(), k, words)], axis=1)
        else:
            spans = np.concatenate([np.frombuffer(codec.unpack(b), np.int64).reshape(4, -1) for b in group["blob"].to_pylist()], axis=1)
        out = pa.table({n: pa.array(c) for n, c in zip(("doc_id", "text_hash", "begin", "end"), spans)})
        if met:
            give_back()
        return out

    found = sent.groupBy("bucket").applyInArrow(run, "doc_id long, text_hash long, begin long, end long")
    return durable(found.groupBy("doc_id", "text_hash").agg(F.collect_list(F.struct("begin", "end")).alias("spans")))


def with_spans(docs: DataFrame, doc: Column, text: Column, spans: DataFrame, cut: Callable[[bytes, np.ndarray | None, np.ndarray | None], tuple], fields: str) -> DataFrame:
    """doc_id and what ``cut`` makes of each row's text and the maximal spans of it; texts travel packed."""
    spans = released(spans)
    plain = docs.select(doc.cast("long").alias("doc_id"), F.coalesce(text.cast("string"), F.lit("")).alias("text"))
    beginning = sample_text(plain)
    keyed = plain.select("doc_id", F.xxhash64("text").alias("text_hash"), F.coalesce("doc_id", F.lit(NO_ID).cast("long")).alias("_id"), "text")

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = Codec(beginning)
        for batch in batches:
            for lo in range(0, batch.num_rows, 1000):
                part = batch.slice(lo, 1000)
                packed = [codec.pack(t) for t in part.column(3).cast(pa.binary()).to_pylist()]
                yield pa.RecordBatch.from_arrays([*part.columns[:3], pa.array(packed, pa.binary())], names=["doc_id", "text_hash", "_id", "packed"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = Codec(beginning)
        for batch in batches:
            for lo in range(0, batch.num_rows, 1000):
                part = batch.slice(lo, 1000)
                rows = []
                for packed, found in zip(part.column(1).to_pylist(), part.column(2)):
                    ends = merged(*(found.values.field(i).to_numpy() for i in (0, 1))) if found.is_valid else (None, None)
                    rows.append(cut(codec.unpack(packed), *ends))
                columns = [pa.array(c, kind) for c, kind in zip(zip(*rows), kinds)]
                yield pa.RecordBatch.from_arrays([part.column(0), *columns], names=names)

    schema = T.StructType([T.StructField("doc_id", T.LongType())] + T._parse_datatype_string(fields).fields)
    names = schema.fieldNames()
    kinds = [{"bigint": pa.int64(), "string": pa.string(), "binary": pa.binary()}[f.dataType.simpleString()] for f in schema.fields[1:]]
    packed = keyed.mapInArrow(tidy(pack), "doc_id long, text_hash long, _id long, packed binary")
    joined = packed.join(spans.withColumnRenamed("doc_id", "_id"), ["_id", "text_hash"], "left")
    return joined.select("doc_id", "packed", "spans").mapInArrow(tidy(run), schema)


def merged(begins: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Maximal runs of what the spans cover."""
    order = np.argsort(begins, kind="stable")
    begins, reach = begins[order], np.maximum.accumulate(ends[order])
    new = np.concatenate(([True], begins[1:] > reach[:-1]))
    at = np.flatnonzero(new)
    return begins[at], reach[np.concatenate((at[1:] - 1, [len(reach) - 1]))]
