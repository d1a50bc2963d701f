import hashlib
from collections import defaultdict

import numpy as np
import pytest
import xxhash

from veilmatch.llm import superkmers
from veilmatch.llm.suffixes import Suffixes, common_extension, dedup_bytes, later
from veilmatch.llm.superkmers import NO_ID, Bucket, as_bytes


def brute(rows, k=100):
    def signed(x):
        return x - 2**64 if x >= 2**63 else x

    texts = {(NO_ID if i is None else i, signed(xxhash.xxh64_intdigest((t or "").encode(), 42))): (t or "").encode() for i, t in rows}
    seen, out = set(), {}
    for key in sorted(texts):
        raw = texts[key]
        gone = np.zeros(len(raw), bool)
        for a in range(len(raw) - k + 1):
            w = raw[a : a + k]
            if w in seen:
                gone[a : a + k] = True
            seen.add(w)
        edges = np.diff(np.concatenate(([0], gone.astype(int), [0])))
        left = np.frombuffer(raw, np.uint8)[~gone].tobytes()
        out[key] = (len(raw), int(gone.sum()), int((edges == 1).sum()), hashlib.sha256(left).hexdigest())
    return out


@pytest.mark.parametrize("hot,chunk", [(4096, 1 << 21), (8, 3000)])
def test_bytes_match_brute_force(spark, sf, monkeypatch, hot, chunk):
    monkeypatch.setattr(superkmers, "HOT", hot)
    monkeypatch.setattr(superkmers, "CHUNK", chunk)
    monkeypatch.setattr(superkmers, "BUCKET", 1 << 18)
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").limit(60).collect()]
    base = rows[3][1] + rows[0][1]
    rows += [
        (8000, None), (8001, ""), (8002, "x" * 99), (8003, "x" * 100), (8004, "y" * 101), (8005, "ab" * 300), (8006, base[7:106]), (8007, base[7:107]), (8008, "é" * 120), (8009, base[:400]), (8009, base[:400]),
        (8009, "q" + base[30:500]), (None, base[:300]), (-5, base[100:260]), (8010, "t" * 5000),
    ]
    rows += [(8100 + i, f"{i} head " * 9 + rows[1][1][:300] + f" tail {i * 7} " * 9) for i in range(25)]
    docs = spark.createDataFrame([(i, t, "x", 1) for i, t in rows], "doc_id long, text string, spans string, bucket int").repartition(3)
    got = dedup_bytes(docs).collect()
    assert len(got) == len(rows)
    by_id = defaultdict(set)
    for (i, _), v in brute(rows).items():
        by_id[None if i == NO_ID else i].add(v)
    for r in got:
        assert (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) in by_id[r.doc_id], r.doc_id
        assert hashlib.sha256(r.kept).hexdigest() == r.kept_sha256
    assert sum(r.n_removed for r in got) > 5000


def test_empty_table(spark):
    assert dedup_bytes(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_suffix_order_and_extension():
    rng = np.random.default_rng(4)
    raw = rng.integers(97, 99, 700, dtype=np.uint8)
    raw[300:420] = raw[20:140]
    s = as_bytes([raw.tobytes()])
    k = 40
    at = rng.permutation(700 - k + 1)
    sort = Suffixes(s, at, rng.permutation(len(at)), k)
    order = sort.order()
    assert sorted(order.tolist()) == list(range(len(at)))
    text = raw.tobytes()
    content = [text[a : a + k] for a in at[order]]
    groups = [c[:16] for c in content]
    for i in range(1, len(order)):
        if groups[i] == groups[i - 1]:
            assert (content[i - 1], sort.rank[order[i - 1]]) < (content[i], sort.rank[order[i]])
    a, b = rng.integers(0, 600, 200), rng.integers(0, 600, 200)
    a[0], b[0] = 20, 300
    want = [next((n for n in range(k) if text[x + n] != text[y + n]), k) for x, y in zip(a, b)]
    assert common_extension(s, a, b, k).tolist() == want and want[0] == k


def test_hash_collisions_are_verified(monkeypatch):
    from veilmatch.llm import suffixes

    class Weak:
        def __init__(self, s):
            self.raw, self.first, self.last, self.sums, self.ends, self.s = s.raw, s.first, s.last, s.sums, s.ends, s

        def hashes(self, at, n):
            return self.s.hashes(at, n) % np.uint64(5)

    rng = np.random.default_rng(1)
    raw = rng.integers(97, 99, 300, dtype=np.uint8)
    s = as_bytes([raw.tobytes()])
    k = 8
    windows = np.arange(300 - k + 1)
    zero = np.zeros(len(windows), np.int64)
    got = later(Bucket(Weak(s), windows, zero, zero[:1], zero[:1], zero[:1], zero[:1].astype(bool)), k)
    seen, want = set(), []
    for a in windows:
        w = raw[a : a + k].tobytes()
        want.append(w in seen)
        seen.add(w)
    assert got.tolist() == want and suffixes.BYTES == 100
