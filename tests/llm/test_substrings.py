import hashlib
from collections import defaultdict

import numpy as np
import pytest

from veilmatch.llm import superkmers
from veilmatch.llm.substrings import classes, dedup_words
from veilmatch.llm.superkmers import Bucket, as_words


def brute(rows, k=35):
    texts = {(i, t or ""): (t or "").encode().split() for i, t in rows}
    places = defaultdict(int)
    for words in texts.values():
        for a in range(len(words) - k + 1):
            places[tuple(words[a : a + k])] += 1
    out = {}
    for key, words in texts.items():
        gone = [False] * len(words)
        for a in range(len(words) - k + 1):
            if places[tuple(words[a : a + k])] > 1:
                gone[a : a + k] = [True] * k
        left = b" ".join(w for w, g in zip(words, gone) if not g)
        out[key] = (len(words), sum(gone), hashlib.sha256(left).hexdigest())
    return out


def odd(base):
    words = base.split()
    return [
        (8000, None), (8001, ""), (8002, " \n\t"), (8003, "one two"), (8004, " ".join(words[:35])), (8005, "\t".join(words[:36])), (8006, "x " * 34), (8007, "y " * 36), (8008, "z " * 400),
        (8009, " ".join(words[:80])), (8009, " ".join(words[:80])), (8009, "other " + " ".join(words[5:70])), (None, " ".join(words[10:90])), (8010, "a b " * 40), (8011, "é\x1fx\x85y " * 40),
    ]


@pytest.mark.parametrize("hot,chunk", [(4096, 1 << 21), (8, 4000)])
def test_words_match_brute_force(spark, sf, monkeypatch, hot, chunk):
    monkeypatch.setattr(superkmers, "HOT", hot)
    monkeypatch.setattr(superkmers, "CHUNK", chunk)
    monkeypatch.setattr(superkmers, "BUCKET", 1 << 18)
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    rows += odd(rows[3][1] + " " + rows[0][1]) + [(8100 + i, "shared " * 3 + " ".join(rows[1][1].split()[:60]) + f" tail{i} {i} " * 20) for i in range(30)]
    docs = spark.createDataFrame([(i, t, "x", 1) for i, t in rows], "doc_id long, text string, spans string, bucket int").repartition(3)
    got = dedup_words(docs).collect()
    assert len(got) == len(rows)
    want = brute(rows)
    by_id = defaultdict(set)
    for (i, _), v in want.items():
        by_id[i].add(v)
    for r in got:
        assert (r.n_words, r.n_removed, r.kept_sha256) in by_id[r.doc_id], r.doc_id
        assert hashlib.sha256(r.kept.encode()).hexdigest() == r.kept_sha256
    assert sum(r.n_removed for r in got) > 1000


def test_empty_table(spark):
    assert dedup_words(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_collisions_are_told_apart(monkeypatch):
    from veilmatch.llm import substrings

    rng = np.random.default_rng(0)
    parts = [" ".join(rng.choice(["a", "bb", "c"], 12)).encode() for _ in range(60)]
    s = as_words(parts)
    k = 5
    windows = np.concatenate([np.arange(a, b - k + 1) for a, b in zip(s.ends[:-1], s.ends[1:])])
    zero = np.zeros(len(windows), np.int64)
    monkeypatch.setattr(substrings, "mixed", lambda x: x % np.uint64(7))
    order, new = classes(Bucket(s, windows, zero, zero[:1], zero[:1], zero[:1], zero[:1].astype(bool)), k)
    text = s.raw.tobytes()
    content = [text[s.first[w] : s.last[w + k - 1]] for w in windows[order]]
    groups = np.cumsum(new)
    assert len(set(content)) == groups[-1]
    assert len({(c, g) for c, g in zip(content, groups)}) == groups[-1]
