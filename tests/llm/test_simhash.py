import random

import pytest
import xxhash

from veilmatch.llm.components import components
from veilmatch.llm.simhash import _forest, near_groups, near_links

SCHEMA = "doc_id long, text string, fingerprint string, component_id int, a int"


def brute_print(text):
    words = (text or "").encode().lower().split()
    if not words:
        return 0
    shingles = [words] if len(words) <= 3 else [words[i : i + 3] for i in range(len(words) - 2)]
    h = [xxhash.xxh64_intdigest(b" ".join(s), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def brute_groups(prints):
    label = {i: i for i in prints}
    while True:
        new = {i: min(label[j] for j in prints if (prints[i] ^ prints[j]).bit_count() <= 3) for i in prints}
        if new == label:
            return label
        label = new


def test_fingerprints_and_groups_match_brute_force(spark, sf):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    extra = [(9001, None), (9002, ""), (9003, " \t\n "), (9004, "One"), (9005, "ONE"), (9006, "a b"), (9007, rows[0][1]), (9007, rows[0][1]), (9008, "Å É x y z ﬀ"), (9009, "w " * 120_000)]
    rows += extra
    docs = spark.createDataFrame([(i, t, "x", 1, 2) for i, t in rows], SCHEMA)
    got = near_groups(docs).collect()
    assert len(got) == len(rows)
    prints = {i: brute_print(t) for i, t in rows}
    want = brute_groups(prints)
    for r in got:
        assert r.fingerprint & (2**64 - 1) == prints[r.doc_id]
        assert r.component_id == want[r.doc_id]


def test_empty_table_and_null_id(spark):
    assert near_groups(spark.createDataFrame([], SCHEMA)).count() == 0
    got = near_groups(spark.createDataFrame([(None, "q w e r t", "x", 1, 2), (4, "q w e r t", "x", 1, 2)], SCHEMA)).collect()
    assert {r.component_id for r in got} == {4}


def test_links_connect_what_is_near_also_in_a_large_group(spark):
    rng = random.Random(5)
    base = rng.getrandbits(64)
    near = {base ^ (1 << rng.randrange(64)) ^ (1 << rng.randrange(64)) ^ (1 << rng.randrange(64)) for _ in range(300)} | {rng.getrandbits(64) for _ in range(200)}
    signed = [x - 2**64 if x >= 2**63 else x for x in near]
    links = near_links(spark.createDataFrame([(x,) for x in signed], "fingerprint long"))
    got = {r.node: r.label for r in components(links).collect()}
    want = brute_groups({x: x & (2**64 - 1) for x in signed})
    groups = {}
    for x in signed:
        groups.setdefault(want[x], set()).add(x)
    mine = {}
    for x in signed:
        mine.setdefault(got.get(x, x), set()).add(x)
    assert sorted(map(sorted, groups.values())) == sorted(map(sorted, mine.values()))


def test_forest_cut_by_bytes_equals_direct(monkeypatch):
    import numpy as np

    from veilmatch.llm import simhash

    rng = np.random.default_rng(1)
    low = rng.integers(0, 2**32, 40, dtype=np.uint64)
    values = np.unique((low[rng.integers(0, 40, 700)] ^ (np.uint64(1) << rng.integers(0, 32, 700).astype(np.uint64))) << np.uint64(32) | np.uint64(77))

    def classes(edges):
        parent = {int(v): int(v) for v in values}

        def root(x):
            while parent[x] != x:
                x = parent[x]
            return x

        for a, b in edges:
            parent[root(a)] = root(b)
        return len({root(int(v)) for v in values})

    monkeypatch.setattr(simhash, "DIRECT", 10)
    cut = classes(_forest(values, 0, 3))
    monkeypatch.setattr(simhash, "DIRECT", 10_000)
    assert cut == classes(_forest(values, 0, 3))


def test_too_many_bits_are_refused(spark):
    with pytest.raises(ValueError):
        near_links(spark.createDataFrame([(1,)], "fingerprint long"), 4)
