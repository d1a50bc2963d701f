import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from veilmatch.llm.bitsliced import Block, quantised, top_k


def brute(ids, values, query, own, k):
    rows = [(-int(v @ query), i) for i, v in zip(ids.tolist(), values) if i != own]
    return sorted(rows)[:k]


@pytest.mark.parametrize("spread,width,keep", [(3, 4, 1), (1000, 16, 5), (1, 8, 2), (5000, 64, 4), (7, 3, 12)])
def test_block_equals_brute_force(spread, width, keep):
    rng = np.random.default_rng(spread)
    n = 900
    values = rng.integers(-spread, spread + 1, (n, width))
    values[100:200] = values[5]
    ids = rng.permutation(n)
    block = Block(ids, values, keep)
    for own in range(0, 30):
        q = rng.integers(-spread, spread + 1, width) if own % 3 else values[own]
        got, scores = block.best(q, own, 10)
        assert [(-s, i) for i, s in zip(got.tolist(), scores.tolist())] == brute(ids, values, q, own, 10)


def test_query_over_blocks_with_odd_rows(spark):
    rng = random.Random(2)
    rows = [(i, [rng.uniform(-1, 1) for _ in range(6)], "x", 1) for i in range(600)]
    rows += [(700 + i, rows[3][1], "x", 1) for i in range(40)] + [(700, rows[3][1], "x", 1)]
    odd = [(800, None), (900, [1.0, None, 0.0, 0.0, 0.0, 0.0]), (901, [math.nan] * 6), (1000, [math.inf] * 6), (None, [1.0] * 6)]
    df = spark.createDataFrame(rows + [(i, v, "x", 1) for i, v in odd], "vec_id long, embedding array<float>, score string, rank int")
    ready = df.select("vec_id", quantised(F.col("embedding")).alias("q")).where("vec_id is not null and q is not null")
    got = {}
    for r in top_k(ready, ready.where("vec_id % 100 = 0"), block_rows=100, block_queries=3).collect():
        got.setdefault(r.query_id, []).append((r["rank"], r.vec_id, r.score))
    clean = [(i, [math.floor(1024 * float(np.float32(x))) for x in v]) for i, v, *_ in rows]
    for q in (0, 100, 200, 300, 400, 500, 700):
        v = next(v for i, v in clean if i == q)
        want = sorted((-sum(a * b for a, b in zip(v, w)), i) for i, w in clean if i != q)[:10]
        assert sorted(got.pop(q)) == [(n + 1, i, -s) for n, (s, i) in enumerate(want)]
    assert not got


def test_few_rows_and_none(spark):
    two = spark.createDataFrame([(0, [1, 2]), (1, [3, 4])], "vec_id long, q array<long>")
    assert [(r.query_id, r["rank"], r.vec_id, r.score) for r in top_k(two, two.where("vec_id = 0")).collect()] == [(0, 1, 1, 11)]
    assert top_k(two.where("false"), two.where("false")).count() == 0
