import numpy as np
from pyspark.sql import functions as F

from veilmatch.operators import baselines, blocks, covers, match
from veilmatch.plans import catalog


def test_patterns_of_blocks_are_those_of_pairs(spark, sf):
    x, y = catalog.ex(spark, sf).limit(60), catalog.ey(spark, sf).limit(70)
    x = x.withColumn("postcode", F.when(F.col("rec_id") % 7 > 0, F.col("postcode")))
    want = match.pairs(x, y).select(*baselines.agreements(None)).groupBy(*baselines.FIELDS).agg(F.count("*").alias("n"))
    got = blocks.pattern_counts(x, y)
    assert got.dtypes == want.dtypes and sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
    assert blocks.pattern_counts(x, y.where("false")).count() == 0


def test_part_pairs_are_dealt_over_the_cores(spark, sf):
    assert catalog.all_part_pairs(spark, sf).rdd.getNumPartitions() >= spark.sparkContext.defaultParallelism


def test_missing_part_names_have_no_dice(spark, tmp_path):
    rows = [(1, "ab cd", "b", 1), (2, None, "b", 1), (3, "ab", "b", 2), (4, "", "b", 2)]
    spark.createDataFrame(rows, "p_partkey long, p_name string, p_brand string, p_size int").write.parquet(f"{tmp_path}/part.parquet")
    got = {(r.a_id, r.b_id): (r.num, r.den) for r in catalog.QUERIES["dice_part_pairs_all"](spark, str(tmp_path)).collect()}
    assert got == {(1, 2): (None, 1), (1, 3): (2, 5), (1, 4): (0, 4), (2, 3): (None, 1), (2, 4): (None, 1), (3, 4): (0, 1)}


def test_items_by_cover_with_odd_rows(spark, monkeypatch):
    monkeypatch.setattr(covers, "ITEMS", 2)  # more than one block
    docs = [(5, "abcdef"), (3, "abcdef"), (7, "xyz"), (8, None), (9, "ab"), (None, "abcdefgh"), (4, "abc"), (4, "def"), (4, "cde bcd"), (6, "é is e")]
    items = [(1, "abcdefgh"), (2, "xyzz"), (10, "qq"), (11, None), (12, "cde bcd"), (12, "zzz")]
    got = covers.best(spark.createDataFrame(items, "x_id long, a string"), spark.createDataFrame(docs, "y_id long, b string"), 3)
    grams = lambda t: {t[i : i + 3] for i in range(len(t or "") - 2)}
    total = {}
    for x, a in items:
        for y, b in docs:
            n = len(grams(a) & grams(b and b.replace("é", "*")))
            total[x, y] = total.get((x, y), 0) + n
    want = set()
    for x in {i for i, _ in items}:
        den = min([len(grams(a)) for i, a in items if i == x and grams(a)], default=0)
        rank = sorted(((-n, y is not None, y or 0, y) for (i, y), n in total.items() if i == x and n))
        if rank:
            want.add((x, rank[0][3], -rank[0][0], den))
    assert {tuple(r) for r in got.collect()} == want


def test_nearest_vectors_with_odd_rows(spark, tmp_path, monkeypatch):
    from veilmatch.plans import more  # noqa: F401

    rng = np.random.default_rng(2)
    rows = [(i, [float(np.float32(v)) for v in rng.normal(size=6)]) for i in range(40)]
    rows += [(50, rows[3][1]), (51, rows[3][1]), (60, None), (61, [1.0, None, 1.0, 1.0, 1.0, 1.0])]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    want = {}
    for x, a in rows:
        for y, b in rows:
            if x != y:
                c = None if x > 59 or y > 59 else round(float(np.dot(a, b) / np.sqrt(np.dot(a, a) * np.dot(b, b))), 6)
                want[x] = max(want.get(x, (-9, 0)), (-2 if c is None else c, -y))
    for size in (covers.ROWS, 11):
        monkeypatch.setattr(covers, "ROWS", size)
        got = {r.x_id: (-2 if r.cosine is None else r.cosine, -r.y_id) for r in catalog.QUERIES["embedding_best"](spark, str(tmp_path)).collect()}
        assert got == want
