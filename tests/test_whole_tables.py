import hashlib

from veilmatch.plans import catalog


def positions(spark, sf):
    return {r.p_partkey: (set(r.pos), r.p_name, r.p_size) for r in catalog.part(spark, sf).collect()}


def edits(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        old, row = row, [i]
        for j, y in enumerate(b, 1):
            row.append(min(old[j] + 1, row[-1] + 1, old[j - 1] + (x != y)))
    return row[-1]


def test_part_pairs_cover_all_parts(spark, sf):
    parts = positions(spark, sf)
    keys = sorted(parts)
    want = [(a, b) for i, a in enumerate(keys) for b in keys[i + 1 :]]
    rules = {
        "dice_part_pairs_all": lambda a, b: (2 * len(a & b), max(len(a) + len(b), 1)),
        "jaccard_part_pairs_all": lambda a, b: (len(a & b), max(len(a | b), 1)),
        "overlap_part_pairs_all": lambda a, b: (len(a & b), max(min(len(a), len(b)), 1)),
    }
    for name, rule in rules.items():
        got = {(r.a_id, r.b_id): (r.num, r.den) for r in catalog.QUERIES[name](spark, sf).collect()}
        assert got == {(a, b): rule(parts[a][0], parts[b][0]) for a, b in want}
    equal = {(r.a_id, r.b_id): r.equal for r in catalog.QUERIES["exact_similarity_all"](spark, sf).collect()}
    assert equal == {(a, b): int(parts[a][2] == parts[b][2]) for a, b in want}
    apart = {(r.a_id, r.b_id): r.edits for r in catalog.QUERIES["levenshtein_part_pairs_all"](spark, sf).collect()}
    assert set(apart) == set(want) and all(apart[w] == edits(parts[w[0]][1], parts[w[1]][1]) for w in want[::97])


def test_registry_pairs_and_texts_are_whole(spark, sf):
    n, m = catalog.ex(spark, sf).count(), catalog.ey(spark, sf).count()
    scores = catalog.QUERIES["pair_scores_all"](spark, sf)
    assert scores.count() == n * m
    best = {(r.x_id, r.y_id, r.num, r.den) for r in catalog.bp(spark, sf).collect()}
    assert best <= {(r.x_id, r.y_id, r.num, r.den) for r in scores.select("x_id", "y_id", "num", "den").collect()}
    rules = catalog.QUERIES["pair_completeness_rules_all"](spark, sf).collect()
    delta = {r.rec_id: r.name_delta for f in (catalog.ex(spark, sf), catalog.ey(spark, sf)) for r in f.select("rec_id", "name_delta").collect()}
    assert len(rules) == n * m
    for r in rules:
        x, y = delta[r.x_rec_id], delta[r.y_rec_id]
        assert (r.by_min, r.by_product, r.by_left, r.by_mean) == (min(x, y), x * y // 100, x, (x + y) // 2)


def test_accents_of_all_texts(spark, sf, tmp_path):
    from pyspark.sql import functions as F

    from veilmatch.functions import text

    long = "plain words " * 100
    spark.createDataFrame([(1, long + "é", "en"), (2, long + "e", "en"), (3, long + "o", "fr")], "doc_id long, text string, lang string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r.doc_id: r.digest for r in catalog.QUERIES["normalise_accents_all"](spark, str(tmp_path)).collect()}
    assert set(got) == {1, 2, 3} and got[2] != got[3]
    want = spark.range(1).select(text.normalise(F.lit(long + "é"))).first()[0]
    assert got[1] == hashlib.md5(want.encode()).hexdigest()


def test_dense_maps_of_parts_are_dealt_over_the_cores(spark, tmp_path):
    names = [(i, n, "b", 1) for i, n in enumerate(["anna anna", "a", "", None, "O'Brien", *["x y z"] * 40])]
    spark.createDataFrame(names, "p_partkey long, p_name string, p_brand string, p_size int").coalesce(1).write.parquet(f"{tmp_path}/part.parquet")
    got = catalog.QUERIES["bigram_dense"](spark, str(tmp_path))
    assert got.rdd.getNumPartitions() >= spark.sparkContext.defaultParallelism
    ones = {r.p_partkey: r.ones for r in got.collect()}
    assert len(ones) == 45 and [ones[i] for i in range(6)] == [5, 0, 0, None, 6, 4]
