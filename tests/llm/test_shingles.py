import random

import corpus_pipeline as pipeline
import pyarrow as pa
import numpy as np
from veilmatch.llm.shingles import _pieces, similar_groups

SCHEMA = "doc_id long, text string, component_id int, n int"


def brute_set(text):
    words = (text or "").encode().lower().split()
    return {tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))} if words else set()


def brute_groups(sets):
    label = {i: i for i in sets}
    near = {i: [j for j in sets if 9 * len(sets[i] & sets[j]) >= 4 * (len(sets[i]) + len(sets[j]))] for i in sets}
    while True:
        new = {i: min(label[j] for j in near[i]) for i in sets}
        if new == label:
            return label
        label = new


def copies():
    """Texts of common sentences and own words, and copies with 0 to 6 words changed, some just above 0.8 and some below."""
    rng = random.Random(7)
    lines = [" ".join(f"c{rng.randrange(300)}" for _ in range(12)) for _ in range(5)]
    out = []
    for _ in range(40):
        words = [f"w{rng.randrange(5000)}" for _ in range(rng.randrange(6, 250))]
        for line in rng.sample(lines, rng.randrange(4)):
            cut = rng.randrange(len(words))
            words[cut:cut] = line.split()
        out.append(" ".join(words))
        for changes in range(7):
            other = list(words)
            for at in rng.sample(range(len(words)), min(changes, len(words) - 1)):
                other[at] = f"x{rng.randrange(10**6)}"
            out.append(" ".join(other).upper())
    return out


def test_groups_match_brute_force(spark, sf):
    texts = [r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()] + copies() + [None, "", " \n", "One two", "one  TWO", "one", "a b c d e", "a b c d f"]
    got = similar_groups(spark.createDataFrame([(i, t, 1, 2) for i, t in enumerate(texts)], SCHEMA).repartition(5)).collect()
    want = brute_groups({i: brute_set(t) for i, t in enumerate(texts)})
    assert len(got) == len(texts) and {r.doc_id: r.component_id for r in got} == want
    assert len(set(want.values())) < len(texts) - 100


def test_stage_drops_a_copy_of_similarity_above_0_8(spark, sf):
    words = [f"u{i}" for i in range(230)]
    changed = [f"v{i}" if i in (20, 70, 120, 170, 220) else w for i, w in enumerate(words)]
    docs = spark.createDataFrame([(1, " ".join(words), "en"), (2, " ".join(changed), "en"), (3, " ".join(words[:150]), "en")], "doc_id long, text string, lang string")
    a, b = brute_set(docs.collect()[0].text), brute_set(docs.collect()[1].text)
    assert 0.8 <= len(a & b) / len(a | b) < 0.82
    assert {r.doc_id for r in pipeline.drop_near_duplicates(spark, docs, sf).collect()} == {1, 3}


def test_empty_table_null_and_equal_ids(spark):
    assert similar_groups(spark.createDataFrame([], SCHEMA)).count() == 0
    rows = [(None, "q w e r t", 1, 2), (4, "q w e r t", 1, 2), (4, "q w e r t", 1, 2), (None, "alone", 1, 2)]
    got = similar_groups(spark.createDataFrame(rows, SCHEMA)).collect()
    assert sorted(str(r.component_id) for r in got) == ["4", "4", "4", "None"]


def test_stage_drops_what_simhash_links(spark, sf):
    """Copies whose words are the same shingles in another number: near by fingerprint, and far by five-word shingles."""
    from veilmatch.llm.simhash import near_groups

    rng = random.Random(5)
    words = [f"u{i}" for i in range(60)]
    tail = [f"v{i}" for i in range(20)]
    texts = [" ".join(words * 40), " ".join(words * 40 + tail)]
    docs = spark.createDataFrame([(1, texts[0], "en"), (2, texts[1], "en"), (3, " ".join(rng.sample(words, 60)), "en")], "doc_id long, text string, lang string")
    assert {r.doc_id: r.component_id for r in near_groups(docs).collect()} == {1: 1, 2: 1, 3: 3}
    assert {r.doc_id: r.component_id for r in similar_groups(docs).collect()} == {1: 1, 2: 2, 3: 3}
    assert {r.doc_id for r in pipeline.drop_near_duplicates(spark, docs, sf).collect()} == {1, 3}


def test_checks_in_rounds_leave_nothing_on_the_disk(spark, sf, monkeypatch):
    import glob

    from veilmatch.llm import shingles
    from veilmatch.llm.common import shared_folder

    before = set(glob.glob(f"{shared_folder(spark)}/written-*"))
    monkeypatch.setattr(shingles, "CHECKS", 20)
    texts = copies()
    got = similar_groups(spark.createDataFrame([(i, t, 1, 2) for i, t in enumerate(texts)], SCHEMA))
    want = brute_groups({i: brute_set(t) for i, t in enumerate(texts)})
    assert {r.doc_id: r.component_id for r in got.collect()} == want
    assert set(glob.glob(f"{shared_folder(spark)}/written-*")) == before


def test_whole_texts_go_in_short_batches(spark):
    from veilmatch.llm.common import BATCH, short_batches

    before, rows = spark.conf.get(BATCH), spark.range(2500).repartition(1)
    sizes = lambda: [r.n for r in rows.mapInArrow(lambda batches: (pa.RecordBatch.from_arrays([pa.array([b.num_rows])], names=["n"]) for b in batches), "n long").collect()]
    with short_batches(spark):
        assert sizes() == [1000, 1000, 500]
    assert spark.conf.get(BATCH) == before and sizes() == [2500]


def test_members_of_large_keys_are_looked_at_in_bounded_pieces():
    wide = np.array([1, 1, 50, 3, 3, 3, 3, 2000, 1, 1, 999, 4])
    got = _pieces(np.arange(12), wide, 10)
    assert np.concatenate(got).tolist() == list(range(12)) and all(len(p) for p in got)
    assert all(wide[p].sum() - wide[p].max() <= 10 for p in got)
    assert sum(len(p) for p in _pieces(np.arange(2048), np.full(2048, 10_000))) == 2048 and max(len(p) for p in _pieces(np.arange(2048), np.full(2048, 10_000))) < 30
    assert _pieces(np.arange(0), np.arange(0)) == []
