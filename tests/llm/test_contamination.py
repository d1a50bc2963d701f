import random
from collections import defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from veilmatch.llm.contamination import Words, common_words, contaminated, places_of

DOCS = "doc_id long, text string, lang string, item_id int"


def brute_lcs(a, b):
    row = [0] * (len(b) + 1)
    for x in a:
        old = row[:]
        for j, y in enumerate(b):
            row[j + 1] = old[j] + 1 if x == y else max(row[j], old[j + 1])
    return row[-1]


def test_common_words_is_the_longest_subsequence():
    rng = random.Random(1)
    for _ in range(300):
        a, b = ([rng.randrange(6) for _ in range(rng.randrange(0, 70))] for _ in range(2))
        assert common_words(places_of(a), len(a), b) == brute_lcs(a, b)


@pytest.fixture(scope="module")
def planted(spark, sf):
    docs = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    rng = random.Random(3)
    rows, want = [], {}
    for n, (i, t) in enumerate(items):
        words = t.split()
        host = docs[n % len(docs)][1].split()
        changed = [rng.choice(host) if rng.random() < (0, 0.1, 0.15)[n % 3] else w for w in words]
        cut = rng.randrange(len(host))
        rows.append((5000 + n, " ".join(host[:cut] + changed + host[cut:])))
        want[5000 + n] = (i, n % 3)
    odd = [(7000, None), (7001, ""), (7002, " . "), (7003, items[0][1]), (7003, items[0][1]), (None, items[1][1].upper()), (7004, "filler words " * 60_000 + items[2][1])]
    frame = spark.createDataFrame([(i, t, "x", 5) for i, t in docs + rows + odd], DOCS).repartition(3)
    asked = spark.createDataFrame([*items, (900, None), (901, ""), (902, "...")], "item_id long, text string")
    return docs, items, want, contaminated(frame, asked).collect()


def test_planted_items_are_found(planted):
    docs, items, want, got = planted
    found = defaultdict(set)
    for r in got:
        found[r.doc_id].add(r.item_id)
    for kind in (0, 1, 2):
        own = [d for d, (_, k) in want.items() if k == kind]
        hit = sum(want[d][0] in found[d] for d in own)
        assert hit >= (len(own) if kind == 0 else 0.9 * len(own)), kind
    assert found[7003] == {items[0][0]} and found[None] == {items[1][0]} and items[2][0] in found[7004]
    assert sum(r.doc_id == 7003 for r in got) == 2
    assert not any(r.item_id >= 900 for r in got)


def test_clean_documents_are_left_alone(planted):
    docs, items, _, got = planted
    w = Words.of([t for _, t in items])
    known = {i: w.ids[a:b].tolist() for (i, _), a, b in zip(items, w.ends[:-1], w.ends[1:])}
    texts = dict(docs)
    for r in got:
        if r.doc_id in texts:
            own = Words.of([texts[r.doc_id]]).ids.tolist()
            assert brute_lcs(known[r.item_id], own) >= 0.45 * len(known[r.item_id])
    # Every item that stands whole in a document is reported.
    have = {(r.doc_id, r.item_id) for r in got}
    for d, t in texts.items():
        padded = " " + " ".join(map(str, Words.of([t]).ids)) + " "
        for i, ids in known.items():
            if " " + " ".join(map(str, ids)) + " " in padded:
                assert (d, i) in have


def test_answers_and_empty_tables(spark):
    text = " ".join(f"word{i}" for i in range(40))
    docs = spark.createDataFrame([(1, "start " + text + " the answer is fortytwo indeed so"), (2, "nothing here at all " * 5)], "doc_id long, text string")
    asked = spark.createDataFrame([(1, text, "fortytwo indeed so")], "item_id long, text string, answer string")
    got = contaminated(docs, asked, answer="answer").collect()
    assert [(r.doc_id, r.item_id, r.answer_found) for r in got] == [(1, 1, True)]
    assert contaminated(docs, asked.where("false")).count() == 0
    assert contaminated(docs.where("false"), asked.select("item_id", F.col("text"))).count() == 0
    assert np.array(Words.of([None]).ids).size == 0


def brute_found(texts, items, answers):
    """The word rule on every passage of every text against every item."""
    out = set()
    w, asked = Words.of([t for _, t in items]), Words.of([answers.get(i) for i, _ in items])
    known = [w.ids[a:b].tolist() for a, b in zip(w.ends[:-1], w.ends[1:])]
    closing = [asked.ids[a:b].tolist() or k[-max(3, len(k) // 4) :] for a, b, k in zip(asked.ends[:-1], asked.ends[1:], known)]
    rule = [(i, k, len(k), places_of(k), c, places_of(c)) for (i, _), k, c in zip(items, known, closing) if k]
    for d, text in texts:
        own = Words.of([text]).ids.tolist()
        for begin in range(0, max(1, len(own) - 16), 16):
            for i, _, size, places, close, ends in rule:
                around = own[max(0, begin - size) : begin + 32 + size]
                n = common_words(places, size, around)
                if n >= max(1, 0.45 * size) and (n >= 0.6 * size or common_words(ends, len(close), around) >= 0.8 * len(close)):
                    out.add((d, i))
    return out


def test_all_that_passes_the_word_rule_is_found(spark, sf):
    rng = random.Random(11)
    hosts = [r.text for r in spark.read.parquet(f"{sf}/documents.parquet").limit(60).collect()]
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    items += [(500 + n, " ".join(t.split()[a : a + m])) for n, (t, a, m) in enumerate((rng.choice(hosts), rng.randrange(20), rng.choice((5, 16, 20, 90, 130))) for _ in range(20))]
    answers = {i: "the answer of " + t.split()[0] for i, t in items[:60:3]}
    texts = [(n, t) for n, t in enumerate(hosts)]
    for n in range(200):
        i, t = items[n % len(items)]
        host = rng.choice(hosts).split()
        part = [rng.choice(host) if rng.random() < (0, 0.25, 0.35, 0.4, 0.5)[n % 5] else w for w in t.split()]
        part += answers[i].split() if i in answers and n % 2 else []
        cut = rng.randrange(len(host))
        texts.append((1000 + n, " ".join(host[:cut] + part + host[cut:])))
    docs = spark.createDataFrame(texts, "doc_id long, text string").repartition(3)
    asked = spark.createDataFrame([(i, t, answers.get(i)) for i, t in items], "item_id long, text string, answer string")
    got = {(r.doc_id, r.item_id) for r in contaminated(docs, asked, answer="answer").collect() if not r.latent}
    assert got == brute_found(texts, items, answers)


def test_items_in_small_tables(spark, sf, monkeypatch):
    from veilmatch.llm import contamination

    known = [[1, 2, 3], [], [4] * 70, [2, 9], [5, 6, 7]]
    whole = contamination.tables_of(known, [k[-3:] for k in known])
    monkeypatch.setattr(contamination, "TABLE", 10)
    cut = contamination.tables_of(known, [k[-3:] for k in known])
    assert len(whole) == 1 and len(cut) > 1 and sum((p.items.tolist() for p in cut), []) == whole[0].items.tolist() == [0, 2, 3, 4]


def test_sentences_in_another_order_are_found_by_their_cosine(spark, sf):
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    hosts = [r.text for r in spark.read.parquet(f"{sf}/documents.parquet").limit(120).collect() if r.text and len(r.text.split()) > 60][:40]
    rows = [(n, t) for n, t in enumerate(hosts)]
    for n, (_, t) in enumerate(items):
        words, host = t.split(), hosts[n % len(hosts)].split()
        e = len(words) // 8
        mixed = [w for k in range(5, -1, -1) for w in words[k * e : (k + 1) * e]] + words[6 * e :]
        rows.append((1000 + n, " ".join(host[:40] + mixed + host[40:80])))
    got = contaminated(spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")).collect()
    hit = {(r.doc_id - 1000, r.item_id) for r in got}
    share = sum((n, i) in hit for n, (i, _) in enumerate(items)) / len(items)
    assert share >= 0.9 and any(r.latent for r in got), share


def test_items_of_one_id_keep_their_own_answers(spark):
    text = " ".join(f"word{i}" for i in range(40))
    half = " ".join(f"word{i}" for i in range(20))
    docs = spark.createDataFrame([(1, half + " the first answer here"), (2, half + " another reply there")], "doc_id long, text string")
    asked = spark.createDataFrame([(7, text, "the first answer here"), (7, text, "another reply there")], "item_id long, text string, answer string")
    assert sorted((r.doc_id, r.item_id) for r in contaminated(docs, asked, answer="answer").collect()) == [(1, 7), (2, 7)]


def test_bound_counts_places_in_lanes():
    from veilmatch.llm import contamination as C

    rng = np.random.default_rng(5)
    for most in (1, 3, 5):  # 64 places a lane: whole bytes hold up to three
        lanes = rng.integers(1, most + 1, 30)
        cuts = np.cumsum(lanes) - lanes
        counts = rng.integers(0, 65, (40, int(lanes.sum()))).astype(np.uint8)
        assert np.array_equal(C._summed(counts, cuts, lanes), np.add.reduceat(counts, cuts, axis=1, dtype=np.int64))
    words = np.array([2, 5, 9], np.uint64)
    assert C.rows_of(words, np.array([9, 1, 2, 10, 5], np.uint64)).tolist() == [2, 3, 0, 3, 1]


def test_a_fit_on_fewer_documents_finds_what_one_on_all_does(spark, sf, monkeypatch):
    """Recall of the bounded fit (every passage is searched either way)."""
    from veilmatch.llm import contamination

    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    hosts = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    rows = list(hosts)
    for n, (_, t) in enumerate(items):
        words, host = t.split(), (hosts[n % len(hosts)][1] or "").split()
        e = len(words) // 8
        mixed = [w for k in range(5, -1, -1) for w in words[k * e : (k + 1) * e]] + words[6 * e :]
        rows.append((5000 + n, " ".join(host[:40] + mixed + host[40:80])))
    docs, asked = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    every = {(r.doc_id, r.item_id) for r in contaminated(docs, asked).collect()}
    monkeypatch.setattr(contamination, "FIT_DOCS", len(rows) // 5)
    some = {(r.doc_id, r.item_id) for r in contaminated(docs, asked).collect()}
    assert len(every) > len(items) / 2 and len(every & some) >= 0.9 * len(every)


def test_the_decomposition_sees_every_document_and_item(spark, monkeypatch):
    """The sums that it is fitted on are those of all passages, whatever FIT_DOCS is; before, of a sample of FIT_DOCS documents and items."""
    from veilmatch.llm import contamination

    random.seed(4)
    texts = [" ".join(random.choices([f"w{i}" for i in range(60)], k=n)) for n in (1, 5, 16, 17, 31, 32, 33, 40, 64, 100, 300)] + ["same " * 50, None, ""]
    idf = np.linspace(1.0, 2.0, contamination.BINS)
    want = {}
    for t in texts:
        bins = contamination.Words.of([t]).bins
        for first in range(0, max(1, len(bins) - contamination.HALF) if len(bins) else 0, contamination.HALF):
            own = bins[first : first + 2 * contamination.HALF]
            for u in own:
                for v in own:
                    want[u, v] = want.get((u, v), 0.0) + 1 / (idf[own] ** 2).sum()
    docs = spark.createDataFrame([(t,) for t in texts], "text string").repartition(3)
    for docs_a_task, words in ((1, 1 << 27), (1000, 100)):
        monkeypatch.setattr(contamination, "FIT_DOCS", docs_a_task)
        monkeypatch.setattr(contamination, "FIT_WORDS", words)
        got = np.zeros((contamination.BINS, contamination.BINS))
        for r in contamination.shared_passages(docs, idf, len(texts)).collect():
            part = np.frombuffer(r["part"], np.float32)
            got[r["bin"], r["bin"] :] += part
            got[r["bin"] :, r["bin"]] += part
        assert {(int(u), int(v)) for u, v in zip(*np.nonzero(got))} == {(int(u), int(v)) for u, v in want}
        assert all(abs(got[u, v] - n) < 1e-4 * n for (u, v), n in want.items())
