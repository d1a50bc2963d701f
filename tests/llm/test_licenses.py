import re

from veilmatch.llm.licenses import BASE, TEMPLATES, scan_licenses

ODD = [
    None, "", "!!!", "Apache License", "apache-license APACHE/LICENSE", "the apache  licensex", "éapache license", "GNU General Public License, cc by cc by mit license",
    "Permission is hereby granted, free of charge, to any person obtaining a copy of this software", "K mit license", "Mozilla Public License", "word " * 50_000 + "MIT License", "cc", "by cc",
]


def brute(text):
    low = (text or "").translate({c: c + 32 for c in range(65, 91)})
    words = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", low)
    at = [(i, label) for phrase, label in BASE for p in [phrase.split()] for i in range(len(words)) if words[i : i + len(p)] == p]
    places = [i for i, _ in at]
    return len(words), len(at), min(places, default=None), max(places, default=None), ",".join(sorted({k for _, k in at}))


def test_base_columns_match_brute_force(spark, sf):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()] + [(6000 + i, t) for i, t in enumerate(ODD)] + [(6003, "Apache License"), (None, "cc by")]
    got = scan_licenses(spark.createDataFrame([(i, t, "x", 3) for i, t in rows], "doc_id long, text string, labels string, score int").repartition(3)).collect()
    assert len(got) == len(rows)
    want = {i: brute(t) for i, t in rows}
    for r in got:
        assert (r.n_words, r.n_base, r.first_word, r.last_word, r.base_labels) == want[r.doc_id]
        assert set(r.base_labels.split(",")) - {""} <= set(r.labels.split(","))
        assert 0 <= r.score <= 1 and (r.score > 0) == (r.labels != "")
    labels = {r.doc_id: r.labels for r in got}
    assert labels[6008] == "mit" and labels[6010] == "mpl" and labels[6002] == ""


def test_a_text_of_many_licenses_has_all_their_labels(spark):
    notices = " . ".join(sentence for _, sentence, _ in TEMPLATES)
    few = "mozilla public license x gnu lesser general public license x gnu affero general public license x eclipse public license x creative commons zero x bsd 3 clause"
    got = {r.doc_id: r for r in scan_licenses(spark.createDataFrame([(1, notices), (2, few), (3, "nothing")], "doc_id long, text string")).collect()}
    assert got[1].labels == ",".join(sorted({label for label, _, _ in TEMPLATES})) and round(got[1].score, 6) == 1
    assert got[2].labels == "agpl,bsd,cc0,epl,lgpl,mpl" and got[3].labels == ""


def test_key_phrases_stand_whole(spark):
    rows = [(1, "software for one purpose with a small fee"), (2, "zzz for any purpose with or without fee"), (3, "for any purpose with or without fee"), (4, "software for any purpose with or without"), (5, "terms of a gnu general public licence")]
    got = {r.doc_id: (r.labels, r.score > 0) for r in scan_licenses(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {1: ("", False), 2: ("isc", True), 3: ("isc", True), 4: ("", False), 5: ("", False)}


def test_empty_table(spark):
    assert scan_licenses(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_no_python_in_the_plan(spark):
    plan = scan_licenses(spark.createDataFrame([(1, "mit license")], "doc_id long, text string"))._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan
