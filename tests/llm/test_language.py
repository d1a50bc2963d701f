from pyspark.sql import functions as F

from veilmatch.llm.language import evidence, fit, host_of, identify, suffix_of, text_scores


def test_held_out_accuracy_and_rejects(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    train, test = docs.where("doc_id % 2 = 0"), docs.where("doc_id % 2 = 1")
    model = fit(train, "doc_id", "text", "lang")
    scored = text_scores(test, "text", model)
    rows = [(r.lang, model[0][max(range(len(model[0])), key=lambda i: r.text_scores[i])]) for r in scored.collect()]
    assert sum(a == b for a, b in rows) / len(rows) >= 0.97
    got = identify(docs.withColumn("predicted", F.lit(5)))
    assert got.count() == docs.count()
    assert got.where("not accepted and length(text) > 20").count() == 0
    assert got.where("predicted <> lang").count() <= 0.03 * docs.count()


def test_odd_rows(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text", "lang", "source")
    odd = spark.createDataFrame(
        [(9000, None, "en", "src0"), (9001, "", None, None), (9002, "123 456 !!", "xx", "src1"), (None, "the of and that was", "en", None), (9003, "the " * 100_000, None, "src0"), (9003, "the " * 100_000, None, "src0"), (9004, "qzxj vkqx wxzq jqkv zzqx xkjq " * 5, "zz", "src0")],
        docs.schema,
    )
    got = {r.doc_id: r for r in identify(docs.union(odd)).where("doc_id is null or doc_id >= 9000").collect()}
    assert not any(got[i].accepted for i in (9000, 9001, 9002, 9004))
    assert got[9003].predicted == "en" and got[9003].accepted and got[None].predicted == "en"
    assert identify(docs.union(odd).where("doc_id = 9003")).count() == 2


def test_empty_and_unlabelled(spark):
    empty = spark.createDataFrame([], "doc_id long, text string, lang string, source string")
    assert identify(empty).count() == 0
    bare = spark.createDataFrame([(1, "text", None, None)], empty.schema)
    assert [r.accepted for r in identify(bare).collect()] == [False]


def test_short_text_follows_host_and_markup(spark):
    rows = [(i, t, l, f"http://{h}/p{i}") for i, (t, l, h) in enumerate([("the cat and the dog were here", "en", "a.example.org")] * 60 + [("der hund und die katze waren hier", "de", "b.example.de")] * 60)]
    short = [(500, "in", "", "http://b.example.de/x"), (501, "in", "en-US", "http://a.example.org/y"), (502, "in", "", "http://new.example.de/")]
    docs = spark.createDataFrame(rows + short, "doc_id long, text string, lang string, source string")
    trained = docs.withColumn("label", F.when(F.col("doc_id") < 500, F.col("lang")))
    got = {r.doc_id: r.predicted for r in identify(trained, label="label").where("doc_id >= 500").collect()}
    assert got == {500: "de", 501: "en", 502: got[502]}
    model = fit(trained, "doc_id", "text", "label")
    priors, odds = evidence(text_scores(trained, "text", model), model[0], "lang", "source")
    held = {r.host: r.prior for r in priors.collect()}
    assert all(abs(sum(p) - 1) < 1e-9 for p in held.values()) and held["b.example.de"][0] > 0.9 and set(odds) == {"", "de", "en"}


def test_pages_as_input(spark, sf):
    pages = spark.read.parquet(f"{sf}/pages.parquet").select("page_id", "html", F.regexp_extract("html", r'<html[^>]*\slang="([^"]+)"', 1).alias("markup"), "url")
    got = identify(pages, "page_id", "html", "markup", "markup", "url").where("accepted")
    assert got.where("predicted = markup").count() >= 0.9 * pages.count()
    assert [r[0] for r in spark.range(1).select(suffix_of(host_of(F.lit("https://u@m.x.example.NET:80/en?q=1")))).collect()] == ["net"]


def test_a_language_of_one_document_is_not_confirmed_by_it(spark):
    rows = [(i, t, l, "a") for i, (t, l) in enumerate([("the cat and the dog were here", "en")] * 20 + [("der hund und die katze", "de")] * 20)]
    rows += [(90, "qzxj vkqx wxzq jqkv zzqx " * 5, "zz", "a"), (91, "kissa ja koira olivat siella " * 5, "fi", "a"), (92, "kissa ja koira ovat siella " * 5, "fi", "a")]
    got = {r.doc_id: (r.predicted, r.accepted) for r in identify(spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")).where("doc_id >= 90").collect()}
    assert got[90] == ("zz", False) and got[91] == got[92] == ("fi", True)
