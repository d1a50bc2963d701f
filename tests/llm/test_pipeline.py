import corpus_pipeline as pipeline
from veilmatch.llm.secrets import spans_of


def test_stages_take_effect_and_keep_columns(spark, sf, tmp_path):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns = docs.columns
    extra = spark.createDataFrame([(9000, "12345 !!", "en", "src1", 8), (9001, docs.first().text, "fr", "src0", 5)], docs.schema)
    docs = docs.unionByName(extra)
    seen = {}
    for name, stage in pipeline.STAGES:
        stage(spark, docs, sf).write.parquet(str(tmp_path / name))
        docs = spark.read.parquet(str(tmp_path / name))
        seen[name] = docs.collect()
        if name != "packing":
            assert docs.columns == columns
    ids = {n: [r.doc_id for r in rows] for n, rows in seen.items()}
    assert 9000 not in ids["language"] and len(ids["language"]) >= 195
    assert 9001 in ids["language"] and 9001 not in ids["near_duplicates"]
    assert len(set(ids["near_duplicates"])) == len(ids["near_duplicates"])
    assert set(ids["decontamination"]) <= set(ids["near_duplicates"]) and ids["secrets"] and set(ids["secrets"]) == set(ids["decontamination"])
    assert not any(spans_of(r.text)[0] for r in seen["secrets"])
    assert {r.doc_id for r in seen["packing"]} == set(ids["secrets"])


def test_decontamination_sends_short_batches_and_heaps_are_given_back(spark, sf, monkeypatch):
    from veilmatch.llm import common

    docs, seen = spark.read.parquet(f"{sf}/documents.parquet").limit(20), []

    def noted(docs, benchmark):
        seen.append(int(spark.conf.get(common.BATCH)))
        return docs.select("doc_id").limit(3)

    monkeypatch.setattr(pipeline.contamination, "contaminated", noted)
    before = spark.conf.get(common.BATCH)
    assert pipeline.drop_contaminated(spark, docs, sf).count() == 17
    assert seen == [1000] and spark.conf.get(common.BATCH) == before

    beans = spark.sparkContext._jvm.java.lang.management.ManagementFactory.getGarbageCollectorMXBeans
    count = lambda: sum(b.getCollectionCount() for b in beans())
    runs = count()
    common.heaps_back(spark)
    assert count() > runs
