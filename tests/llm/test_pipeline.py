"""The pipeline's stages against brute force over the smallest tables, and on odd rows."""

import corpus_pipeline
from test_operators import ODD, brute_components, brute_contamination, brute_fingerprint, clash


def test_stages(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet")
    items = [(str(r["item_id"]), r["text"]) for r in spark.read.parquet(f"{data}/benchmark.parquet").collect()]
    stages = dict(corpus_pipeline.STAGES)
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    roots = brute_components(sorted(texts), {i: brute_fingerprint(t) for i, t in texts.items()})
    kept = stages["near_dedup"](spark, docs, data)
    assert kept.columns == docs.columns and sorted(r["doc_id"] for r in kept.select("doc_id").collect()) == sorted(set(roots.values()))
    clean = {r["doc_id"] for r in stages["decontamination"](spark, docs, data).select("doc_id").collect()}
    want = set()
    for i, t in texts.items():
        n, hit, _ = brute_contamination(t, items)
        if not (hit and 20 * hit >= n):
            want.add(i)
    assert clean == want
    mild = stages["toxicity"](spark, docs, data)
    labels = spark.read.parquet(f"{data}/labels.parquet")
    assert mild.join(labels.filter("toxic = 1"), "doc_id").count() <= 1
    assert mild.join(labels.filter("toxic = 0"), "doc_id").count() >= 0.97 * labels.filter("toxic = 0").count()


def test_run(spark, data):
    out = corpus_pipeline.run(spark, data)
    docs = spark.read.parquet(f"{data}/documents.parquet")
    assert out.columns == [*docs.columns, "slot", "shard"]
    assert out.groupBy("doc_id").count().filter("count > 2").count() == 0 and out.count() > 100


def test_odd_rows(spark, data):
    docs = spark.createDataFrame(ODD, "doc_id long, text string, source string").withColumns(clash())
    for name, stage in corpus_pipeline.STAGES[:-1]:
        after = stage(spark, docs, data)
        assert after.columns == docs.columns, name
        assert stage(spark, docs.limit(0), data).count() == 0
    dedup = dict(corpus_pipeline.STAGES)["near_dedup"](spark, docs, data)
    assert sorted(r["doc_id"] or 0 for r in dedup.collect()) == [0, 1, 3, 5, 6]
