from __future__ import annotations

import corpus_pipeline
from utilmine.llm import decontamination, near_dedup, quality_classifier
from utilmine.llm.shared import documents


def test_stages(spark, sf):
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert len(names) == 5 and len(set(names)) == 5
    docs = documents(spark, sf)
    columns = docs.columns
    kept = {r["doc_id"] for r in quality_classifier.classify(docs, spark.read.parquet(f"{sf}/labels.parquet")).where("kept").collect()}
    one = corpus_pipeline.quality(spark, docs, sf)
    assert one.columns == columns and {r["doc_id"] for r in one.collect()} == kept
    two = corpus_pipeline.near_copies(spark, one, sf)
    classes = near_dedup.near_duplicates(one).collect()
    assert two.columns == columns and {r["doc_id"] for r in two.collect()} == {r["class_id"] for r in classes}
    three = corpus_pipeline.decontaminated(spark, two, sf)
    hit = {r["doc_id"] for r in decontamination.contaminated(two, spark.read.parquet(f"{sf}/benchmark.parquet")).collect()}
    assert three.columns == columns and {r["doc_id"] for r in three.collect()} == {r["doc_id"] for r in two.collect()} - hit
    four = corpus_pipeline.mixed(spark, three, sf)
    assert four.columns == columns and {r["doc_id"] for r in four.collect()} <= {r["doc_id"] for r in three.collect()}
    last = corpus_pipeline.run(spark, sf)
    assert last.count() == four.count()
    assert sorted(r["slot"] for r in last.where("shard = 0").collect()) == list(range(last.where("shard = 0").count()))
