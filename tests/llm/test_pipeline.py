"""The pipeline on a small table against brute-force versions of its stages."""

import corpus_pipeline
from orbitgraph.llm import decontam, quality
from test_operators import brute_lines, brute_near


def test_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["quality_rules", "line_dedup", "near_duplicates", "decontamination", "packing"]
    judged = {r.doc_id for r in quality.quality_rules(docs).where("quality.kept").collect()}
    one = corpus_pipeline.quality_stage(spark, docs, sf).persist()
    assert one.columns == docs.columns and {r.doc_id for r in one.collect()} == judged
    two = corpus_pipeline.line_stage(spark, one, sf).persist()
    want = brute_lines([(r.doc_id, r.text) for r in one.collect()])
    assert {r.doc_id: r.text for r in two.collect()} == want and all(r.n_chars == len(r.text) for r in two.collect())
    three = corpus_pipeline.near_stage(spark, two, sf).persist()
    near = brute_near(list(want.items()), corpus_pipeline.NEAR_PERCENT)
    assert {r.doc_id for r in three.collect()} == {d for d, (_, c) in near.items() if c == d}
    four = corpus_pipeline.decontamination_stage(spark, three, sf).persist()
    leaks = {r.doc_id for r in decontam.contamination(three, spark.read.parquet(f"{sf}/benchmark.parquet")).collect()}
    assert {r.doc_id for r in four.collect()} == {r.doc_id for r in three.collect()} - leaks and leaks
    five = corpus_pipeline.packing_stage(spark, four, sf)
    assert {r.doc_id for r in five.collect()} == {r.doc_id for r in four.collect()}


def test_run(spark, sf):
    assert corpus_pipeline.run(spark, sf).count() > 0
