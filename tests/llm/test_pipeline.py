import corpus_pipeline
from quadpost.llm import decontamination, simhash
from tests.conftest import SMALL


def test_stages(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").cache()
    seen = [docs.count()]
    now = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before, now = now, stage(spark, now, SMALL).cache()
        seen.append(now.count())
        assert now.columns == list(corpus_pipeline.COLUMNS) and seen[-1] <= seen[-2]
        if name == "language_id":
            assert seen[-1] > 0.95 * seen[-2]
        if name == "near_dedup":
            found = simhash.wide_classes(before).collect()
            assert {r["doc_id"] for r in now.collect()} == {r["component_id"] for r in found}
    left = decontamination.contamination(now, spark.read.parquet(f"{SMALL}/benchmark.parquet"))
    assert left.where("contaminated").count() == 0
    packed = corpus_pipeline.STAGES[-1][1](spark, now, SMALL)
    assert packed.select("doc_id").distinct().count() == seen[-1]


def test_empty_documents(spark):
    now = spark.read.parquet(f"{SMALL}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        now = stage(spark, now, SMALL)
    assert now.count() == 0
