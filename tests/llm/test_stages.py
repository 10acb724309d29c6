"""The pipeline: each stage reads what the one before it wrote."""

import corpus_pipeline

LARGER = "/root/testdata/sf0.01"


def test_pipeline_stages_read_what_the_one_before_wrote(spark, monkeypatch):
    seen = []

    def stage(spark, docs, sf_dir):
        seen.append(docs.inputFiles()[0])
        return docs.select("doc_id").where("doc_id % 2 = 0")

    monkeypatch.setattr(corpus_pipeline, "STAGES", [("a", stage), ("b", stage)])
    out = corpus_pipeline.run(spark, LARGER)
    assert seen[0].endswith("documents.parquet") and "/pipeline-" in seen[1] and "/pipeline-" in out.inputFiles()[0]
    assert out.count() == spark.read.parquet(f"{LARGER}/documents.parquet").where("doc_id % 2 = 0").count()
