from __future__ import annotations


def test_pipeline_on_a_small_corpus(spark, small, tmp_path):
    import corpus_pipeline
    from passage_engine.llm import decontaminate, ngram_join, secrets

    docs = spark.read.parquet(f"{small}/documents.parquet")
    columns, before = docs.columns, docs
    for name, stage in corpus_pipeline.STAGES:
        after = stage(spark, before, small)
        after.write.parquet(path := f"{tmp_path}/{name}")
        after = spark.read.parquet(path)
        if name != "mixing":
            assert after.columns == columns or sorted(after.columns) == sorted(columns)
        ids = lambda d: {r.doc_id for r in d.select("doc_id").collect()}
        if name == "ngram_jaccard_join":
            want = {r.doc_id for r in ngram_join.similarity_components(before).where("doc_id = component_id").collect()}
            assert ids(after) == want and after.count() == len(want)
        if name == "benchmark_decontamination":
            found = decontaminate.hits(before, decontaminate.load(spark.read.parquet(f"{small}/benchmark.parquet")))
            assert ids(after) == ids(before) - {r.doc_id for r in found.where("contaminated").collect()}
        if name == "secret_scan":
            assert ids(after) == ids(before)
            assert all(not secrets.base_spans(r.text) for r in after.where("text is not null").collect())
        before = after
    assert before.select("mix_copy").distinct().count() <= 3
