import corpus_pipeline


def test_stages_keep_rows_whole(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    before, cols = docs.count(), docs.columns
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = corpus_pipeline.Scratch(spark, "t").keep(stage(spark, docs, "/root/testdata/sf0.001"), name)
        now = docs.count()
        assert docs.columns == cols and 0 < now <= before
        before = now
    packed = corpus_pipeline.STAGES[-1][1](spark, docs, "/root/testdata/sf0.001")
    assert packed.select("doc_id").distinct().count() == before
