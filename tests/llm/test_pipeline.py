import corpus_pipeline


def test_stages_keep_columns_and_pack_everything(spark):
    folder = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    columns, before = docs.columns, docs.count()
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, folder).cache()
        assert docs.columns == columns, name
        if name != "mixing":
            assert docs.count() <= before
            before = docs.count()
    whole = corpus_pipeline.run(spark, folder).collect()
    assert sum(r.piece == 0 for r in whole) == docs.count()


def test_stages_on_odd_rows(spark, odd, none):
    for df in (odd, none):
        docs = df
        for _, stage in corpus_pipeline.STAGES[:-1]:
            docs = stage(spark, docs, "/root/testdata/sf0.001").cache()
            assert docs.columns == df.columns
        assert corpus_pipeline.pack(spark, docs, "").count() >= docs.count()
