"""The pipeline's stages on a small corpus."""

from __future__ import annotations


def test_pipeline(spark, sf):
    import corpus_pipeline
    from curator.functions.workspace import stash

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns, n = docs.columns, docs.count()
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        docs = stash(stage(spark, docs, sf), "stage")
        assert docs.count() <= n
        n = docs.count()
        if k < len(corpus_pipeline.STAGES) - 1:
            assert docs.columns == columns
    assert n > 0 and docs.select("doc_id").distinct().count() == n
    assert corpus_pipeline.run(spark, sf).count() == n


def test_repeated_rows_leave_one(spark, sf):
    import corpus_pipeline

    text = "one two three four five six seven eight nine ten"
    rows = [(1, text), (1, text), (1, text), (2, text), (3, "something else is written here"), (3, "something else is written here")]
    kept = corpus_pipeline.keep_one_of_each_group(spark, spark.createDataFrame(rows, "doc_id long, text string"), sf).collect()
    assert sorted(r["doc_id"] for r in kept) == [1, 3]
