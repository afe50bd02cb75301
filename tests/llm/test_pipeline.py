import corpus_pipeline as pipeline
from vecspark.llm.tables import settle


def test_stages_in_order_on_planted_documents(spark, tmp_path, text, make_docs):
    good = [text(i, 120) for i in range(60)]
    leak = text(900, 40)
    texts = [*good, good[0], good[1] + " more", text(70, 60) + " " + leak + " " + text(71, 60), "too short", text(72, 100) + " password=abcdef123456", "w " * 300, None]
    docs = make_docs(texts)
    docs.write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(0, leak)], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    spark.createDataFrame([(i, 1, 0) for i in range(40)] + [(63, 0, 0), (65, 0, 0)], "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    assert [n for n, _ in pipeline.STAGES] == ["quality rules", "MinHash near-dedup", "benchmark decontamination", "secret scans", "mixing sources to target weights"]
    kept = [set(range(60)) | {60, 61, 62, 64}, set(range(60)) | {62, 64}, set(range(60)) | {64}, set(range(60)) | {64}]
    now = spark.read.parquet(str(tmp_path / "documents.parquet"))
    columns = now.columns
    for (_, stage), want in zip(pipeline.STAGES, kept):
        now = settle(stage(spark, now, str(tmp_path)), "stage")
        assert now.columns == columns and {r["doc_id"] for r in now.collect()} == want
    assert now.where("doc_id = 64").first()["text"].endswith("[SECRET]")
    mixed = pipeline.STAGES[-1][1](spark, now, str(tmp_path))
    assert {r["doc_id"] for r in mixed.collect()} <= kept[-1] and "copy_no" in mixed.columns
    assert pipeline.run(spark, str(tmp_path)).count() == mixed.count()


def test_empty_documents(spark, tmp_path, make_docs):
    none = make_docs([])
    none.write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    assert pipeline.run(spark, str(tmp_path)).count() == 0
