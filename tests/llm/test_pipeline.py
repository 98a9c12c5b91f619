import corpus_pipeline
from pyspark.sql import functions as F

SF = "/root/testdata/sf0.001"


def test_stages_take_effect_in_order(spark, tmp_path):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns, sizes = docs.columns, [docs.count()]
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    for n, (name, stage) in enumerate(corpus_pipeline.STAGES):
        docs = stage(spark, docs, SF)
        docs.write.parquet(path := str(tmp_path / str(n)))
        docs = spark.read.parquet(path)
        sizes.append(docs.count())
        if n < 4:
            assert docs.columns == columns
        if name == "toxicity":
            assert docs.join(labels.where("toxic = 1"), "doc_id").count() <= 2
            assert docs.join(labels.where("toxic = 0"), "doc_id").count() >= 0.95 * labels.where("toxic = 0").count()
        if name == "exact dedup":
            assert docs.select(F.lower("text")).distinct().count() == sizes[-1]
    assert sizes[0] > sizes[1] > sizes[2] >= sizes[3] > sizes[4] == sizes[5]
    assert corpus_pipeline.run(spark, SF).count() == sizes[-1]
