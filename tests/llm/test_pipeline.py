"""The pipeline's stages on a small table with planted cases."""

import corpus_pipeline
from pyspark.sql import functions as F

DATA = "/root/testdata/sf0.01"


def test_stages(spark):
    docs = spark.read.parquet(f"{DATA}/documents.parquet").withColumn("score", F.lit(1)).withColumn("t", F.lit("x"))
    base = docs.filter("doc_id = 3").first()
    words = [f"{a}{b}" for a in ("than", "oner", "shed", "tion", "ered") for b in ("ing", "the", "and", "ble", "wh", "nd", "ou", "re", "st", "ti", "ly", "es", "ha")]
    passage = " ".join(words[:60])
    clean = docs.filter("doc_id in (11, 12, 17)").collect()
    extra = [(90001, base.text), (90002, base.text.replace(" ", "  ")), *((90010 + i, r.text + "\n" + passage + ".") for i, r in enumerate(clean)), (90020, None), (90021, "")]
    plus = spark.createDataFrame([(i, t, "en", "src0", len(t or ""), 1, "x") for i, t in extra], docs.schema)
    docs = docs.unionByName(plus)
    columns = docs.columns
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, DATA)
        assert out.columns == columns, name
        out.write.mode("overwrite").parquet(f"{spark.conf.get('spark.checkpoint.dir')}/{name.replace(' ', '_')}")
        docs = spark.read.parquet(f"{spark.conf.get('spark.checkpoint.dir')}/{name.replace(' ', '_')}")
        if name == "n-gram Jaccard join":
            ids = {r.doc_id for r in docs.select("doc_id").collect()}
            assert not ids & {90001, 90002, 90020, 90021}
    texts = {r.doc_id: r.text for r in docs.collect()}
    assert sum(passage in (t or "") for t in texts.values()) == 0
    assert len(texts) > 500
    packed = corpus_pipeline.STAGES[-1][1](spark, docs, DATA)
    assert {r.doc_id for r in packed.select("doc_id").distinct().collect()} == set(texts)


def test_run(spark):
    assert corpus_pipeline.run(spark, "/root/testdata/sf0.001").count() > 0
