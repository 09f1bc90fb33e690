"""The pipeline: stages in order, each on all that its predecessor kept, and what comes out at the end."""

import corpus_pipeline
from pyspark.sql import functions as F
from test_dedup import exact_brute, near_brute

from levelwave.llm import quality, toxicity
from levelwave.llm.shared import DOCUMENT_COLUMNS


def test_stages_decide_as_their_operators_and_brute_force(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "quality", "exact dedup", "near dedup", "packing"]
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    labels = spark.read.parquet(f"{small}/labels.parquet")
    want = {r["doc_id"] for r in toxicity.toxicity(docs, labels).where("score < 0.7").collect()}
    frame = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = frame
        frame = stage(spark, frame, small)
        assert frame.columns == DOCUMENT_COLUMNS
        frame = spark.createDataFrame(frame.collect(), docs.schema)
        if name == "quality":
            want = {r["doc_id"] for r in quality.judged(before).where("kept").collect()}
        elif name == "exact dedup":
            want = {i for i, v in exact_brute([(i, texts[i]) for i in want]).items() if v[2]}
        elif name == "near dedup":
            want = {i for i, (_, c) in near_brute([(i, texts[i]) for i in want]).items() if i == c}
        assert {r["doc_id"] for r in frame.collect()} == want, name
    pieces = corpus_pipeline.run(spark, small)
    assert {r["doc_id"] for r in pieces.select("doc_id").distinct().collect()} == want


def test_empty_and_odd_tables(spark, tmp_path, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    odd = docs.limit(30).unionByName(docs.limit(2)).withColumn("lang", F.when(F.col("doc_id") % 2 == 0, F.col("lang"))).withColumn("kept", F.lit(True))
    odd = odd.unionByName(odd.limit(2).withColumn("doc_id", F.lit(None).cast("long"))).unionByName(odd.limit(1).withColumn("text", F.lit(None).cast("string")))
    for name, frame in (("odd", odd), ("empty", odd.limit(0))):
        frame.write.parquet(f"{tmp_path}/{name}/documents.parquet")
        spark.read.parquet(f"{small}/labels.parquet").write.parquet(f"{tmp_path}/{name}/labels.parquet")
        out = corpus_pipeline.run(spark, f"{tmp_path}/{name}")
        assert out.isEmpty() == (name == "empty")
