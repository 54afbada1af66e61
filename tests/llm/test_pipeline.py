import corpus_pipeline
from stationlink.llm import decontaminate, near_dedup, quality

SMALL = "/root/testdata/sf0.001"


def test_stages_take_effect_and_keep_columns(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    columns = docs.columns
    assert [n for n, _ in corpus_pipeline.STAGES][0] == "quality classifier" and len(corpus_pipeline.STAGES) == 5
    model = quality.fit(docs, spark.read.parquet(f"{SMALL}/labels.parquet"))
    benchmark = spark.read.parquet(f"{SMALL}/benchmark.parquet")
    kept = None
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES[:3]):
        before = {r.doc_id for r in docs.select("doc_id").collect()}
        if k == 0:
            kept = {r.doc_id for r in quality.score(docs, model).where("accepted").collect()}
        elif k == 1:
            kept = {r.doc_id for r in near_dedup.near_duplicates(docs).where("kept").collect()}
        else:
            kept = {r.doc_id for r in decontaminate.find_contamination(docs, benchmark).where("size(items) = 0").collect()}
        docs = stage(spark, docs, SMALL)
        assert docs.columns == columns and {r.doc_id for r in docs.select("doc_id").collect()} == kept <= before
    mixed = corpus_pipeline.mix_sources(spark, docs, SMALL)
    assert mixed.columns == columns and {r.doc_id for r in mixed.collect()} <= kept and mixed.groupBy("doc_id").count().agg({"count": "max"}).first()[0] <= 3
    last = corpus_pipeline.shard(spark, mixed, SMALL)
    assert last.count() == mixed.count()


def test_empty_documents(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, SMALL)
    assert docs.count() == 0


def test_stages_keep_rows_of_null_and_repeated_ids_and_clashing_columns(spark):
    from pyspark.sql import functions as F

    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    ids = F.when(F.col("doc_id") % 10 == 0, F.lit(None)).when(F.col("doc_id") % 10 == 1, 1).otherwise(F.col("doc_id"))
    clash = {c: F.col("doc_id") for c in ("key", "copies", "__copy", "__f", "__s", "row", "size", "shard", "node", "text_key", "__size", "p", "lo", "some")}
    docs = docs.withColumns({"was": F.col("doc_id"), **clash}).withColumn("doc_id", ids)
    columns, kept = docs.columns, docs
    plain = spark.read.parquet(f"{SMALL}/documents.parquet")
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES[:4]):
        kept, plain = stage(spark, kept, SMALL), stage(spark, plain, SMALL)
        assert kept.columns == columns
        got = [r.was for r in kept.select("was").collect()]
        if k == 1:  # which one of a group stays depends on the ids; their number does not
            assert len(got) == len(set(got)) == plain.count()
            plain = spark.read.parquet(f"{SMALL}/documents.parquet").join(kept.select(F.col("was").alias("doc_id")), "doc_id", "left_semi")
        elif k < 3:
            assert sorted(got) == sorted(r.doc_id for r in plain.select("doc_id").collect())
        else:
            assert max(got.count(x) for x in set(got)) <= 3
    assert corpus_pipeline.shard(spark, kept, SMALL).count() == kept.count()
