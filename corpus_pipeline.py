"""The corpus pipeline: filter by quality, keep one of near duplicates, decontaminate, mix sources, shard."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stationlink.llm import decontaminate, mixing, near_dedup, quality, sharding
from stationlink.plans.shipping import ship
from stationlink.plans.workspace import materialize


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def accept_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the ordinal regression accepts; it is fitted on labelled rows of the documents table."""
    ship(spark)
    model = quality.fit(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))
    return quality.accepted(docs, model)


def one_of_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document of least id of each group of near duplicates."""
    ship(spark)
    return near_dedup.drop_near_duplicates(docs)


def without_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no window of a benchmark item."""
    ship(spark)
    return decontaminate.drop_contaminated(docs, _table(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them: sources weigh 1, 2, 3, repeating, none above three times its size."""
    ship(spark)
    sized = docs.select(F.col("doc_id").alias("key"), "source", mixing.word_count(F.col("text")).alias("size"), F.array("source").alias("sources"))
    sizes = materialize(sized, "mix-sizes")
    rule = mixing.Mix(sizes, [(s, t) for s, _, t in mixing.source_targets(sizes)])
    found = rule.copies(docs, F.col("doc_id"), F.array("source"), mixing.has_words(F.col("text")))
    return found.where("copies > 0").select("row", F.explode(F.sequence(F.lit(1), F.col("copies")))).select("row.*")


def shard(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, size, text_crc32, shard and slot of every document of the mix, in 16 shards of near equal bytes."""
    ship(spark)
    return sharding.shard_by_bytes(docs, 16)


STAGES = [
    ("quality classifier", accept_quality),
    ("minhash near-dedup", one_of_near_duplicates),
    ("benchmark decontamination", without_benchmark),
    ("mixing to weights", mix_sources),
    ("sharding", shard),
]

#: The regression and the hashes can't be said in SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each written and read again."""
    docs = _table(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = materialize(docs, name.replace(" ", "-"))
    return docs
