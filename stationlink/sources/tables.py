"""Given tables, station feeds and sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

NODE = T.StructType([
    T.StructField("node_id", T.LongType()), T.StructField("lat", T.DoubleType()), T.StructField("lon", T.DoubleType()),
    T.StructField("area_id", T.LongType()), T.StructField("group_id", T.LongType()), T.StructField("labels", T.MapType(T.StringType(), T.StringType())),
])
FEED = "node_id long, area_id long, group_id long, label string, lat double, lon double, broken string"


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_feed(spark: SparkSession, path: str, kind: str = "csv") -> DataFrame:
    """A station feed with a fixed schema; rows that do not fit keep their text in ``broken``."""
    reader = spark.read.schema(FEED).option("columnNameOfCorruptRecord", "broken").option("mode", "PERMISSIVE")
    return reader.option("header", True).csv(path) if kind == "csv" else reader.json(path)


def write_cells(idents: DataFrame, path: str, degrees: float = 1.0) -> None:
    """Parquet partitioned by coarse cell, so that reads of an area skip other files."""
    cell = F.concat_ws("_", F.floor(F.col("lat") / degrees), F.floor(F.col("lon") / degrees))
    idents.withColumn("cell", cell).repartition("cell").write.partitionBy("cell").mode("overwrite").parquet(path)


def write_bucketed(pairs: DataFrame, table: str, buckets: int = 64) -> None:
    """A table bucketed by pair_id: repeats that join on it need no further shuffle."""
    pairs.write.bucketBy(buckets, "pair_id").sortBy("pair_id").mode("overwrite").format("parquet").saveAsTable(table)
