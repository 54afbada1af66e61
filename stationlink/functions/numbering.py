"""Uniform numbers from hashes, and row numbers without one big sort."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def uniform(salt: str, *keys) -> Column:
    """Number in [0, 1) from the first 8 hex digits of md5('salt:key:...')."""
    parts = [F.lit(salt), *[k.cast("string") for k in keys]]
    return F.conv(F.substring(F.md5(F.concat_ws(":", *parts)), 1, 8), 16, 10).cast("long") / 4294967296.0


def numbered(df: DataFrame, key: str, order: list[str], name: str, rows_per_range: int = 1 << 14) -> DataFrame:
    """``df`` with ``name`` = 1, 2, ... by (key, order); ``key`` is a long.

    Rows are numbered inside ranges of the key; only the counts of ranges pass through one task.
    """
    ranged = df.withColumn("__range", F.floor(F.col(key) / rows_per_range))
    counts = ranged.groupBy("__range").agg(F.count("*").alias("__n"))
    before = counts.select("__range", (F.sum("__n").over(Window.orderBy("__range")) - F.col("__n")).alias("__before"))
    w = Window.partitionBy("__range").orderBy(key, *order)
    return ranged.withColumn("__row", F.row_number().over(w)).join(before, "__range").withColumn(name, (F.col("__before") + F.col("__row")).cast("long")).drop("__range", "__row", "__before")
