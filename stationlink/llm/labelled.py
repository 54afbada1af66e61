"""A bounded sample of labelled documents for fitting classifiers."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Most labelled rows any classifier here is fitted on.
MAX_ROWS = 20_000


def held_out(doc_id) -> F.Column:
    """Whether crc32 of the id, written as text, is divisible by 5; a null id is never held out."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(False))


def labelled_sample(docs: DataFrame, labels: DataFrame, target: F.Column, max_rows: int = MAX_ROWS) -> DataFrame:
    """(doc_id, text, y) of at most ``max_rows`` labelled rows outside the held-out fifth, chosen by a hash of the id.

    Ids labelled more than once have their largest label. Rows with a null id, label or text are left out. Only the ids
    of the sample, whose number is bounded, are broadcast; texts are not shuffled.
    """
    rows = labels.select("doc_id", target.alias("y")).where("doc_id is not null and y is not null").where(~held_out(F.col("doc_id")))
    rows = rows.groupBy("doc_id").agg(F.max("y").alias("y")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_rows)
    return docs.select("doc_id", "text").where("text is not null").join(F.broadcast(rows), "doc_id")
