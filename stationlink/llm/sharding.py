"""Shards of near equal bytes from sampled splitters.

Keys are (hash of the text, id), so equal texts are neighbours and a group of copies can still be divided. A sample of
keys, each as likely as its size, gives quantiles that cut the keys into many more ranges than shards; ranges that turn
out overfull are cut again from a sample of their own. Then each range's rows are ordered and summed by themselves, and
the sums of whole ranges (a bounded number, on the driver) carry them on to places in the order of all keys. A shard is
a run of this order whose bytes are its share of all bytes, to within one row at either end.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from stationlink.plans.workspace import materialize

#: Most sampled keys in one round, and ranges for each shard.
SAMPLE, RANGES_PER_SHARD = 20_000, 16
#: A range of more than this many times its share of bytes is cut again; rounds of it.
OVERFULL, ROUNDS = 2.0, 4


def text_size(text: Column) -> Column:
    """UTF-8 bytes plus one; one for null."""
    return (F.coalesce(F.octet_length(text), F.lit(0)) + 1).cast("long")


def _keyed(docs: DataFrame, text: Column) -> DataFrame:
    return docs.withColumn("__h", F.xxhash64(F.coalesce(text, F.lit("")))).withColumn("__id", F.coalesce(F.col("__doc"), F.lit(-(1 << 63))))


def range_of(h: np.ndarray, i: np.ndarray, cuts: list[tuple[int, int]]) -> np.ndarray:
    """Number of splitters at or below each key (h, i)."""
    if not cuts:
        return np.zeros(len(h), np.int32)
    high, low = np.array([c[0] for c in cuts], np.int64), np.array([c[1] for c in cuts], np.int64)
    a, b = np.searchsorted(high, h, "left"), np.searchsorted(high, h, "right")
    for k in np.flatnonzero(a < b):
        a[k] += np.searchsorted(low[a[k] : b[k]], i[k], "right")
    return a.astype(np.int32)


def _ranged(cuts: list[tuple[int, int]]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            got = range_of(batch.column("__h").to_numpy(), batch.column("__id").to_numpy(), cuts)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(got)], [*batch.schema.names, "__range"])

    return run


def _sampled(keys: DataFrame, total: int, want: int) -> list[tuple[int, int]]:
    """About ``want`` keys, each chosen with probability in proportion to its size (at most once)."""
    chance = F.least(F.lit(1.0), F.col("size") * (want / max(total, 1)))
    u = F.pmod(F.xxhash64("__h", "__id", F.lit(5)), F.lit(1 << 40)) / float(1 << 40)
    return sorted({(r["__h"], r["__id"]) for r in keys.where(u < chance).select("__h", "__id").collect()})


def splitters(keys: DataFrame, shards: int, sample: int = SAMPLE) -> tuple[list[tuple[int, int]], DataFrame]:
    """(splitters, keys with __range) for (__h, __id, size) rows."""
    from pyspark.sql.types import IntegerType, StructField, StructType

    total, rows = keys.agg(F.coalesce(F.sum("size"), F.lit(0)), F.count("*")).first()
    want = shards * RANGES_PER_SHARD
    keys_out = StructType([*keys.schema.fields, StructField("__range", IntegerType())])
    if not rows:
        return [], keys.mapInArrow(_ranged([]), keys_out)
    drawn = _sampled(keys, total, sample)
    cuts = sorted({drawn[len(drawn) * k // want] for k in range(1, want)}) if drawn else []
    for turn in range(ROUNDS):
        ranged = keys.mapInArrow(_ranged(cuts), keys_out)
        full = ranged.groupBy("__range").agg(F.sum("size").alias("s"), F.count("*").alias("n")).where((F.col("s") > total / want * OVERFULL) & (F.col("n") > 1))
        over = {r["__range"]: r["s"] for r in full.collect()}
        if not over or turn == ROUNDS - 1:
            return cuts, ranged
        again = ranged.where(F.col("__range").isin(list(over)))
        more = _sampled(again, sum(over.values()), sample)
        at = range_of(np.array([m[0] for m in more], np.int64), np.array([m[1] for m in more], np.int64), cuts)
        added: set[tuple[int, int]] = set()
        for r, s in over.items():
            own = [m for m, k in zip(more, at) if k == r]
            parts = int(np.ceil(s / (total / want)))
            added |= {own[len(own) * k // parts] for k in range(1, parts)} if own else set()
        if not added - set(cuts):
            return cuts, ranged
        cuts = sorted({*cuts, *added})
    return cuts, ranged


def shard_by_bytes(docs: DataFrame, shards: int = 16, sample: int = SAMPLE) -> DataFrame:
    """(doc_id, size, text_crc32, shard, slot) for every row of ``docs`` (doc_id, text).

    Shards hold near equal bytes: any two differ by less than twice the largest row. slot counts the rows of a shard from
    0 in key order. A null text is empty; null ids come first among equal texts; rows that repeat a key are
    interchangeable. With fewer rows than shards some shards are empty. Other columns are ignored. A very long text is one
    row, never divided, so its shard may exceed the others by it; copies of one text are neighbours in the order, and a
    group of them that crosses the edge of a shard is divided there, as the bytes ask.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("__doc"), F.col("text").alias("__text"))
    keys = _keyed(rows, F.col("__text")).select(
        "__h", "__id", F.col("__doc").alias("doc_id"), text_size(F.col("__text")).alias("size"),
        F.crc32(F.coalesce("__text", F.lit("")).cast("binary")).alias("text_crc32"),
    )
    keys = materialize(keys, "shard-keys")  # texts are read and hashed once
    _, ranged = splitters(keys, shards, sample)
    sums = {r["__range"]: (r["s"], r["n"]) for r in ranged.groupBy("__range").agg(F.sum("size").alias("s"), F.count("*").alias("n")).collect()}
    return _placed(ranged, sums, shards)


def _placed(ranged: DataFrame, sums: dict[int, tuple[int, int]], shards: int) -> DataFrame:
    spark = ranged.sparkSession
    before, at, n = [], 0, 0
    for r in sorted(sums):
        before.append((r, at, n))
        at, n = at + sums[r][0], n + sums[r][1]
    total = max(at, 1)
    offsets = F.broadcast(spark.createDataFrame(before, "__range int, __bytes long, __rows long"))
    w = Window.partitionBy("__range").orderBy("__h", "__id", "size", "text_crc32")
    placed = ranged.withColumn("__sum", F.sum("size").over(w.rowsBetween(Window.unboundedPreceding, 0)) - F.col("size")).withColumn("__row", F.row_number().over(w) - 1)
    # The shard of a row is that of its middle byte.
    shard = F.expr(f"cast(least({shards - 1}, ((__bytes + __sum) * 2 + size) * {shards} div {2 * total}) as int)")
    placed = placed.join(offsets, "__range").select("doc_id", "size", "text_crc32", shard.alias("shard"), (F.col("__rows") + F.col("__row")).alias("__place"))
    first = placed.groupBy("shard").agg(F.min("__place").alias("__first"))
    return placed.join(F.broadcast(first), "shard").select("doc_id", "size", "text_crc32", "shard", (F.col("__place") - F.col("__first")).alias("slot"))
