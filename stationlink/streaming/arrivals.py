"""Arriving identifiers as streams: windows, watermark, duplicates, matches against a registry, running state.

Each function takes a stream (or a table) with event_id, ts, event_type, label, lat, lon and returns the transformed
frame; ``drain`` runs a stream to the end of its input into Parquet and reads the result back.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stationlink.functions import geo, naive, similarity, voting
from stationlink.plans.workspace import shared_folder


def as_stream(spark: SparkSession, rows: DataFrame, files: int = 2) -> DataFrame:
    """``rows`` written as files in order of time and read as a stream."""
    path = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    rows.repartitionByRange(files, "ts").sortWithinPartitions("ts").write.parquet(path)
    return spark.readStream.schema(rows.schema).parquet(path)


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    spark = stream.sparkSession
    path = f"{shared_folder(spark)}/sink-{uuid.uuid4().hex}"
    run = stream.writeStream.format("parquet").outputMode(mode).option("path", path).option("checkpointLocation", f"{path}-log").trigger(availableNow=True).start()
    run.awaitTermination()
    return spark.read.schema(stream.schema).parquet(path)


def drain_parts(parts: list[DataFrame], step: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """``step`` over a stream whose files come part by part, each part run to its end before the next one is there.

    The watermark is kept between the parts, so rows of a part that are older than it allows are left out.
    """
    spark = parts[0].sparkSession
    path = f"{shared_folder(spark)}/parts-{uuid.uuid4().hex}"
    for rows in parts:
        rows.write.mode("append").parquet(path)
        out = step(spark.readStream.schema(parts[0].schema).parquet(path))
        run = out.writeStream.format("parquet").outputMode("append").option("path", f"{path}-sink").option("checkpointLocation", f"{path}-log").trigger(availableNow=True).start()
        run.awaitTermination()
    return spark.read.schema(out.schema).parquet(f"{path}-sink")


def tumbling(stream: DataFrame, length: str = "1 hour", late: str = "0 seconds") -> DataFrame:
    out = stream.withWatermark("ts", late).groupBy(F.window("ts", length), "event_type").agg(F.count("*").alias("n"))
    return out.select(F.col("window.start").alias("start"), "event_type", "n")


def sliding(stream: DataFrame, length: str = "2 hours", step: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", "0 seconds").groupBy(F.window("ts", length, step)).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "n")


def sessions(stream: DataFrame, gap: str = "30 minutes") -> DataFrame:
    out = stream.withWatermark("ts", "0 seconds").groupBy(F.session_window("ts", gap), "node_id").agg(F.count("*").alias("n"))
    return out.select("node_id", F.col("session_window.start").alias("start"), "n")


def deduplicated(stream: DataFrame, within: str = "365 days") -> DataFrame:
    """The first announcement of each (node, type)."""
    return stream.withWatermark("ts", within).dropDuplicatesWithinWatermark(["node_id", "event_type"])


def matched(stream: DataFrame, registry: DataFrame, d_hat: float = 60.0, t: float = 0.5, radius_m: float = 1000.0) -> DataFrame:
    """Arrivals against a registry of identifiers: pairs within the radius with the soft vote of P and ED.

    The registry is dealt to cells, so the join is an equal join and neither side has to fit in memory.
    """
    known = registry.select(F.col("ident_id"), F.col("label").alias("r_label"), F.col("lat").alias("r_lat"), F.col("lon").alias("r_lon"))
    known = known.select("*", F.inline(geo.covering_cells(F.col("r_lat"), F.col("r_lon"), radius_m)))
    own = stream.withColumn("band", geo.band(F.col("lat"), radius_m))
    own = own.withColumn("cell", geo.cell(F.col("lon"), geo.band_cells(F.col("band"), radius_m)))
    near = own.join(known, ["band", "cell"]).withColumn("dist_m", geo.haversine_m(F.col("lat"), F.col("lon"), F.col("r_lat"), F.col("r_lon"))).where(F.col("dist_m") <= radius_m)
    score = voting.soft(naive.decay(F.col("dist_m"), d_hat), voting.rescale(similarity.edit("label", "r_label"), t))
    return near.withColumn("score", score).withColumn("predicted", voting.decide(score))


def interval_join(left: DataFrame, right: DataFrame, minutes: int = 10) -> DataFrame:
    """Pairs of an arrival and a later one of the same node within some minutes."""
    a = left.select(F.col("event_id").alias("a_id"), F.col("node_id").alias("a_node"), F.col("ts").alias("a_ts")).withWatermark("a_ts", f"{minutes} minutes")
    b = right.select(F.col("event_id").alias("b_id"), F.col("node_id").alias("b_node"), F.col("ts").alias("b_ts")).withWatermark("b_ts", f"{minutes} minutes")
    on = (F.col("a_node") == F.col("b_node")) & (F.col("b_ts") > F.col("a_ts")) & (F.col("b_ts") <= F.col("a_ts") + F.expr(f"interval {minutes} minutes"))
    return a.join(b, on).select("a_id", "b_id")


def running_centroids(stream: DataFrame) -> DataFrame:
    """Count and mean position of each node so far, one row for each node and batch (custom state)."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def update(key: tuple, parts, state: GroupState):
        n, lat, lon = state.get if state.exists else (0, 0.0, 0.0)
        for p in parts:
            n, lat, lon = n + len(p), lat + float(p["lat"].sum()), lon + float(p["lon"].sum())
        state.update((n, lat, lon))
        yield pd.DataFrame({"node_id": [key[0]], "n": [n], "lat": [lat / n], "lon": [lon / n]})

    return stream.select("node_id", "lat", "lon").groupBy("node_id").applyInPandasWithState(update, "node_id long, n long, lat double, lon double", "n long, lat double, lon double", "update", GroupStateTimeout.NoTimeout)


def last_state(stream: DataFrame) -> DataFrame:
    """``running_centroids`` run to the end; the row with the largest count of each node."""
    spark = stream.sparkSession
    path = f"{shared_folder(spark)}/state-{uuid.uuid4().hex}"
    write: Callable[[DataFrame, int], None] = lambda batch, k: batch.write.mode("append").parquet(path)
    out = running_centroids(stream)
    run = out.writeStream.outputMode("update").foreachBatch(write).option("checkpointLocation", f"{path}-log").trigger(availableNow=True).start()
    run.awaitTermination()
    got = spark.read.schema(out.schema).parquet(path)
    return got.groupBy("node_id").agg(F.max_by(F.struct("n", "lat", "lon"), "n").alias("x")).select("node_id", "x.*")
