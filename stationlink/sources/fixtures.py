"""Station nodes derived from the given tables, the same rows in Spark and in SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stationlink.functions.geo import DEGREE_M
from stationlink.functions.numbering import uniform
from stationlink.sources.tables import load


def _placed(df: DataFrame, salt: str, g: str, k: str, town: str, lat0: float, lon0: float, box: float) -> DataFrame:
    """lat and lon: a site in its town's box, and the node around it at exponential distance (mean 25 m)."""
    base_lat, base_lon = lat0 + 0.2 * (F.col(town) % 40), lon0 + 0.25 * (F.floor(F.col(town) / 40) % 40)
    g, k = F.col(g), F.col(k)
    away, turn = -F.log(1 - uniform(f"{salt}r", k)) * 25, 6.283185307179586 * uniform(f"{salt}a", k)
    north = (uniform(f"{salt}y" if salt else "gy", g) - 0.5) * box + away * F.sin(turn)
    east = (uniform(f"{salt}x" if salt else "gx", g) - 0.5) * box + away * F.cos(turn)
    return df.withColumn("lat", base_lat + north / DEGREE_M).withColumn("lon", base_lon + east / (DEGREE_M * F.cos(F.radians(base_lat))))


def station_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """NODE rows (node_id, lat, lon, area_id, group_id, labels) with town, from parts and nations."""
    part = load(spark, sf_dir, "part")
    # Keys alone look small enough to be sent to all tasks through the driver, however many there are; so the join is told not to.
    nodes = part.select(F.col("p_partkey").alias("node_id"), F.floor(F.col("p_partkey") / 4).alias("g"), (F.col("p_partkey") % 4).alias("j"))
    anchors = part.where("p_partkey % 4 = 0").select(F.floor(F.col("p_partkey") / 4).alias("g"), F.col("p_name").alias("m"), F.col("p_brand").alias("b"))
    nodes = nodes.join(anchors.hint("merge"), "g").withColumn("town", F.floor(F.col("g") / 20))
    nations = load(spark, sf_dir, "nation").select(F.col("n_nationkey"), F.col("n_name").alias("t"))
    nodes = nodes.join(F.broadcast(nations), F.col("town") % 25 == F.col("n_nationkey"))  # 25 rows by definition
    nodes = _placed(nodes, "", "g", "node_id", "town", 47.0, 6.0, 4200.0)
    nodes = nodes.withColumns({
        "area_id": F.when(F.col("g") % 4 != 3, F.col("g")),
        "group_id": F.when((F.col("g") % 10).isin(1, 2), F.floor(F.col("g") / 10)),
    })
    t, m, b, j = (F.col(c) for c in "tmbj")
    diverse = F.col("g") % 5 == 0
    bracket = F.concat(m, F.lit(" ("), b, F.lit(")"))
    plain, full = F.concat_ws(" ", t, m), F.concat_ws(" ", t, b, m)
    generic = F.when(~diverse | (j == 3), plain).when(j == 0, F.concat(t, F.lit(", "), m)).when(j == 1, m).otherwise(F.when(F.col("g") % 7 == 0, F.upper(bracket)).otherwise(bracket))
    reference = F.when((diverse & j.isin(0, 2)) | (~diverse & (F.col("g") % 5 == 2) & (j == 0)), full)
    short = F.when(diverse & (j == 1), F.concat(F.substring(F.substring_index(m, " ", 1), 1, 2), F.lit(". "), F.get(F.split(m, " "), F.lit(1))))
    local = F.when(diverse & (j == 3), F.concat(m, F.lit(", "), b))
    of_area = F.when((F.col("g") % 2 == 0) & F.col("area_id").isNotNull() & (j < 2), plain)
    pairs = F.array(*[F.struct(F.lit(k).alias("key"), v.alias("value")) for k, v in (("generic", generic), ("reference", reference), ("short", short), ("local", local), ("area", of_area))])
    nodes = nodes.withColumn("labels", F.map_from_entries(F.filter(pairs, lambda e: e["value"].isNotNull())))
    return nodes.select("node_id", "lat", "lon", "area_id", "group_id", "labels", "town", F.col("t").alias("nation"))


def page_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """NODE rows from web pages: the number in the path names the area, title and its first words are labels."""
    pages = load(spark, sf_dir, "pages").select(
        F.col("page_id").alias("node_id"), F.regexp_extract("url", r"/[a-z][a-z]/([0-9]+)", 1).cast("long").alias("g"),
        F.substring(F.replace(F.regexp_extract("html", "<title>([^<]*)</title>", 1), F.lit("&amp;"), F.lit("&")), 1, 80).alias("title"),
    )
    sizes = pages.groupBy("g").agg(F.count("*").alias("pages"))
    nodes = pages.join(sizes, "g").withColumn("town", F.floor(F.col("g") / 40))
    nodes = _placed(nodes, "p", "g", "node_id", "town", 52.0, -8.0, 3000.0)
    nodes = nodes.withColumn("area_id", F.when(~((F.col("g") % 2 == 0) & (F.col("pages") == 1)), F.col("g")))
    slug = F.when(F.col("node_id") % 2 == 1, F.array_join(F.slice(F.filter(F.split(F.lower("title"), r"[^\p{L}\p{N}_]+"), lambda x: x != ""), 1, 4), " "))
    labels = F.map_from_entries(F.filter(F.array(F.struct(F.lit("generic").alias("key"), F.col("title").alias("value")), F.struct(F.lit("short").alias("key"), slug.alias("value"))), lambda e: e["value"].isNotNull()))
    return nodes.select("node_id", "lat", "lon", "area_id", F.lit(None).cast("long").alias("group_id"), labels.alias("labels"), "town", F.lit("").alias("nation"))


def arrivals(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events as arriving identifiers: a station node, moved by ``value`` metres."""
    from stationlink.functions.geo import moved

    nodes = station_nodes(spark, sf_dir)
    n = load(spark, sf_dir, "part").count()
    events = load(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "event_type", "value", (F.col("event_id") % n).alias("node_id"))
    turn = 6.283185307179586 * uniform("ev", F.col("event_id"))
    out = events.join(nodes.select("node_id", "lat", "lon", F.element_at("labels", "generic").alias("label")), "node_id")
    lat, lon = moved(F.col("lat"), F.col("lon"), F.col("value") * F.cos(turn), F.col("value") * F.sin(turn))
    return out.select("event_id", "ts", "event_type", "node_id", "label", lat.alias("lat"), lon.alias("lon"))
