"""Features of a pair for the forest: distance, trigrams in one label only, grid cells, signed trigram differences."""

from __future__ import annotations

import json
import zlib

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stationlink.functions import geo, text


def trigram_xor(a, b) -> Column:
    """Number of distinct trigrams in one label only."""
    x, y = text.trigrams(a), text.trigrams(b)
    return F.size(F.array_union(x, y)) - F.size(F.array_intersect(x, y))


def order_differs(a, b) -> Column:
    """1 if the tokens that both labels have come in another order (the first place of a token counts), else 0."""
    x, y = text.tokens(a), text.tokens(b)
    return (F.array_intersect(x, y) != F.array_intersect(y, x)).cast("int")


def trigram_counts(label) -> Column:
    """map of trigram to its count in a label."""
    grams = text.trigrams(label)
    return F.map_from_entries(F.transform(F.array_distinct(grams), lambda g: F.struct(g.alias("key"), F.size(F.filter(grams, lambda x: x == g)).alias("value"))))


def trigram_dictionary(labels: DataFrame, k: int = 2500, column: str = "label") -> list[str]:
    """The k most frequent trigrams over labels, ties by code point; k strings come to the driver."""
    counted = labels.select(F.explode(text.trigrams(F.col(column))).alias("gram")).groupBy("gram").agg(F.count("*").alias("n"))
    return [r["gram"] for r in counted.orderBy(F.col("n").desc(), "gram").limit(k).collect()]


def trigram_delta(a, b, dictionary: list[str]) -> Column:
    """array of count(b) - count(a) for each trigram of the dictionary."""
    x, y = trigram_counts(a), trigram_counts(b)
    grams = F.array(*[F.lit(g) for g in dictionary]) if dictionary else F.array().cast("array<string>")
    bound = F.array(F.struct(x.alias("x"), y.alias("y")))  # maps are made once
    return F.transform(bound, lambda m: F.transform(grams, lambda g: F.coalesce(F.try_element_at(m["y"], g), F.lit(0)) - F.coalesce(F.try_element_at(m["x"], g), F.lit(0))))[0]


def vectors(pairs: DataFrame, dictionary: list[str], grids: int = 2, order: bool = False) -> DataFrame:
    """``pairs`` with sparse ``index`` and ``value`` arrays: distance, xor, 2 * grids cell numbers, trigram differences.

    Only trigrams of the two labels that are in the dictionary and differ take room. ``order`` puts ``order_differs``
    after the cell numbers. What depends on the labels alone is computed once for each distinct pair of them, and what
    depends on one label once for that label; rows come in no certain order.
    """
    lat, lon = geo.centroid(F.col("a_lat"), F.col("a_lon"), F.col("b_lat"), F.col("b_lon"))
    cells = geo.grid_cells(lat, lon, grids)
    base = 2 + 2 * grids + order
    # Places of the trigrams, dealt to many small maps by a hash: a map is searched from its start.
    slots: list[dict[str, int]] = [{} for _ in range(max(len(dictionary), 1))]
    for i, g in enumerate(dictionary):
        slots[zlib.crc32(g.encode()) % len(slots)][g] = base + i
    places = F.from_json(F.lit(json.dumps(slots)), "array<map<string,int>>")
    place = lambda g: F.try_element_at(F.get(places, (F.crc32(g.cast("binary")) % len(slots)).cast("int")), g)
    spark = pairs.sparkSession
    tasks = max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))  # few bytes, but much work
    labels = pairs.select(F.col("a_label").alias("__a"), F.col("b_label").alias("__b")).distinct()
    own = labels.select(F.explode(F.array("__a", "__b")).alias("label")).distinct().repartition(tasks, "label")
    entry = lambda gs: lambda g: F.struct(place(g).alias("key"), F.size(F.filter(gs, lambda x: x == g)).alias("value"))
    counted = lambda gs: F.map_from_entries(F.filter(F.transform(F.array_distinct(gs), entry(gs)), lambda e: e["key"].isNotNull()))
    # An array of one, so that a label is cut once and not for each of its trigrams.
    own = own.select("label", F.transform(F.array(text.trigrams("label")), lambda gs: F.struct(F.array_distinct(gs).alias("grams"), counted(gs).alias("n")))[0].alias("of"))
    for side in "ab":
        of = own.select(F.col("label").alias("__label"), F.col("of").alias(f"__of_{side}"))
        labels = labels.join(of, F.col(f"__{side}").eqNullSafe(F.col("__label"))).drop("__label")
    labels = labels.repartition(tasks, "__a", "__b")
    count = lambda n, i: F.coalesce(F.try_element_at(n, i), F.lit(0))
    differ = F.transform(F.array_union(F.map_keys("__of_a.n"), F.map_keys("__of_b.n")), lambda i: F.struct(i.alias("i"), (count(F.col("__of_b.n"), i) - count(F.col("__of_a.n"), i)).cast("double").alias("v")))
    kept = F.sort_array(F.filter(differ, lambda d: d["v"] != 0))
    xor = F.size(F.array_union("__of_a.grams", "__of_b.grams")) - F.size(F.array_intersect("__of_a.grams", "__of_b.grams"))
    labels = labels.select("__a", "__b", kept.alias("__kept"), xor.cast("double").alias("__xor"), *([order_differs("__a", "__b").cast("double").alias("__order")] if order else []))
    dense = [F.col("dist_m"), F.col("__xor")]
    for i in range(grids):
        dense += [cells[i]["x"].cast("double"), cells[i]["y"].cast("double")]
    if order:
        dense.append(F.col("__order"))
    rows = pairs.join(labels, pairs["a_label"].eqNullSafe(labels["__a"]) & pairs["b_label"].eqNullSafe(labels["__b"]))
    index = F.concat(F.array(*[F.lit(i) for i in range(base)]), F.transform("__kept", lambda d: d["i"]))
    value = F.concat(F.array(*dense), F.transform("__kept", lambda d: d["v"]))
    return rows.withColumn("index", index).withColumn("value", value).drop("__a", "__b", "__kept", "__xor", "__order")
