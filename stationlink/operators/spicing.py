"""Harder truth: foreign labels near stations, shaken positions; and train parts."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stationlink.functions import geo
from stationlink.functions.numbering import uniform


def foreign_labels(idents: DataFrame, p: float = 0.5, m: int = 5, radius_m: float = 100.0, outside_m: float = 1000.0, tries: int = 16) -> DataFrame:
    """Pairs, not similar, of an identifier and ``m`` identifiers from outside ``outside_m`` that are put within ``radius_m`` of it.

    Identifiers are drawn by hashed numbers (an equal join; ident_id is 1 to n without gaps) and rejected by distance; of
    ``tries`` draws the first m different ones stay, so there are fewer than m only where most identifiers lie within the
    radius. Their place is uniform in the disc. Other columns of ``idents`` go along on both sides.
    """
    from stationlink.plans.workspace import materialize

    n = idents.agg(F.max("ident_id")).first()[0] or 0
    names = [c for c in ("ident_id", "node_id", "area_id", "group_id", "label", "lat", "lon", "town", "nation") if c in idents.columns]
    drawn = idents.where(uniform("sp", F.col("ident_id")) < p).select(F.col("ident_id").alias("a"), F.col("lat").alias("a_y"), F.col("lon").alias("a_x"))
    place = idents.select(F.col("ident_id").alias("b"), F.col("lat").alias("b_y"), F.col("lon").alias("b_x"))

    def picked(drawn: DataFrame, tries: int) -> DataFrame:
        draws = F.array(*[1 + F.floor(uniform("sw", F.col("a"), F.lit(i)) * n) for i in range(tries)])
        rows = drawn.withColumn("draws", draws).select("a", "a_y", "a_x", "draws", F.posexplode("draws").alias("i", "b"))
        rows = rows.where(F.array_position("draws", F.col("b")) == F.col("i") + 1).drop("draws")  # a number drawn again counts once
        far = rows.join(place.hint("shuffle_hash"), "b").where(geo.haversine_m(F.col("a_y"), F.col("a_x"), F.col("b_y"), F.col("b_x")) > outside_m)
        # Which of the draws come first: counted over at most ``tries`` rows of one identifier.
        return far.groupBy("a").agg(F.slice(F.array_sort(F.collect_list(F.struct("i", "b"))), 1, m).alias("first"))

    if m + 2 < tries:  # few draws are rejected, so the first few are enough for nearly all
        some = materialize(picked(drawn, m + 2), "foreign-draws").where(F.size("first") == m)
        seen = some.unionByName(picked(drawn.join(some.select("a"), "a", "left_anti"), tries))
    else:
        seen = picked(drawn, tries)
    seen = seen.select("a", F.inline("first"))
    left = idents.select(*[F.col(c).alias(f"a_{c}") for c in names])
    right = idents.select(*[F.col(c).alias(f"b_{c}") for c in names])
    pairs = seen.join(left, seen.a == left.a_ident_id).join(right, seen.b == right.b_ident_id).drop("a", "b")
    key = (F.col("a_ident_id"), F.col("i"))
    away, turn = radius_m * F.sqrt(uniform("sd", *key)), 2 * math.pi * uniform("sb", *key)
    lat, lon = geo.moved(F.col("a_lat"), F.col("a_lon"), away * F.sin(turn), away * F.cos(turn))
    pairs = pairs.withColumn("b_lat", lat).withColumn("b_lon", lon)
    pairs = pairs.withColumn("dist_m", geo.haversine_m(F.col("a_lat"), F.col("a_lon"), F.col("b_lat"), F.col("b_lon")))
    pairs = pairs.withColumn("pair_id", F.concat_ws(":", F.lit("A"), "a_ident_id", "i"))
    return pairs.withColumn("truth", F.lit(0)).withColumn("origin", F.lit("spiced_label")).drop("i")


def shaken(pairs: DataFrame, p: float = 0.5, sigma_m: float = 100.0) -> DataFrame:
    """Similar pairs, with probability p, get Gaussian noise on the right end's position (per axis)."""
    key = (F.col("a_ident_id"), F.col("b_ident_id"))
    hit = (F.col("truth") == 1) & (uniform("ns", *key) < p)
    size = sigma_m * F.sqrt(-2 * F.log(1 - uniform("n1", *key)))
    turn = 2 * math.pi * uniform("n2", *key)
    lat, lon = geo.moved(F.col("b_lat"), F.col("b_lon"), size * F.cos(turn), size * F.sin(turn))
    hit = F.coalesce(hit, F.lit(False))
    out = pairs.withColumns({"b_lat": F.when(hit, lat).otherwise(F.col("b_lat")), "b_lon": F.when(hit, lon).otherwise(F.col("b_lon")), "origin": F.when(hit, F.lit("spiced_position")).otherwise(F.col("origin"))})
    dist = geo.haversine_m(F.col("a_lat"), F.col("a_lon"), F.col("b_lat"), F.col("b_lon"))
    return out.withColumn("dist_m", F.when(F.col("origin") == "spiced_position", dist).otherwise(F.col("dist_m")))


def spiced_pairs(idents: DataFrame, pairs: DataFrame, p: float = 0.5) -> DataFrame:
    """Judged pairs, shaken, and foreign-label pairs beside them; columns that these don't have are null there."""
    if p <= 0:
        return pairs
    extra = foreign_labels(idents, p)
    return shaken(pairs, p).unionByName(extra.select(*[c for c in pairs.columns if c in extra.columns]), allowMissingColumns=True)


def spice_levels(idents: DataFrame, pairs: DataFrame, levels: dict, m: int = 5) -> DataFrame:
    """(level, truth, dist_m) of the pairs with known truth at each of ``levels``: name to (probability of foreign labels, of shaken positions).

    What a draw gives does not depend on its probability, so foreign pairs and shaken distances are made once, for the
    largest, and each level takes those whose hashed number is below its own.
    """
    most_labels, most_shaken = (max(p[k] for p in levels.values()) for k in (0, 1))
    own = pairs.where("truth is not null").withColumn("plain_m", F.col("dist_m"))
    hit = uniform("ns", F.col("a_ident_id"), F.col("b_ident_id"))
    mapped = shaken(own, most_shaken).select("truth", "plain_m", "dist_m", F.when(F.col("origin") == "spiced_position", hit).alias("u"))
    each = F.explode(F.array(*[F.struct(F.lit(n).alias("level"), F.lit(float(p)).alias("p")) for n, (_, p) in levels.items()])).alias("l")
    out = mapped.select("truth", "plain_m", "dist_m", "u", each).select("l.level", "truth", F.when(F.col("u") < F.col("l.p"), F.col("dist_m")).otherwise(F.col("plain_m")).alias("dist_m"))
    if most_labels <= 0:
        return out
    extra = foreign_labels(idents, most_labels, m).select("truth", "dist_m", uniform("sp", F.col("a_ident_id")).alias("u"))
    each = F.explode(F.array(*[F.struct(F.lit(n).alias("level"), F.lit(float(p)).alias("p")) for n, (p, _) in levels.items()])).alias("l")
    return out.unionByName(extra.select("truth", "dist_m", "u", each).where(F.col("u") < F.col("l.p")).select("l.level", "truth", "dist_m"))


def misspelled(pairs: DataFrame, p: float = 0.5, column: str = "b_label") -> DataFrame:
    """``pairs`` where a label has, with probability p, one random edit: a character lost, a letter put in or put in its place.

    Empty and null labels stay as they are.
    """
    key, label = F.col("pair_id"), F.col(column)
    at = F.floor(uniform("wp", key) * F.length(label)).cast("int")
    letter = F.substr(F.lit("abcdefghijklmnopqrstuvwxyz"), 1 + F.floor(uniform("wc", key) * 26).cast("int"), F.lit(1))
    kind = F.floor(uniform("wk", key) * 3)
    head, tail = F.substr(label, F.lit(1), at), F.substr(label, at + 1)
    edited = F.concat(head, F.when(kind > 0, letter).otherwise(F.lit("")), F.when(kind == 1, tail).otherwise(F.substr(label, at + 2)))
    return pairs.withColumn(column, F.when((F.length(label) > 0) & (uniform("ws", key) < p), edited).otherwise(label))


def in_train(pair_id, repeat: int = 0, share: float = 0.2) -> Column:
    """Whether a pair is in the train part of a repeat; the same for all methods and partitionings."""
    return uniform(f"split:{repeat}", pair_id) < share
