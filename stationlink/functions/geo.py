"""Distances, places and grid cells as column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

EARTH_M = 6_371_008.8
DEGREE_M = 111_194.93


def haversine_m(lat1, lon1, lat2, lon2) -> Column:
    """Metres along a great circle."""
    lat1, lon1, lat2, lon2 = (F.radians(x) for x in (lat1, lon1, lat2, lon2))
    h = F.pow(F.sin((lat2 - lat1) / 2), 2) + F.cos(lat1) * F.cos(lat2) * F.pow(F.sin((lon2 - lon1) / 2), 2)
    return 2 * EARTH_M * F.asin(F.least(F.lit(1.0), F.sqrt(h)))


def fast_distance_m(lat1, lon1, lat2, lon2) -> Column:
    """Equirectangular metres: for filters before the exact distance, not for truth."""
    lat1, lon1, lat2, lon2 = (F.radians(x) for x in (lat1, lon1, lat2, lon2))
    x = (lon2 - lon1) * F.cos((lat1 + lat2) / 2)
    return EARTH_M * F.sqrt(x * x + (lat2 - lat1) * (lat2 - lat1))


def centroid(lat1: Column, lon1: Column, lat2: Column, lon2: Column) -> tuple[Column, Column]:
    """Middle of two near points; longitudes on either side of the antimeridian wrap."""
    turn = F.when(F.abs(lon1 - lon2) > 180, 360.0).otherwise(0.0)
    lon = (F.when(lon1 < 0, lon1 + turn).otherwise(lon1) + F.when(lon2 < 0, lon2 + turn).otherwise(lon2)) / 2
    return (lat1 + lat2) / 2, F.when(lon > 180, lon - 360).otherwise(lon)


def grid_cells(lat: Column, lon: Column, n: int = 2, cells: int = 256) -> Column:
    """array<struct<x,y>> of n equal grids of the whole map, grid i moved by i/n of a cell; x wraps, y is clamped."""
    x, y = (lon + 180) / (360 / cells), (lat + 90) / (180 / cells)
    one = [F.struct(F.pmod(F.floor(x - i / n), F.lit(cells)).cast("int").alias("x"), F.least(F.greatest(F.floor(y - i / n), F.lit(0)), F.lit(cells - 1)).cast("int").alias("y")) for i in range(n)]
    return F.array(*one) if one else F.array().cast("array<struct<x:int,y:int>>")


def moved(lat: Column, lon: Column, east_m: Column, north_m: Column) -> tuple[Column, Column]:
    """A point moved by metres east and north."""
    return lat + north_m / DEGREE_M, lon + east_m / (DEGREE_M * F.cos(F.radians(lat)))


def band_height(radius_m: float) -> float:
    """Degrees of a latitude band that is a little higher than the radius."""
    return radius_m / 111_100.0


def band(lat: Column, radius_m: float) -> Column:
    return F.floor((lat + 90) / band_height(radius_m)).cast("int")


def band_cells(b: Column, radius_m: float) -> Column:
    """Number of longitude cells of a band; none is narrower than the radius anywhere in it."""
    h = band_height(radius_m)
    edge = F.least(F.lit(90.0), F.greatest(F.abs(b * h - 90), F.abs((b + 1) * h - 90)))
    return F.greatest(F.lit(1), F.floor(360 * F.cos(F.radians(edge)) / h)).cast("int")


def cell(lon: Column, count: Column) -> Column:
    return F.pmod(F.floor((lon + 180) / 360 * count), count).cast("int")


def covering_cells(lat: Column, lon: Column, radius_m: float) -> Column:
    """array<struct<band,cell>> of all cells that a point within the radius can be in."""
    h = band_height(radius_m)

    def of(b: Column) -> Column:
        count = band_cells(b, radius_m)
        at = F.floor((lon + 180) / 360 * count)
        # A cell is at least the radius wide, so one more to either side is enough; few cells are all taken.
        near = F.when(count <= 3, F.sequence(F.lit(0), count - 1)).otherwise(F.array_distinct(F.array(*[F.pmod(at + d, count).cast("int") for d in (-1, 0, 1)])))
        return F.transform(near, lambda c: F.struct(b.alias("band"), c.alias("cell")))

    own = F.floor((lat + 90) / h).cast("int")
    return F.flatten(F.array(*[of(own + d) for d in (-1, 0, 1)]))
