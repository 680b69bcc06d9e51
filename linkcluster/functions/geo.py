"""Geographic similarity and grid cells."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

EARTH_KM = 6371.0088
#: Greatest distance that counts, and the scale of the normalised similarity.
MAX_KM = 1358.0


def haversine_km(lat1: Column, lon1: Column, lat2: Column, lon2: Column) -> Column:
    half = lambda d: F.pow(F.sin(F.radians(d) / 2), F.lit(2))
    h = half(lat2 - lat1) + F.cos(F.radians(lat1)) * F.cos(F.radians(lat2)) * half(lon2 - lon1)
    return 2 * EARTH_KM * F.asin(F.sqrt(F.least(F.lit(1.0), h)))


def geo_similarity(lat1: Column, lon1: Column, lat2: Column, lon2: Column, max_km: float = MAX_KM) -> Column:
    d = haversine_km(lat1, lon1, lat2, lon2)
    return F.when(d <= max_km, 1 - d / max_km)


def cell(lat: Column, lon: Column, km: float) -> tuple[Column, Column, Column]:
    """(row, column, columns in that row) of the cell that holds a point; cells are at least ``km`` wide and high."""
    step = math.degrees(km / EARTH_KM)
    row = F.floor((lat + 90) / step).cast("int")
    return (row, *_columns(row, lon, step))


def _columns(row: Column, lon: Column, step: float) -> tuple[Column, Column]:
    # the narrowest latitude of the row sets the cell width, so equal neighbours reach far enough
    edge = F.least(F.lit(89.999), F.greatest(F.abs(row * step - 90), F.abs((row + 1) * step - 90)))
    n = F.greatest(F.lit(1), F.floor(360 / (step / F.cos(F.radians(edge)))).cast("int"))
    return F.floor((lon + 180) / 360 * n).cast("int") % n, n


def neighbour_cells(lat: Column, lon: Column, km: float) -> Column:
    """All (row, column) cells that may hold a point within ``km``; wraps at the date line."""
    step = math.degrees(km / EARTH_KM)
    row = F.floor((lat + 90) / step).cast("int")

    def of(r: Column) -> Column:
        col, n = _columns(r, lon, step)
        # within a row a distance of km spans at most one cell; near a pole all columns count
        wide = F.transform(F.array(F.lit(-1), F.lit(0), F.lit(1)), lambda d: F.struct(r.alias("row"), ((col + d + n) % n).alias("col")))
        return F.when(n <= 6, F.transform(F.sequence(F.lit(0), F.least(n, F.lit(6)) - 1), lambda c: F.struct(r.alias("row"), c.cast("int").alias("col")))).otherwise(wide)

    return F.array_distinct(F.flatten(F.transform(F.sequence(row - 1, row + 1), of)))
