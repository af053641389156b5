"""Projection, distances and predicates on points."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

EARTH_M = 6_371_008.8


def project(places: DataFrame, lon0: float | None = None, lat0: float | None = None) -> DataFrame:
    """Degrees to metres around a point (default: per zone of six degrees, whose number is added as `zone`)."""
    lon, lat = F.col("lon"), F.col("lat")
    zone = F.floor((lon + 180) / 6).cast("int")
    x0 = F.lit(lon0) if lon0 is not None else zone * 6 - 177.0
    y0 = F.lit(lat0) if lat0 is not None else F.lit(0.0)
    middle = F.lit(lat0) if lat0 is not None else F.round(lat)
    return places.withColumns({"zone": zone, "x_m": F.radians(lon - x0) * F.cos(F.radians(middle)) * EARTH_M, "y_m": F.radians(lat - y0) * EARTH_M})


def euclid_m(xa: Column, ya: Column, xb: Column, yb: Column) -> Column:
    return F.sqrt((xa - xb) * (xa - xb) + (ya - yb) * (ya - yb))


def haversine_m(lon_a: Column, lat_a: Column, lon_b: Column, lat_b: Column) -> Column:
    h = F.pow(F.sin(F.radians(lat_b - lat_a) / 2), 2) + F.cos(F.radians(lat_a)) * F.cos(F.radians(lat_b)) * F.pow(F.sin(F.radians(lon_b - lon_a) / 2), 2)
    return 2 * EARTH_M * F.asin(F.sqrt(h))


def within_box(x0: float, y0: float, x1: float, y1: float) -> Column:
    return F.col("x_m").between(x0, x1) & F.col("y_m").between(y0, y1)


def within_radius(x: float, y: float, r: float) -> Column:
    """The box comes first: it can be pushed to the scan."""
    return within_box(x - r, y - r, x + r, y + r) & (euclid_m(F.col("x_m"), F.col("y_m"), F.lit(x), F.lit(y)) <= r)
