"""Positions in milli-arc-seconds: distances, bearings, rectangles and text forms, all as native columns."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import RegionSpec

EARTH_KM = 6371.0088
MAS = 3_600_000.0


def lon(x: Column, region: RegionSpec = RegionSpec()) -> Column:
    return F.lit(region.west) + x / F.lit(MAS)


def lat(y: Column, region: RegionSpec = RegionSpec()) -> Column:
    return F.lit(region.south) + y / F.lit(MAS)


def great_circle_km(x1: Column, y1: Column, x2: Column, y2: Column, region: RegionSpec = RegionSpec()) -> Column:
    """Haversine distance."""
    a, b = F.radians(lat(y1, region)), F.radians(lat(y2, region))
    dx = F.radians(lon(x2, region)) - F.radians(lon(x1, region))
    h = F.pow(F.sin((b - a) / 2), F.lit(2.0)) + F.cos(a) * F.cos(b) * F.pow(F.sin(dx / 2), F.lit(2.0))
    return F.lit(2 * EARTH_KM) * F.asin(F.sqrt(h))


def bearing(x1: Column, y1: Column, x2: Column, y2: Column, region: RegionSpec = RegionSpec()) -> Column:
    """Initial bearing in degrees from north, 0 to 360."""
    a, b = F.radians(lat(y1, region)), F.radians(lat(y2, region))
    d = F.radians(lon(x2, region)) - F.radians(lon(x1, region))
    deg = F.degrees(F.atan2(F.sin(d) * F.cos(b), F.cos(a) * F.sin(b) - F.sin(a) * F.cos(b) * F.cos(d)))
    return F.when(deg < 0, deg + 360.0).otherwise(deg)


def speed_kmh(km: Column, seconds: Column) -> Column:
    return F.when(seconds > 0, km * 3600.0 / seconds)


def in_box(x: Column, y: Column, x0, y0, x1, y1) -> Column:
    """Half-open containment."""
    return (x >= x0) & (x < x1) & (y >= y0) & (y < y1)


def boxes_meet(ax0, ay0, ax1, ay1, bx0, by0, bx1, by1) -> Column:
    """Half-open rectangles with a common point."""
    return (ax0 < bx1) & (bx0 < ax1) & (ay0 < by1) & (by0 < ay1)


def clip(points: DataFrame, region: RegionSpec = RegionSpec(), x: str = "x_mas", y: str = "y_mas") -> DataFrame:
    """Rows whose position is known and inside the region."""
    return points.where(in_box(F.col(x), F.col(y), 0, 0, region.width, region.height))


def wkt_line(x1: Column, y1: Column, x2: Column, y2: Column) -> Column:
    """Line text in whole milli-arc-seconds, which no rounding can change."""
    t = lambda c: c.cast("string")
    return F.concat(F.lit("LINESTRING("), t(x1), F.lit(" "), t(y1), F.lit(", "), t(x2), F.lit(" "), t(y2), F.lit(")"))
