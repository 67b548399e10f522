"""Sinks: GeoJSON lines for clients."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.geo import lat, lon


def feature(x: Column, y: Column, properties: Column) -> Column:
    """A point feature as JSON text."""
    return F.to_json(F.struct(F.lit("Feature").alias("type"), F.struct(F.lit("Point").alias("type"), F.array(lon(x), lat(y)).alias("coordinates")).alias("geometry"), properties.alias("properties")))


def geojson(df: DataFrame, path: str, x: str = "cent_x", y: str = "cent_y") -> None:
    """One feature a line, with all other columns as properties."""
    rest = [c for c in df.columns if c not in (x, y)]
    df.select(feature(F.col(x), F.col(y), F.struct(*rest)).alias("value")).write.mode("overwrite").text(path)
