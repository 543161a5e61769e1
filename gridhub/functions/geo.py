"""Geometry on the sphere as Catalyst expressions; never used for tile keys."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Fixed value: mean radius of the earth in metres.
EARTH_M = 6_371_008.8


def haversine(lon1: Column, lat1: Column, lon2: Column, lat2: Column) -> Column:
    """Great-circle distance in metres between points in degrees."""
    a = F.pow(F.sin(F.radians(lat2 - lat1) / 2), 2) + F.cos(F.radians(lat1)) * F.cos(F.radians(lat2)) * F.pow(F.sin(F.radians(lon2 - lon1) / 2), 2)
    return F.lit(2 * EARTH_M) * F.asin(F.least(F.lit(1.0), F.sqrt(a)))


def degrees_to_metres(lat: Column) -> tuple[Column, Column]:
    """Metres per degree of longitude and of latitude at a latitude."""
    per = F.lit(EARTH_M) * F.radians(F.lit(1.0))
    return per * F.cos(F.radians(lat)), per
