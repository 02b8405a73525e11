"""Distances on the sphere and polygons, as expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

RADIUS_KM = 6371.0088


def haversine_km(lat1: Column, lon1: Column, lat2: Column, lon2: Column) -> Column:
    a = F.pow(F.sin(F.radians(lat2 - lat1) / 2), 2) + F.cos(F.radians(lat1)) * F.cos(F.radians(lat2)) * F.pow(F.sin(F.radians(lon2 - lon1) / 2), 2)
    return F.asin(F.least(F.sqrt(a), F.lit(1.0))) * (2 * RADIUS_KM)


def inside(lat: Column, lon: Column, ring: Column) -> Column:
    """Parity of the eastward ray's crossings of a ring of (lat, lon); an edge holds its lower end only."""

    def crosses(a: Column, b: Column) -> Column:
        spans = (a["lat"] > lat) != (b["lat"] > lat)
        return spans & (lon < (b["lon"] - a["lon"]) * F.try_divide(lat - a["lat"], b["lat"] - a["lat"]) + a["lon"])

    edges = F.zip_with(ring, F.concat(F.slice(ring, 2, F.size(ring)), F.slice(ring, 1, 1)), lambda a, b: F.when(crosses(a, b), 1).otherwise(0))
    return F.aggregate(edges, F.lit(0), lambda n, x: n + x) % 2 == 1
