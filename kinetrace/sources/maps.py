"""Maps of annotated places: GeoJSON features and WKT polygons, read to (place_id, name, type, priority, polygon) and written from it.

A polygon is its outer ring as (lat, lon) corners without the closing one; holes are not kept. Both formats give longitude first.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

RING = "array<struct<lat:double,lon:double>>"
#: What is read of a feature; unknown members are ignored, and a feature without a polygon is dropped.
FEATURE = "properties struct<place_id:bigint,name:string,type:string,priority:int>, geometry struct<type:string,coordinates:array<array<array<double>>>>"


def _base(spark: SparkSession) -> str:
    return (spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.sql.warehouse.dir")).rstrip("/")


def _opened(ring):
    """A closed ring without its last corner."""
    closed = (F.size(ring) > 1) & (F.element_at(ring, 1) == F.element_at(ring, -1))
    return F.when(closed, F.slice(ring, F.lit(1), F.size(ring) - 1)).otherwise(ring)


def read_geojson(spark: SparkSession, path: str) -> DataFrame:
    """Polygons of GeoJSON files: a FeatureCollection in each file, or a feature in each line."""
    text = spark.read.option("wholetext", True).text(path)
    whole = F.from_json("value", f"type string, features array<struct<{FEATURE}>>")
    lines = F.transform(F.split("value", "\n"), lambda x: F.from_json(x, FEATURE))
    rows = text.select(F.explode(F.coalesce(whole["features"], lines)).alias("f")).where("f.geometry.type = 'Polygon'").select("f.*")
    ring = F.transform(F.col("geometry.coordinates")[0], lambda p: F.struct(p[1].alias("lat"), p[0].alias("lon")))
    return rows.select("properties.*", _opened(ring).cast(RING).alias("polygon"))


def write_geojson(places: DataFrame, path: str | None = None) -> str:
    """A feature in each line."""
    path = path or f"{_base(places.sparkSession)}/kinetrace/map-{uuid.uuid4().hex}"
    ring = F.concat("polygon", F.slice("polygon", 1, 1))
    shape = F.struct(F.lit("Polygon").alias("type"), F.array(F.transform(ring, lambda v: F.array(v["lon"], v["lat"]))).alias("coordinates"))
    feature = F.struct(F.lit("Feature").alias("type"), F.struct(*(F.col(c) for c in ("place_id", "name", "type", "priority"))).alias("properties"), shape.alias("geometry"))
    places.select(F.to_json(feature).alias("value")).write.text(path)
    return path


def to_wkt(places: DataFrame) -> DataFrame:
    ring = F.concat("polygon", F.slice("polygon", 1, 1))
    corners = F.array_join(F.transform(ring, lambda v: F.concat_ws(" ", v["lon"].cast("string"), v["lat"].cast("string"))), ", ")
    return places.withColumn("wkt", F.concat(F.lit("POLYGON (("), corners, F.lit("))"))).drop("polygon")


def from_wkt(rows: DataFrame, column: str = "wkt") -> DataFrame:
    """`rows` with the polygon of a WKT column in its place; text that is no polygon gives null."""
    outer = F.regexp_extract(F.upper(column), r"^\s*POLYGON\s*\(\s*\(([^()]*)\)", 1)
    corner = lambda t: F.split(F.trim(t), r"\s+")
    ring = F.transform(F.split(outer, ","), lambda t: F.struct(corner(t)[1].try_cast("double").alias("lat"), corner(t)[0].try_cast("double").alias("lon")))
    return rows.withColumn("polygon", F.when(F.length(outer) > 0, _opened(ring)).cast(RING)).drop(column)
