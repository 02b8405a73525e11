"""Time in annotated places, and the fused features study and social time."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kinetrace.functions.geo import inside
from kinetrace.operators.location import dwell
from kinetrace.operators.steps import BIN_US, FEW
from kinetrace.plans.bouts import ordered, runs, swept
from kinetrace.plans.slices import KEYS, SliceSpec, attach, in_slices, time_in_slices

OUTSIDE, CELL = "off_campus", 0.005


def label_spaces(points: DataFrame, places: DataFrame, overlap: str = "primary") -> DataFrame:
    """`points` with their type: the polygons of a point's cell come by a broadcast of the map, and the exact test is made in the row, without a shuffle.

    overlap: primary (least priority number) or all (a row for each type). Outside every polygon: off_campus.
    """
    lat, lon = (F.transform("polygon", lambda v: v["lat"]), F.transform("polygon", lambda v: v["lon"]))
    cell = lambda c: F.floor(c / CELL)
    cover = places.select("type", "priority", "polygon", F.explode(F.sequence(cell(F.array_min(lat)), cell(F.array_max(lat)))).alias("cy"), cell(F.array_min(lon)).alias("a"), cell(F.array_max(lon)).alias("b"))
    cover = cover.select("type", "priority", "polygon", "cy", F.explode(F.sequence("a", "b")).alias("cx"))
    cover = cover.groupBy("cy", "cx").agg(F.collect_list(F.struct("priority", "type", "polygon")).alias("near"))
    hit = points.withColumns({"cy": cell(F.col("lat")), "cx": cell(F.col("lon"))}).join(F.broadcast(cover), ["cy", "cx"], "left")
    within = F.filter("near", lambda p: inside(F.col("lat"), F.col("lon"), p["polygon"]))
    types = F.array_sort(F.array_distinct(F.transform(F.coalesce(within, F.array().cast(hit.schema["near"].dataType)), lambda p: F.struct(p["priority"].alias("priority"), p["type"].alias("type")))))
    found = hit.withColumn("types", types["type"]).drop("cy", "cx", "near")
    if overlap == "all":
        return found.withColumn("type", F.explode(F.when(F.size("types") > 0, F.col("types")).otherwise(F.array(F.lit(OUTSIDE))))).drop("types")
    return found.withColumn("type", F.coalesce(F.get(F.col("types"), F.lit(0)), F.lit(OUTSIDE))).drop("types")


def space_bouts(spaces: DataFrame) -> DataFrame:
    """person_id, type, start_us, end_us, minutes: runs of one type, each lasting until the next sample after it."""
    rows = spaces.withColumn("to", F.coalesce(F.lead("us").over(ordered()), F.col("us")))
    found = runs(rows, "type", extra=(F.max("to").alias("end_us"),))
    return found.select("person_id", "type", F.col("first_us").alias("start_us"), "end_us", ((F.col("end_us") - F.col("first_us")) / 60e6).alias("minutes"))


def space_minutes(spaces: DataFrame, spec: SliceSpec | None = None) -> DataFrame:
    """Minutes and share of each type in a slice; what a sample holds beyond a slice's border counts in the next."""
    rows = time_in_slices(dwell(spaces), spec or SliceSpec()).groupBy("person_id", *KEYS, "type").agg(F.sum("minutes").alias("minutes"))
    return rows.withColumn("share", F.try_divide("minutes", F.sum("minutes").over(Window.partitionBy("person_id", *KEYS))))


def space_transitions(spaces: DataFrame, spec: SliceSpec | None = None) -> DataFrame:
    rows = spaces.withColumn("moved", (F.col("type") != F.lag("type").over(ordered())).cast("bigint"))
    return attach(rows, spec or SliceSpec()).groupBy("person_id", *KEYS).agg(F.coalesce(F.sum("moved"), F.lit(0)).alias("transitions"))


def bout_features(bouts: DataFrame, spec: SliceSpec | None = None, least: tuple[int, ...] = (10, 20, 30)) -> DataFrame:
    """Bouts, those of at least 10, 20 and 30 minutes, and length statistics by type; bouts are cut at the slice's borders."""
    m = F.col("minutes")
    rows = in_slices(bouts, spec or SliceSpec(), ("type",)).groupBy("person_id", *KEYS, "type")
    return rows.agg(F.count("*").alias("bouts"), *(F.count_if(m >= k).alias(f"bouts_{k}") for k in least), F.min(m).alias("shortest"), F.max(m).alias("longest"), F.avg(m).alias("mean"), F.stddev_pop(m).alias("std"))


def study_intervals(bouts: DataFrame, bins: DataFrame, interaction: DataFrame, min_minutes: float = 30, max_steps: int = FEW) -> DataFrame:
    """Maximal intervals in an academic place with fewer than ten steps in each five minutes and no phone in use.

    A five-minute bin without step samples counts as still."""
    active = bins.where(F.col("steps") >= max_steps).select("person_id", F.lit("active").alias("kind"), F.col("us").alias("start_us"), (F.col("us") + BIN_US).alias("end_us"))
    at = bouts.where("type = 'academic'").select("person_id", F.lit("academic").alias("kind"), "start_us", "end_us")
    phone = interaction.select("person_id", F.lit("phone").alias("kind"), "start_us", "end_us")
    found = swept(at.union(active).union(phone), ["academic"], ["active", "phone"])
    return found.withColumn("minutes", (F.col("end_us") - F.col("start_us")) / 60e6).where(F.col("minutes") >= min_minutes)


def social_bouts(bouts: DataFrame, voice: DataFrame, min_minutes: float = 20, min_share: float = 0.8, types: tuple[str, ...] = ("apartment", "residence", "green")) -> DataFrame:
    """Bouts at residential or green places in which voice or noise makes up the share: an equi-join on hours, then the exact bounds."""
    hour = 3_600_000_000
    b = bouts.where(F.col("type").isin(*types) & (F.col("minutes") >= min_minutes)).select("person_id", "start_us", "end_us", "minutes")
    b = b.withColumn("hour", F.explode(F.sequence(F.floor(F.col("start_us") / float(hour)), F.floor((F.col("end_us") - 1) / float(hour)))))
    v = voice.select("person_id", "us", "inference", F.floor(F.col("us") / float(hour)).alias("hour"))
    both = b.join(v, ["person_id", "hour"]).where("us >= start_us and us < end_us")
    rows = both.groupBy("person_id", "start_us", "end_us", "minutes").agg(F.avg(F.col("inference").isin("voice", "noise").cast("double")).alias("voiced"))
    return rows.where(F.col("voiced") >= min_share)


def total_minutes(intervals: DataFrame, name: str, spec: SliceSpec | None = None) -> DataFrame:
    """Minutes and number of intervals in each slice, cut at its borders."""
    rows = in_slices(intervals.select("person_id", "start_us", "end_us"), spec or SliceSpec(epochs=False))
    return rows.groupBy("person_id", *KEYS).agg(F.sum("minutes").alias(name), F.count("*").alias("bouts"))
