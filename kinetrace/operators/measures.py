"""Cost and accuracy measures."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kinetrace.functions.geo import haversine_km
from kinetrace.functions.timeparts import div, epoch_of
from kinetrace.operators import location
from kinetrace.plans.slices import KEYS, SliceSpec, attach
from kinetrace.sources import views as V


def coverage(stream: DataFrame, spec: SliceSpec | None = None) -> DataFrame:
    """Samples and hours with data of each slice; hours are counted once by a first aggregation."""
    hours = attach(stream, spec or SliceSpec()).groupBy("person_id", *KEYS, div(F.col("us"), 3_600_000_000).alias("hour")).agg(F.count("*").alias("n"))
    return hours.groupBy("person_id", *KEYS).agg(F.sum("n").alias("samples"), F.count("*").alias("hours"))


def pair_agreement(rows: DataFrame, a: str, b: str) -> DataFrame:
    """person_id and the adjusted Rand index of two labellings, from the contingency table."""
    pairs = lambda n: F.col(n) * (F.col(n) - 1) / 2
    cells = rows.groupBy("person_id", a, b).agg(F.count("*").alias("n"))
    side = lambda c: cells.groupBy("person_id", c).agg(F.sum("n").alias("n")).groupBy("person_id").agg(F.sum(pairs("n")).alias(f"s_{c}"))
    both = cells.groupBy("person_id").agg(F.sum(pairs("n")).alias("s"), F.sum("n").alias("t"))
    j = both.join(side(a), "person_id").join(side(b), "person_id")
    expect = F.try_divide(F.col(f"s_{a}") * F.col(f"s_{b}"), F.col("t") * (F.col("t") - 1) / 2)
    return j.select("person_id", F.coalesce(F.try_divide(F.col("s") - expect, (F.col(f"s_{a}") + F.col(f"s_{b}")) / 2 - expect), F.lit(1.0)).alias("agreement"))


def place_agreement(spark, sf_dir) -> DataFrame:
    """Mean agreement of found places with the places the fixture was made from."""
    points = V.point_events(spark, sf_dir)
    found = location.significant_places(location.label_motion(points).select("person_id", "us", "lat", "lon", "pl", "moving")).where("place >= 0")
    return pair_agreement(found, "place", "pl").agg(F.count("*").alias("persons"), F.avg("agreement").alias("agreement"))


def home_error(spark, sf_dir) -> DataFrame:
    """Mean distance in metres of found homes to the fixture's place that the person's static nights were mostly spent at."""
    points = V.point_events(spark, sf_dir)
    night = location.label_motion(location.dwell(points).where(epoch_of(F.col("us")) == "night")).where("not moving")
    true = night.groupBy("person_id", "pl").agg(F.count("*").alias("n")).groupBy("person_id").agg(F.max_by("pl", F.struct("n", -F.col("pl"))).alias("pl"))
    both = location.home_location(points).join(true, "person_id")
    m = haversine_km(F.col("home_lat"), F.col("home_lon"), 40 + 0.02 * F.floor(F.col("pl") / 5), -80 + 0.02 * (F.col("pl") % 5)) * 1000
    return both.agg(F.count("*").alias("persons"), F.count_if(m < 100).alias("right"), F.median(m).alias("median_error_m"))


def cells_agreement(spark, sf_dir, cells_m: float = 10.0) -> DataFrame:
    """How much of the exact clustering the one on cells of samples keeps: share of samples with the same place or none, and agreement of the groups."""
    points = location.label_motion(V.point_events(spark, sf_dir)).select("person_id", "us", "lat", "lon", "moving")
    exact = location.significant_places(points).where("not moving").select("person_id", "us", F.col("place").alias("exact"))
    cells = location.significant_places(points, cells_m=cells_m).where("not moving").select("person_id", "us", F.col("place").alias("cells"))
    both = exact.join(cells, ["person_id", "us"])
    noise = both.agg(F.count("*").alias("samples"), F.avg(((F.col("exact") < 0) == (F.col("cells") < 0)).cast("double")).alias("same_noise"))
    return noise.crossJoin(pair_agreement(both, "exact", "cells").agg(F.avg("agreement").alias("agreement")))


def cluster_sse(scores: DataFrame, label: str) -> DataFrame:
    w = Window.partitionBy("person_id", label)
    return scores.withColumn("_c", F.avg("score").over(w)).groupBy("person_id").agg(F.sum((F.col("score") - F.col("_c")) ** 2).alias("sse"))


def _nodes(plan):
    """The operators of an executed plan, those inside query stages included."""
    name = plan.getClass().getSimpleName()
    inner = plan.executedPlan() if name == "AdaptiveSparkPlanExec" else plan.plan() if name.endswith("QueryStageExec") else None
    yield name, plan
    if inner is not None:
        yield from _nodes(inner)
    children = plan.children()
    for i in range(children.size()):
        yield from _nodes(children.apply(i))


def measured(frame: DataFrame) -> dict[str, float]:
    """Seconds, rows, rows a second, exchanges and bytes shuffled of a plan as it ran."""
    began = time.time()
    execution = frame._jdf.queryExecution()
    rows = execution.executedPlan().execute().count()
    took = time.time() - began
    exchanges = [p for n, p in _nodes(execution.executedPlan()) if n == "ShuffleExchangeExec"]
    written = sum(p.metrics().apply("shuffleBytesWritten").value() for p in exchanges)
    return {"seconds": took, "rows": rows, "rows_per_second": rows / max(took, 1e-9), "exchanges": len(exchanges), "shuffle_bytes": written}


def costs(spark, sf_dir, asked: dict) -> DataFrame:
    """The measures of each of `asked` (name to a callable of (spark, sf_dir)), one row each."""
    found = [(name, *measured(run(spark, sf_dir)).values()) for name, run in asked.items()]
    return spark.createDataFrame(found, "name string, seconds double, rows bigint, rows_per_second double, exchanges int, shuffle_bytes bigint")
