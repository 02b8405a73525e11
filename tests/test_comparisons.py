"""Comparisons of two ways to one result: values on a rounding point, and plans."""

from pyspark.sql import functions as F

from kinetrace.operators import baselines, change, location
from kinetrace.sources import views

SF = "/root/testdata/sf0.001"


def test_equal_slopes_on_a_rounding_point(spark, monkeypatch):
    """What both ways give for one supplier of sf0.1: a slope of 15/64, missed by parts of 1e-14, one of them below the rounding point at five digits."""
    names = "person_id bigint, feature string, breakpoint int, slope_before double, slope_after double"
    for way, slope in (("breakpoints", 0.23437499999998174), ("breakpoints_naive", 0.23437500000000194)):
        rows = spark.createDataFrame([(208, "lines", 1315, slope, -0.0008763993462074989)], names)
        monkeypatch.setattr(change, way, lambda *_, rows=rows: rows)
    assert baselines.break_difference(spark, SF).first().differing == 0


def test_rows_that_differ(spark):
    a = spark.createDataFrame([(1, 7, 1.0), (2, 7, None), (3, 7, 1.0), (4, 7, 5e9), (5, 7, 1.0)], "person_id int, week int, x double")
    b = spark.createDataFrame([(1, 7, 1.0 + 1e-9), (2, 7, None), (3, 8, 1.0), (4, 7, 5e9 + 1), (6, 7, None)], "person_id int, week int, x double")
    found = lambda rows_a, rows_b: baselines._apart(rows_a, rows_b, ["person_id"]).first().differing
    assert found(a, a) == 0 and found(a, b) == 2 + 1 + 1
    assert found(a.where("person_id = 2"), b.where("person_id = 2").withColumn("x", F.lit(0.0))) == 2
    assert found(a.limit(0), b.limit(0)) == 0


def plan(frame):
    return frame._jdf.queryExecution().executedPlan().toString()


def test_neighbours_broadcast_nothing(spark):
    """Copies of samples for 27 cubes each, or all samples, don't fit a driver, whatever size Spark expects of the file."""
    points = views.point_events(spark, SF)
    for frame in (location.neighbours_by_grid(points), baselines.neighbours_naive(points)):
        assert "Broadcast" not in plan(frame)
    assert baselines._differing(location.neighbours_by_grid(points), baselines.neighbours_naive(points)).first().differing == 0


def test_phases_are_not_broadcast(spark):
    """Phases of every person and period don't fit a driver."""
    points = views.point_events(spark, SF)
    assert "Broadcast" not in plan(baselines.periodogram_direct(points, [6.0, 24.0, 48.0]))
    assert baselines.circadian_difference(spark, SF).first().differing == 0
