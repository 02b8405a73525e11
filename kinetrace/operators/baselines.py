"""Plainer ways to the same results, and the number of rows in which they differ."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kinetrace.functions.geo import haversine_km
from kinetrace.operators import assemble, change, location, phone, places, steps
from kinetrace.plans.slices import KEYS, SliceSpec, attach
from kinetrace.sources import views as V


def _differing(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.exceptAll(b).union(b.exceptAll(a)).agg(F.count("*").alias("differing"))


def _round(frame: DataFrame, digits: int = 5) -> DataFrame:
    return frame.select(*(F.round(c, digits).alias(c) if t == "double" else F.col(c).cast("bigint").alias(c) if t in ("int", "bigint") else F.col(c) for c, t in frame.dtypes))


def _apart(a: DataFrame, b: DataFrame, keys: list[str], tolerance: float = 1e-6) -> DataFrame:
    """Rows of both sides that have none with their keys on the other side, or one with other values. Doubles are the same up to the tolerance
    (of their size, if above 1), since rounding parts equal values that lie on a rounding point, such as 0.234375 at five digits."""

    def same(c: str, kind: str):
        x, y = F.col(f"a.{c}"), F.col(f"b.{c}")
        if kind != "double":
            return x.eqNullSafe(y)
        return x.eqNullSafe(y) | F.coalesce(F.abs(x - y) <= tolerance * F.greatest(F.lit(1.0), F.abs(x), F.abs(y)), F.lit(False))

    both = F.lit(True)
    for c, kind in a.dtypes:
        if c not in keys:
            both = both & same(c, kind)
    left, right = a.withColumn("_in", F.lit(1)).alias("a"), b.withColumn("_in", F.lit(1)).alias("b")
    on = F.lit(True)
    for k in keys:
        on = on & (F.col(f"a.{k}") == F.col(f"b.{k}"))
    sides = F.coalesce(F.col("a._in"), F.lit(0)) + F.coalesce(F.col("b._in"), F.lit(0))
    rows = left.join(right, on, "full").select(F.when((sides == 2) & both, 0).otherwise(sides).alias("n"))
    return rows.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("differing"))


def neighbours_naive(points: DataFrame, eps_m: float = location.EPS_M) -> DataFrame:
    """All pairs of a person's samples: quadratic."""
    b = points.select("person_id", F.col("us").alias("us2"), F.col("lat").alias("lat2"), F.col("lon").alias("lon2"))
    near = points.join(b.hint("merge"), "person_id").where(haversine_km(F.col("lat"), F.col("lon"), F.col("lat2"), F.col("lon2")) * 1000 <= eps_m)
    return near.groupBy("person_id", "us").agg(F.count("*").alias("n"))


def dbscan_difference(spark, sf_dir) -> DataFrame:
    """Places from cubes against places from all distances, and neighbours by cubes against all pairs."""
    points = location.label_motion(V.point_events(spark, sf_dir)).select("person_id", "us", "lat", "lon", "moving")
    cells, whole = (location.significant_places(points, dense=n).select("person_id", "us", "place") for n in (0, 1 << 30))
    static = points.where("not moving")
    near = _differing(location.neighbours_by_grid(static), neighbours_naive(static))
    return _differing(cells, whole).union(near).agg(F.sum("differing").alias("differing"), F.lit(points.count()).alias("samples"))


def break_difference(spark, sf_dir) -> DataFrame:
    weekly = V.weekly_lines(spark, sf_dir)
    names = ["person_id", "feature", "breakpoint", "slope_before", "slope_after"]
    return _apart(change.breakpoints(weekly, "free").select(*names), change.breakpoints_naive(weekly).select(*names), names[:2])


def slices_difference(spark, sf_dir) -> DataFrame:
    """Partials rolled up against one aggregation for each span over all rows."""
    rows, spec = V.events(spark, sf_dir), SliceSpec.crossed()
    naive = None
    for span in spec.spans:
        one = attach(rows, SliceSpec((span,), True, True)).groupBy("person_id", *KEYS).agg(F.count("*").alias("n"), F.sum("value").alias("total"))
        naive = one if naive is None else naive.union(one)
    return _differing(_round(assemble.slice_rollup(rows, spec)), _round(naive))


def study(spark, sf_dir, spec: SliceSpec | None = None) -> DataFrame:
    spaces = places.space_bouts(places.label_spaces(V.point_events(spark, sf_dir), V.places(spark, sf_dir)))
    found = places.study_intervals(spaces, steps.five_minute_bins(V.step_events(spark, sf_dir)), phone.interaction_bouts(V.screen_events(spark, sf_dir)))
    return places.total_minutes(found, "study", spec)


def social_naive(bouts: DataFrame, voice: DataFrame, min_minutes: float = 20, min_share: float = 0.8) -> DataFrame:
    """Bouts meet all of a person's voice samples: a join on bounds only."""
    b = bouts.where(F.col("type").isin("apartment", "residence", "green") & (F.col("minutes") >= min_minutes)).select(F.col("person_id").alias("p"), "start_us", "end_us", "minutes")
    both = b.join(voice, (F.col("p") == F.col("person_id")) & (F.col("us") >= F.col("start_us")) & (F.col("us") < F.col("end_us")))
    rows = both.groupBy("person_id", "start_us", "end_us", "minutes").agg(F.avg(F.col("inference").isin("voice", "noise").cast("double")).alias("voiced"))
    return rows.where(F.col("voiced") >= min_share)


def study_naive(bouts: DataFrame, bins: DataFrame, interaction: DataFrame, min_minutes: float = 30, max_steps: int = steps.FEW) -> DataFrame:
    """Every stretch between two borders meets all of a person's intervals, by joins on bounds only; good stretches that touch are joined."""
    at = bouts.where("type = 'academic'").select("person_id", "start_us", "end_us")
    bad = interaction.select("person_id", "start_us", "end_us").union(bins.where(F.col("steps") >= max_steps).select("person_id", F.col("us").alias("start_us"), (F.col("us") + steps.BIN_US).alias("end_us")))
    times = at.union(bad).select("person_id", F.explode(F.array("start_us", "end_us")).alias("us")).distinct()
    parts = times.withColumn("to", F.lead("us").over(Window.partitionBy("person_id").orderBy("us"))).where("to is not null")
    hits = lambda x, n: x.select(F.col("person_id").alias(f"p{n}"), F.col("start_us").alias(f"s{n}"), F.col("end_us").alias(f"e{n}"))
    good = parts.join(hits(at, 1), (F.col("person_id") == F.col("p1")) & (F.col("s1") <= F.col("us")) & (F.col("to") <= F.col("e1")), "left_semi")
    good = good.join(hits(bad, 2), (F.col("person_id") == F.col("p2")) & (F.col("s2") < F.col("to")) & (F.col("us") < F.col("e2")), "left_anti")
    w = Window.partitionBy("person_id").orderBy("us")
    joined = good.withColumn("new", (~F.col("us").eqNullSafe(F.lag("to").over(w))).cast("int")).withColumn("run", F.sum("new").over(w))
    found = joined.groupBy("person_id", "run").agg(F.min("us").alias("start_us"), F.max("to").alias("end_us")).drop("run")
    return found.withColumn("minutes", (F.col("end_us") - F.col("start_us")) / 60e6).where(F.col("minutes") >= min_minutes)


def interval_difference(spark, sf_dir) -> DataFrame:
    """Social bouts and study intervals by buckets and by one sweep, against joins on bounds."""
    bouts, voice = places.space_bouts(places.label_spaces(V.point_events(spark, sf_dir), V.places(spark, sf_dir))), V.voice_events(spark, sf_dir)
    bins, interaction = steps.five_minute_bins(V.step_events(spark, sf_dir)), phone.interaction_bouts(V.screen_events(spark, sf_dir))
    names = ["person_id", "start_us", "end_us", "minutes"]
    swept = places.study_intervals(bouts, bins, interaction)
    study_rows = _differing(_round(swept.select(*names)), _round(study_naive(bouts, bins, interaction).select(*names)))
    social_rows = _differing(_round(places.social_bouts(bouts, voice)), _round(social_naive(bouts, voice)))
    return study_rows.union(social_rows).agg(F.sum("differing").alias("differing"), F.lit(swept.count()).alias("intervals"))


def periodogram_direct(points: DataFrame, periods: list[float], origin: int = 19723) -> DataFrame:
    """Two passes: the phase first, then the sums with it."""
    w = F.lit(2 * math.pi) * (F.col("us") - origin * 86_400_000_000) / 3.6e9 / F.col("period")
    grid = points.withColumn("period", F.explode(F.array(*map(F.lit, periods)))).withColumn("w", w)
    phase = grid.groupBy("person_id", "period").agg((F.atan2(F.sum(F.sin(2 * F.col("w"))), F.sum(F.cos(2 * F.col("w")))) / 2).alias("tau"), F.avg("lat").alias("mlat"), F.avg("lon").alias("mlon"))
    # A person's phases are joined as one row, before its samples multiply, and never broadcast: they grow with the persons.
    phases = phase.groupBy("person_id").agg(F.collect_list(F.struct("period", "tau", "mlat", "mlon")).alias("phases"))
    r = points.join(phases.hint("merge"), "person_id").select("person_id", "us", "lat", "lon", F.inline("phases")).withColumn("w", w)
    c, s = F.cos(F.col("w") - F.col("tau")), F.sin(F.col("w") - F.col("tau"))
    y, x = F.col("lat") - F.col("mlat"), F.col("lon") - F.col("mlon")
    sums = r.groupBy("person_id", "period").agg(*(F.sum(e).alias(n) for n, e in {"cc": c * c, "ss": s * s, "yc": y * c, "ys": y * s, "xc": x * c, "xs": x * s}.items()))
    safe = F.when(F.col("ss") > 5e-7, F.col("ss"))
    return sums.select("person_id", "period", (((F.col("yc") ** 2 + F.col("xc") ** 2) / F.col("cc") + F.coalesce((F.col("ys") ** 2 + F.col("xs") ** 2) / safe, F.lit(0.0))) / 2).alias("power"))


def circadian_difference(spark, sf_dir) -> DataFrame:
    points = V.point_events(spark, sf_dir)
    periods = sorted({*(round(23.5 + 0.1 * i, 6) for i in range(11)), *(float(h) for h in range(6, 49))})
    fast = location.periodogram(points, periods).select("person_id", "period", "power")
    return _apart(fast, periodogram_direct(points, periods), ["person_id", "period"], 1e-8)


SINGLE_CHANNEL = {"location": ("location.*",), "screen": ("phone.*",), "location_screen": ("location.*", "phone.*")}


def single_channel(spark, sf_dir, name: str, spec: SliceSpec | None = None) -> DataFrame:
    """The features that a study of few channels would have: baseline of the multimodal catalogue."""
    return assemble.feature_long(spark, sf_dir, SINGLE_CHANNEL[name], spec)


def hourly_spectrum(points: DataFrame, periods: list[float], origin: int = 19723) -> DataFrame:
    """Power at each period by a discrete Fourier sum over hourly means, as for regular series: hours without samples are left out."""
    hour = F.floor((F.col("us") - origin * 86_400_000_000) / 3.6e9)
    bins = points.groupBy("person_id", hour.alias("h")).agg(F.avg("lat").alias("lat"), F.avg("lon").alias("lon"))
    whole = Window.partitionBy("person_id")
    flat = bins.select("person_id", "h", (F.col("lat") - F.avg("lat").over(whole)).alias("y"), (F.col("lon") - F.avg("lon").over(whole)).alias("x"))
    grid = flat.withColumn("period", F.explode(F.array(*map(F.lit, periods)))).withColumn("w", F.lit(2 * math.pi) * (F.col("h") + 0.5) / F.col("period"))
    sums = grid.groupBy("person_id", "period").agg(*(F.sum(F.col(v) * f("w")).alias(f"{v}{n}") for v in ("y", "x") for n, f in (("c", F.cos), ("s", F.sin))), F.count("*").alias("n"))
    return sums.select("person_id", "period", ((F.col("yc") ** 2 + F.col("ys") ** 2 + F.col("xc") ** 2 + F.col("xs") ** 2) / F.col("n")).alias("power"))
