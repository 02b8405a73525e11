"""The catalogue of features, the long table of their values, and wide selections."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from fnmatch import fnmatch

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kinetrace.functions.timeparts import DAY, day_of, hour_of
from kinetrace.operators import calls, location, phone, places, proximity, sleep, steps
from kinetrace.plans.slices import KEYS, SliceSpec, attach, rolled_up
from kinetrace.sources import views as V


@dataclass(frozen=True)
class Part:
    """Features that one plan gives, in columns: of a slice, or of a slice and a group (owner of devices, type of place, state of sleep)."""

    build: Callable
    names: tuple[str, ...]
    group: str | None = None
    groups: tuple[str, ...] = ()
    prefix: str = ""

    def features(self) -> list[str]:
        return [f"{g}.{n}" for g in self.groups for n in self.names] if self.group else [f"{self.prefix}{n}" for n in self.names]


def _spaces(s, d) -> DataFrame:
    return places.label_spaces(V.point_events(s, d), V.places(s, d))


def _study(s, d, spec) -> DataFrame:
    found = places.study_intervals(places.space_bouts(_spaces(s, d)), steps.five_minute_bins(V.step_events(s, d)), phone.interaction_bouts(V.screen_events(s, d)))
    return places.total_minutes(found, "study", spec)


def _social(s, d, spec) -> DataFrame:
    return places.total_minutes(places.social_bouts(places.space_bouts(_spaces(s, d)), V.voice_events(s, d)), "social", spec)


def _sleep_bouts(s, d, spec) -> DataFrame:
    return sleep.bouts_in_slices(V.sleep_events(s, d), spec)


def _extremes(s, d, spec) -> DataFrame:
    """Times in minutes since the study's first day."""
    found = sleep.extreme_bouts(_sleep_bouts(s, d, spec))
    return found.select(*(((F.col(c) - spec.origin * DAY) / 60e6).alias(c) if c.endswith(("_start", "_end")) else c for c in found.columns))


BOUT = ("max", "min", "mean")
PLACE = (
    "places", "transitions", "gyration_km", "top1_minutes", "top2_minutes", "top3_minutes", "moving_share", "rare_share", "stay_max", "stay_min", "stay_mean", "stay_std", "entropy", "normalised_entropy",
)
CALLS = tuple(f"{k}_{d}_{g}" for g in ("all", *calls.CATEGORIES) for d in calls.DIRECTIONS for k in ("n", "s")) + tuple(f"people_{g}" for g in ("all", *calls.CATEGORIES))
#: All features by sensor. What isn't asked for is never planned.
CATALOGUE: dict[str, list[Part]] = {
    "proximity": [Part(lambda s, d, x: proximity.scan_features(V.scan_events(s, d), x), ("devices", "most", "least", "total", "mean", "std"), "owners", proximity.GROUPS)],
    "calls": [Part(lambda s, d, x: calls.call_features(V.call_events(s, d), V.contacts_of(V.call_events(s, d)), x), CALLS)],
    "location": [
        Part(lambda s, d, x: location.mobility_basic(V.point_events(s, d), x), ("variance", "log_variance", "distance_km", "speed_mean", "speed_variance")),
        Part(lambda s, d, x: location.circadian(V.point_events(s, d), x), ("circadian",)),
        Part(lambda s, d, x: location.place_features(V.point_events(s, d), x), PLACE),
        Part(lambda s, d, x: location.place_features(V.point_events(s, d), x, "local"), PLACE, prefix="local_"),
        Part(lambda s, d, x: location.home_features(V.point_events(s, d), x), ("home_10m", "home_100m")),
    ],
    "places": [
        Part(lambda s, d, x: places.space_minutes(_spaces(s, d), x), ("minutes", "share"), "type", tuple(V.TYPES)),
        Part(lambda s, d, x: places.bout_features(places.space_bouts(_spaces(s, d)), x), ("bouts", "bouts_10", "bouts_20", "bouts_30", "shortest", "longest", "mean", "std"), "type", tuple(V.TYPES)),
        Part(lambda s, d, x: places.space_transitions(_spaces(s, d), x), ("transitions",)),
        Part(_study, ("study",)),
        Part(_social, ("social",)),
    ],
    "phone": [
        Part(lambda s, d, x: phone.phone_features(V.screen_events(s, d), x), ("unlocks", "unlocks_per_minute", *(f"{k}_{m}" for k in phone.KINDS for m in ("total", *BOUT, "std")))),
        Part(lambda s, d, x: phone.first_last_hours(V.screen_events(s, d), x), ("first_unlock", "first_on", "last_unlock", "last_lock", "last_on")),
    ],
    "sleep": [
        Part(lambda s, d, x: sleep.counts_efficiency(V.sleep_events(s, d), x), ("asleep", "restless", "awake", "unknown", "weak_efficiency", "strong_efficiency")),
        Part(lambda s, d, x: sleep.bout_stats(_sleep_bouts(s, d, x)), ("bouts", "total", "mean", "longest", "shortest"), "state", sleep.STATES),
        Part(_extremes, ("longest_start", "longest_end", "shortest_start", "shortest_end"), "state", sleep.STATES),
    ],
    "steps": [Part(lambda s, d, x: steps.step_features(V.step_events(s, d), x), ("total", "max5", *(f"{k}_{m}" for k in ("active", "sedentary") for m in ("bouts", *BOUT)), "steps_min", "steps_max", "steps_mean"))],
}
#: Change values of each series, and what may be crossed with each span.
CHANGES, EPOCH_KINDS, DAY_KINDS = ("slope", "slope_first", "slope_second", "breakpoint", "slope_before", "slope_after"), 5, 3


def features() -> list[str]:
    """Every feature of the catalogue as "sensor.feature"."""
    return [f"{sensor}.{f}" for sensor, parts in CATALOGUE.items() for part in parts for f in part.features()]


def slice_counts(rows: DataFrame, spec: SliceSpec) -> DataFrame:
    return attach(rows, spec).groupBy("person_id", *KEYS).agg(F.count("*").alias("n"))


def slice_rollup(rows: DataFrame, spec: SliceSpec) -> DataFrame:
    """Counts and sums of all slices from partials of six hours."""
    quarter = F.floor(hour_of(F.col("us")) / 6)
    partials = rows.groupBy("person_id", day_of(F.col("us")).alias("day"), quarter.alias("quarter")).agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    return rolled_up(partials, ["n", "total"], spec)


def select(patterns: list[str]) -> list[tuple[str, Part, list[str]]]:
    """(sensor, part, its features) of all whose "sensor.feature" matches a pattern."""
    found = [(sensor, part, [f for f in part.features() if any(fnmatch(f"{sensor}.{f}", p) for p in patterns)]) for sensor, parts in CATALOGUE.items() for part in parts]
    return [x for x in found if x[2]]


def feature_long(spark, sf_dir, patterns: tuple[str, ...] = ("*",), spec: SliceSpec | None = None) -> DataFrame:
    """person_id, sensor, feature, slice keys, value of every selected feature; null values are left out."""
    out = None
    for sensor, part, wanted in select([*patterns]):
        ids = ["person_id", *KEYS, *([part.group] if part.group else [])]
        names = [n for n in part.names if any(f == f"{part.prefix}{n}" or f.endswith(f".{n}") for f in wanted)]
        rows = part.build(spark, sf_dir, spec or SliceSpec()).select(*ids, *(F.col(n).cast("double").alias(n) for n in names)).unpivot(ids, names, "_name", "value")
        name = F.concat_ws(".", part.group, "_name") if part.group else F.concat(F.lit(part.prefix), F.col("_name"))
        rows = rows.where("value is not null").select("person_id", F.lit(sensor).alias("sensor"), name.alias("feature"), *KEYS, "value")
        rows = rows.where(F.col("feature").isin(wanted)) if len(wanted) < len(part.features()) else rows
        out = rows if out is None else out.union(rows)
    if out is None:
        raise ValueError(f"no feature matches {patterns}")
    return out


def to_wide(long: DataFrame, names: list[str]) -> DataFrame:
    """A column for each of `names` ("sensor.feature", dots and all), a row for each person."""
    return long.withColumn("_f", F.concat_ws(".", "sensor", "feature")).groupBy("person_id").pivot("_f", names).agg(F.first("value"))


#: A selection over all sensors.
WIDE = (
    "steps.total", "steps.max5", "phone.unlocks", "phone.interaction_total", "sleep.asleep", "sleep.asleep.longest", "calls.n_incoming_all", "calls.people_family", "proximity.self.devices", "proximity.others.total",
    "location.distance_km", "location.entropy", "location.local_places", "location.home_100m", "places.academic.minutes", "places.green.bouts_30", "places.study", "places.social",
)


def feature_wide(spark, sf_dir) -> DataFrame:
    wide = to_wide(feature_long(spark, sf_dir, WIDE, SliceSpec(epochs=False)), [*WIDE])
    return wide.select("person_id", *(F.col(f"`{n}`").alias(n.replace(".", "_")) for n in WIDE))


def weekly_features(spark, sf_dir) -> DataFrame:
    """Every catalogue feature by week, as the change layer takes it."""
    long = feature_long(spark, sf_dir, ("*",), SliceSpec.weekly())
    return long.select("person_id", F.concat_ws(".", "sensor", "feature").alias("feature"), F.col("span_id").alias("week"), "value")


def by_segment(spark, sf_dir) -> DataFrame:
    """Steps by the persons' segment: aggregated by person before the join."""
    mine = V.step_events(spark, sf_dir).groupBy("person_id").agg(F.sum("steps").alias("steps"))
    return mine.join(V.person_dim(spark, sf_dir), "person_id").groupBy("segment").agg(F.count("*").alias("persons"), F.sum("steps").alias("total"))


def catalogue_count(spark, sf_dir) -> DataFrame:
    """Features of the catalogue by sensor, and the values that all slices (weeks of the data, halves, all) and the change of each give."""
    weeks = F.floor((day_of(F.max("us")) + 3) / 7) - F.floor((day_of(F.min("us")) + 3) / 7) + 1
    sizes = spark.createDataFrame([(sensor, sum(len(p.features()) for p in parts)) for sensor, parts in CATALOGUE.items()], "sensor string, features int")
    span = V.events(spark, sf_dir).agg(weeks.alias("weeks"))
    return sizes.join(F.broadcast(span)).select("sensor", "features", "weeks", (F.col("features") * EPOCH_KINDS * DAY_KINDS * (F.col("weeks") + 3 + len(CHANGES))).alias("values_total"))
