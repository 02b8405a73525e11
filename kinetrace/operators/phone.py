"""Phone use from screen status: bouts of interaction and of the unlocked screen."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kinetrace.functions.timeparts import day_of, hour_of
from kinetrace.plans.bouts import ordered
from kinetrace.plans.slices import KEYS, SliceSpec, attach, in_slices, part_of, slice_minutes


KINDS = {"interaction": ("off", "lock"), "unlocked": ("lock",)}


def bouts(screen: DataFrame, kinds: tuple[str, ...] = tuple(KINDS)) -> DataFrame:
    """person_id, kind, start_us, end_us: from an unlock to the next closing status; a repeated unlock doesn't start anew, an open bout
    ends with the person's last sample. One ordered pass for all kinds: an opening or closing row is a mark, and a bout's end is the mark after it."""
    before = ordered().rowsBetween(Window.unboundedPreceding, -1)
    marks = screen.select("person_id", "us", "status", F.max("us").over(Window.partitionBy("person_id")).alias("last_us"))
    found = None
    for kind in kinds:
        closing = KINDS[kind]
        relevant = F.when(F.col("status").isin("unlock", *closing), F.col("status"))
        marks = marks.withColumn(f"_{kind}", F.last(relevant, ignorenulls=True).over(before))
    for kind in kinds:
        closing, held = KINDS[kind], F.coalesce(F.col(f"_{kind}") == "unlock", F.lit(False))
        opens, closes = (F.col("status") == "unlock") & ~held, F.col("status").isin(*closing) & held
        ends = F.lead("us").over(ordered())
        mine = marks.where(opens | closes).select("person_id", F.lit(kind).alias("kind"), "us", "status", F.coalesce(ends, "last_us").alias("end_us"))
        mine = mine.where("status = 'unlock'").select("person_id", "kind", F.col("us").alias("start_us"), "end_us")
        found = mine if found is None else found.union(mine)
    return found


def interaction_bouts(screen: DataFrame) -> DataFrame:
    return bouts(screen, ("interaction",)).drop("kind")


def unlocked_bouts(screen: DataFrame) -> DataFrame:
    return bouts(screen, ("unlocked",)).drop("kind")


def phone_features(screen: DataFrame, spec: SliceSpec | None = None) -> DataFrame:
    """Unlocks per minute of the slice, total and statistics of both kinds of bout, cut at the slice's borders."""
    spec = spec or SliceSpec()
    parts = screen.groupBy("person_id", part_of()).agg(F.count_if(F.col("status") == "unlock").alias("unlocks"))
    counts = attach(parts, spec).groupBy("person_id", *KEYS).agg(F.sum("unlocks").alias("unlocks"))
    rate = counts.select("person_id", *KEYS, "unlocks", (F.col("unlocks") / slice_minutes(spec)).alias("unlocks_per_minute"))
    stats = []
    for kind in KINDS:
        m = F.when(F.col("kind") == kind, F.col("minutes"))
        stats += [F.sum(m).alias(f"{kind}_total"), F.max(m).alias(f"{kind}_max"), F.min(m).alias(f"{kind}_min"), F.avg(m).alias(f"{kind}_mean"), F.stddev_pop(m).alias(f"{kind}_std")]
    lengths = in_slices(bouts(screen), spec, ("kind",)).groupBy("person_id", *KEYS).agg(*stats)
    return rate.join(lengths, ["person_id", *KEYS], "left")


def first_last_hours(screen: DataFrame, spec: SliceSpec | None = None) -> DataFrame:
    """Hours of the first unlock and screen-on and of the last unlock, lock and screen-on; the mean over a slice's days."""
    at = lambda s: F.when(F.col("status") == s, hour_of(F.col("us")))
    asked = [("first", "unlock", F.min), ("first", "on", F.min), ("last", "unlock", F.max), ("last", "lock", F.max), ("last", "on", F.max)]
    parts = screen.groupBy("person_id", part_of()).agg(*(f(at(s)).alias(f"{when}_{s}") for when, s, f in asked))
    daily = attach(parts, spec or SliceSpec()).groupBy("person_id", *KEYS, day_of(F.col("us")).alias("day"))
    days = daily.agg(*(f(f"{when}_{s}").alias(f"{when}_{s}") for when, s, f in asked))
    return days.groupBy("person_id", *KEYS).agg(*(F.avg(f"{when}_{s}").alias(f"{when}_{s}") for when, s, _ in asked))
