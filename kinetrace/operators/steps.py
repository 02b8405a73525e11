"""Steps: totals, the busiest five minutes, active and sedentary bouts."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kinetrace.plans.bouts import numbered_runs, ordered, runs, runs_in_slices
from kinetrace.plans.slices import KEYS, SliceSpec, attach, part_of

BIN_US, FEW = 300_000_000, 10


def five_minute_bins(steps: DataFrame) -> DataFrame:
    return steps.groupBy("person_id", (F.col("us") - F.pmod(F.col("us"), F.lit(BIN_US))).alias("us")).agg(F.sum("steps").alias("steps"))


def labelled(bins: DataFrame, at_threshold: str = "active", fill: str = "break") -> DataFrame:
    """Bins as sedentary (fewer than ten steps) or active. at_threshold: active, or keep (the state before). fill: zero adds
    empty bins between a person's first and last bin of a day."""
    if fill == "zero":
        day = F.floor(F.col("us") / 86_400_000_000.0)
        full = bins.groupBy("person_id", day.alias("day")).agg(F.min("us").alias("a"), F.max("us").alias("b")).select("person_id", F.explode(F.sequence("a", "b", F.lit(BIN_US))).alias("us"))
        bins = full.join(bins, ["person_id", "us"], "left").withColumn("steps", F.coalesce("steps", F.lit(0)))
    n = F.col("steps")
    if at_threshold == "keep":
        clear = F.when(n < FEW, "sedentary").when(n > FEW, "active")
        label = F.coalesce(F.last(clear, ignorenulls=True).over(ordered().rowsBetween(Window.unboundedPreceding, 0)), F.lit("sedentary"))
    else:
        label = F.when(n < FEW, "sedentary").otherwise("active")
    return bins.withColumn("label", label)


def step_bouts(bins: DataFrame, at_threshold: str = "active", fill: str = "break") -> DataFrame:
    """person_id, label, start_us, end_us, minutes, steps; a missing bin ends a bout."""
    found = runs(labelled(bins, at_threshold, fill), "label", BIN_US, extra=(F.sum("steps").alias("steps"),))
    return found.select("person_id", "label", F.col("first_us").alias("start_us"), (F.col("last_us") + BIN_US).alias("end_us"), (F.col("n") * 5.0).alias("minutes"), "steps")


def totals(steps: DataFrame, spec: SliceSpec | None = None) -> DataFrame:
    """Total steps and the most in a five-minute bin."""
    parts = five_minute_bins(steps).groupBy("person_id", part_of()).agg(F.sum("steps").alias("total"), F.max("steps").alias("max5"))
    return attach(parts, spec or SliceSpec()).groupBy("person_id", *KEYS).agg(F.sum("total").alias("total"), F.max("max5").alias("max5"))


def sliding_max(steps: DataFrame, spec: SliceSpec | None = None) -> DataFrame:
    """The most steps in any five minutes that end with a sample."""
    w = ordered().rangeBetween(-(BIN_US - 1), 0)
    return attach(steps.withColumn("last5", F.sum("steps").over(w)), spec or SliceSpec()).groupBy("person_id", *KEYS).agg(F.max("last5").alias("max5_sliding"))


def bouts_in_slices(bins: DataFrame, spec: SliceSpec | None = None, at_threshold: str = "active", fill: str = "break") -> DataFrame:
    """Bouts cut at the borders of each slice: person_id, slice keys, label, minutes, steps, those of the bins inside."""
    numbered = numbered_runs(labelled(bins, at_threshold, fill), "label", BIN_US)
    found = runs_in_slices(numbered, "label", spec or SliceSpec(), extra=(F.sum("steps").alias("steps"),))
    return found.select("person_id", *KEYS, "label", (F.col("n") * 5.0).alias("minutes"), "steps")


def bout_stats(bouts: DataFrame) -> DataFrame:
    """Number and length of bouts of both kinds and steps of active ones; `bouts`: in slices."""
    out = []
    for label in ("active", "sedentary"):
        m = F.when(F.col("label") == label, F.col("minutes"))
        out += [F.count(m).alias(f"{label}_bouts"), F.max(m).alias(f"{label}_max"), F.min(m).alias(f"{label}_min"), F.avg(m).alias(f"{label}_mean")]
    s = F.when(F.col("label") == "active", F.col("steps"))
    return bouts.groupBy("person_id", *KEYS).agg(*out, F.min(s).alias("steps_min"), F.max(s).alias("steps_max"), F.avg(s).alias("steps_mean"))


def step_features(steps: DataFrame, spec: SliceSpec | None = None) -> DataFrame:
    return totals(steps, spec).join(bout_stats(bouts_in_slices(five_minute_bins(steps), spec)), ["person_id", *KEYS], "left")
