"""Sleep from inferred states: counts, efficiencies and bouts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kinetrace.plans.bouts import numbered_runs, runs, runs_in_slices
from kinetrace.plans.slices import KEYS, SliceSpec, attach, part_of

STATES, PERIOD_US = ("asleep", "restless", "awake"), 60_000_000


def counts_efficiency(samples: DataFrame, spec: SliceSpec | None = None) -> DataFrame:
    """Samples of each state; weak efficiency counts restless as sleep, strong doesn't; null without a rated sample."""
    kinds = (*STATES, "unknown")
    parts = samples.groupBy("person_id", part_of()).agg(*(F.count_if(F.col("state") == s).alias(s) for s in kinds))
    rows = attach(parts, spec or SliceSpec()).groupBy("person_id", *KEYS).agg(*(F.sum(s).alias(s) for s in kinds))
    rated = F.col("asleep") + F.col("restless") + F.col("awake")
    return rows.withColumn("weak_efficiency", F.try_divide(F.col("asleep") + F.col("restless"), rated)).withColumn("strong_efficiency", F.try_divide(F.col("asleep"), rated))


def sleep_bouts(samples: DataFrame, period_us: int = PERIOD_US, max_gap_us: int | None = None) -> DataFrame:
    """person_id, state, start_us, end_us, minutes of each run; a run lasts as many periods as it has samples."""
    found = runs(samples, "state", max_gap_us)
    return found.select("person_id", "state", F.col("first_us").alias("start_us"), (F.col("last_us") + period_us).alias("end_us"), (F.col("n") * period_us / 60e6).alias("minutes"))


def bouts_in_slices(samples: DataFrame, spec: SliceSpec | None = None, period_us: int = PERIOD_US, max_gap_us: int | None = None) -> DataFrame:
    """The bouts of rated states, cut at the borders of each slice: person_id, slice keys, state, start_us, end_us, minutes."""
    numbered = numbered_runs(samples, "state", max_gap_us).where(F.col("state").isin(*STATES))
    found = runs_in_slices(numbered, "state", spec or SliceSpec())
    return found.select("person_id", *KEYS, "state", F.col("first_us").alias("start_us"), (F.col("last_us") + period_us).alias("end_us"), (F.col("n") * period_us / 60e6).alias("minutes"))


def bout_stats(bouts: DataFrame) -> DataFrame:
    """Count, sum, mean, max, min of bout length by state; `bouts`: in slices."""
    m = F.col("minutes")
    return bouts.groupBy("person_id", *KEYS, "state").agg(F.count("*").alias("bouts"), F.sum(m).alias("total"), F.avg(m).alias("mean"), F.max(m).alias("longest"), F.min(m).alias("shortest"))


def extreme_bouts(bouts: DataFrame) -> DataFrame:
    """Start and end of the longest and of the shortest bout by state; the earliest of equals. `bouts`: in slices."""
    when = F.struct("start_us", "end_us")
    best = bouts.groupBy("person_id", *KEYS, "state").agg(F.max_by(when, F.struct("minutes", -F.col("start_us"))).alias("l"), F.min_by(when, F.struct("minutes", "start_us")).alias("s"))
    return best.select("person_id", *KEYS, "state", F.col("l.start_us").alias("longest_start"), F.col("l.end_us").alias("longest_end"), F.col("s.start_us").alias("shortest_start"), F.col("s.end_us").alias("shortest_end"))
