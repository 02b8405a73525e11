"""Bouts: maximal runs of one label in a person's ordered samples."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, WindowSpec
from pyspark.sql import functions as F

from kinetrace.plans.slices import KEYS, SliceSpec, attach, stretch


def ordered() -> WindowSpec:
    """The one window of all per-person sequences, so that they share a shuffle and a sort."""
    return Window.partitionBy("person_id").orderBy("us")


def numbered_runs(rows: DataFrame, label: str, max_gap_us: int | None = None, order: WindowSpec | None = None) -> DataFrame:
    """`rows` with `_run`, the number of the person's run that a row belongs to; a longer gap ends a run."""
    w = order or ordered()
    start = ~F.col(label).eqNullSafe(F.lag(label).over(w)) | F.lag("us").over(w).isNull()
    if max_gap_us is not None:
        start = start | (F.col("us") - F.lag("us").over(w) > max_gap_us)
    flagged = rows.withColumn("_start", start.cast("int"))
    return flagged.withColumn("_run", F.sum("_start").over(w.rowsBetween(Window.unboundedPreceding, 0))).drop("_start")


def runs(rows: DataFrame, label: str, max_gap_us: int | None = None, extra: tuple = (), order: WindowSpec | None = None) -> DataFrame:
    """person_id, label, first_us, last_us, n and `extra` aggregates of each run."""
    numbered = numbered_runs(rows, label, max_gap_us, order)
    return numbered.groupBy("person_id", "_run", label).agg(F.min("us").alias("first_us"), F.max("us").alias("last_us"), F.count("*").alias("n"), *extra).drop("_run")


def runs_in_slices(numbered: DataFrame, label: str, spec: SliceSpec, extra: tuple = ()) -> DataFrame:
    """person_id, slice keys, label, first_us, last_us, n and `extra` of each run as far as it lies in a slice: only its samples there count."""
    cells = attach(numbered, spec).withColumn("_stretch", stretch())
    return cells.groupBy("person_id", *KEYS, "_run", "_stretch", label).agg(F.min("us").alias("first_us"), F.max("us").alias("last_us"), F.count("*").alias("n"), *extra).drop("_run", "_stretch")


def swept(intervals: DataFrame, need: list[str], forbid: list[str]) -> DataFrame:
    """Maximal intervals in which all `need` kinds hold and no `forbid` kind does.

    intervals: person_id, kind, start_us, end_us (half-open). One pass over the border events of each person.
    """
    kinds = [*need, *forbid]
    edges = intervals.where("end_us > start_us").select("person_id", F.explode(F.array(F.struct(F.col("start_us").alias("us"), F.lit(1).alias("d"), "kind"), F.struct(F.col("end_us").alias("us"), F.lit(-1).alias("d"), "kind"))).alias("e")).select("person_id", "e.*")
    steps = edges.groupBy("person_id", "us").agg(*(F.sum(F.when(F.col("kind") == k, F.col("d")).otherwise(0)).alias(k) for k in kinds))
    running = ordered().rowsBetween(Window.unboundedPreceding, 0)
    held = steps.select("person_id", "us", F.lead("us").over(ordered()).alias("to"), *(F.sum(k).over(running).alias(k) for k in kinds))
    ok = F.lit(True)
    for k in need:
        ok = ok & (F.col(k) > 0)
    for k in forbid:
        ok = ok & (F.col(k) == 0)
    marked = held.where("to is not null").select("person_id", "us", "to", ok.alias("ok"))
    found = runs(marked, "ok", extra=(F.max("to").alias("end_us"),))
    return found.where("ok").select("person_id", F.col("first_us").alias("start_us"), "end_us")
