"""Temporal slices: spans (full, halves, weeks) by day types by parts of the day."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kinetrace.functions.timeparts import DAY, HOUR, day_of, daytype_of, epoch_of, week_of

KEYS = ["span", "span_id", "daytype", "epoch"]


@dataclass(frozen=True)
class SliceSpec:
    """Which slices to evaluate. origin: first day of the study (days since 1970); days: its length."""

    spans: tuple[str, ...] = ("full",)
    daytypes: bool = False
    epochs: bool = True
    origin: int = 19723
    days: int = 30

    @classmethod
    def crossed(cls) -> SliceSpec:
        """Every span with every day type and part of the day."""
        return cls(("full", "half", "week"), True, True)

    @classmethod
    def weekly(cls) -> SliceSpec:
        return cls(("week",), False, False)


def _ids(at: Column, spec: SliceSpec) -> dict[str, Column]:
    """Number of the span of each kind that a time lies in."""
    half = F.when(day_of(at) - spec.origin < spec.days // 2, 1).otherwise(2)
    return {"full": F.lit(0), "half": half, "week": week_of(at) - (spec.origin + 3) // 7 + 1}


def lies_in(spec: SliceSpec, us: str = "us") -> Column:
    """Whether a time lies in the slice that the row's slice keys name."""
    at = F.col(us)
    same = [(F.col("span") == s) & (F.col("span_id") == _ids(at, spec)[s]) for s in spec.spans]
    span = same[0]
    for x in same[1:]:
        span = span | x
    return span & F.col("daytype").isin("all", daytype_of(at)) & F.col("epoch").isin("allday", epoch_of(at))


def attach(rows: DataFrame, spec: SliceSpec, us: str = "us") -> DataFrame:
    """`rows`, one copy for each slice that holds them, with the slice's keys."""
    at = F.col(us)
    ids = _ids(at, spec)
    spans = F.array(*(F.struct(F.lit(s).alias("span"), ids[s].cast("int").alias("span_id")) for s in spec.spans))
    daytypes = F.array(F.lit("all"), daytype_of(at)) if spec.daytypes else F.array(F.lit("all"))
    epochs = F.array(F.lit("allday"), epoch_of(at)) if spec.epochs else F.array(F.lit("allday"))
    cells = F.flatten(F.flatten(F.transform(spans, lambda s: F.transform(daytypes, lambda d: F.transform(epochs, lambda e: F.struct(s["span"].alias("span"), s["span_id"].alias("span_id"), d.alias("daytype"), e.alias("epoch")))))))
    return rows.withColumn("_cell", F.explode(cells)).select(*rows.columns, *(F.col(f"_cell.{k}").alias(k) for k in KEYS))


def slice_minutes(spec: SliceSpec) -> Column:
    """Nominal minutes of a slice of the default kind: its share of the day times its days."""
    days = F.when(F.col("span") == "full", spec.days).when(F.col("span") == "half", spec.days // 2).otherwise(7)
    share = F.when(F.col("daytype") == "weekday", 5 / 7).when(F.col("daytype") == "weekend", 2 / 7).otherwise(1.0)
    return days * share * F.when(F.col("epoch") == "allday", 1440.0).otherwise(360.0)


def clipped(bouts: DataFrame, start: str = "start_us", end: str = "end_us") -> DataFrame:
    """Intervals cut at the borders of the day's parts, of which all slices consist; `us` and `to_us` bound a piece, `minutes` is its length."""
    step = 6 * HOUR
    first = F.col(start) - F.pmod(F.col(start), F.lit(step))
    pieces = F.sequence(first, F.greatest(F.col(end) - 1, F.col(start)), F.lit(step))
    cut = bouts.withColumn("_from", F.explode(pieces))
    us, to = F.greatest(F.col(start), F.col("_from")), F.least(F.col(end), F.col("_from") + step)
    return cut.withColumns({"us": us, "to_us": to}).withColumn("minutes", (F.col("to_us") - F.col("us")) / 60e6).drop("_from")


def part_of(us: str = "us") -> Column:
    """Start of the part of a day that a time lies in. Slices consist of such parts, so dense samples are aggregated by them before rows multiply by slices."""
    return (F.col(us) - F.pmod(F.col(us), F.lit(6 * HOUR))).alias("us")


def stretch(us: str = "us") -> Column:
    """Number of the unbroken stretch of a slice that a time lies in: a part of a day is one each day, week days and week ends one each week."""
    at = F.col(us)
    return F.when(F.col("epoch") != "allday", F.floor(at / F.lit(6.0 * HOUR))).when(F.col("daytype") != "all", week_of(at)).otherwise(0)


def in_slices(bouts: DataFrame, spec: SliceSpec, extra: tuple[str, ...] = ()) -> DataFrame:
    """Intervals (person_id, start_us, end_us, `extra`) cut at the borders of each slice, and only there: person_id, slice keys, `extra`, start_us, end_us, minutes."""
    given = bouts.select("person_id", *extra, F.col("start_us").alias("_start"), F.col("end_us").alias("_end"))
    cells = attach(clipped(given, "_start", "_end"), spec).withColumn("_stretch", stretch())
    joined = cells.groupBy("person_id", *KEYS, *extra, "_start", "_end", "_stretch").agg(F.min("us").alias("start_us"), F.max("to_us").alias("end_us"), F.sum("minutes").alias("minutes"))
    return joined.drop("_start", "_end", "_stretch")


def time_in_slices(held: DataFrame, spec: SliceSpec) -> DataFrame:
    """Samples (us, minutes that each holds) cut at the borders of the day's parts and put into slices; additive times need no joining."""
    ends = held.withColumn("_end", (F.col("us") + F.round(F.col("minutes") * 60e6)).cast("bigint")).withColumnRenamed("us", "_start").drop("minutes")
    return attach(clipped(ends, "_start", "_end").drop("to_us", "_end"), spec)


def rolled_up(partials: DataFrame, measures: list[str], spec: SliceSpec) -> DataFrame:
    """Slices of additive measures from partials by (person_id, day, epoch): rows multiply after aggregation, not before."""
    cells = attach(partials.withColumn("us", F.col("day") * DAY + F.col("quarter") * 6 * HOUR), spec)
    return cells.groupBy("person_id", *KEYS).agg(*(F.sum(m).alias(m) for m in measures))
