"""Parts of local wall-clock time as integer arithmetic on microseconds, the same in every engine and time zone."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

HOUR, DAY = 3_600_000_000, 86_400_000_000
EPOCHS = ["night", "morning", "afternoon", "evening"]  # 0-6, 6-12, 12-18, 18-24


def micros(ts: str | Column) -> Column:
    """Microseconds since 1970 of a timestamp without zone."""
    name = ts if isinstance(ts, str) else None
    column = F.col(name) if name else ts
    return F.timestamp_diff("MICROSECOND", F.lit("1970-01-01 00:00:00").cast("timestamp_ntz"), column.cast("timestamp_ntz"))


def div(a: Column, b: int) -> Column:
    return F.floor(a / F.lit(float(b))).cast("bigint") if b < 1 << 20 else ((a - F.pmod(a, F.lit(b))) / F.lit(b)).cast("bigint")


def day_of(us: Column) -> Column:
    return div(us, DAY)


def hour_of(us: Column) -> Column:
    return F.pmod(div(us, HOUR), F.lit(24)).cast("int")


def epoch_of(us: Column) -> Column:
    return F.element_at(F.array(*map(F.lit, EPOCHS)), F.floor(hour_of(us) / 6).cast("int") + 1)


def week_of(us: Column) -> Column:
    """Weeks begin on Monday; 1970-01-01 was a Thursday."""
    return F.floor((day_of(us) + 3) / 7).cast("int")


def daytype_of(us: Column) -> Column:
    return F.when(F.pmod(day_of(us) + 3, F.lit(7)) >= 5, "weekend").otherwise("weekday")
