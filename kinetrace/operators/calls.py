"""Communication: counts and durations of calls by direction and by the correspondent's category."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kinetrace.plans.slices import KEYS, SliceSpec, attach, part_of

DIRECTIONS, CATEGORIES = ("incoming", "outgoing", "missed"), ("family", "friend_off", "friend_on")


def call_features(calls: DataFrame, contacts: DataFrame, spec: SliceSpec | None = None, categories: tuple[str, ...] = CATEGORIES, missed_duration: bool = True) -> DataFrame:
    """Number and duration for everyone and each category, and correspondents overall and by category.

    Calls are summed by correspondent and part of a day before they meet contacts and slices; correspondents are rows of the next
    aggregation, so the last counts them without distinct sets.
    """
    sums = {f"n_{d}": F.count_if(F.col("direction") == d) for d in DIRECTIONS}
    sums |= {f"s_{d}": F.sum(F.when((F.col("direction") == d) & F.lit(missed_duration or d != "missed"), F.col("duration_s")).otherwise(0.0)) for d in DIRECTIONS}
    parts = calls.groupBy("person_id", "correspondent", part_of()).agg(*(e.alias(n) for n, e in sums.items()))
    cells = attach(parts.join(contacts, ["person_id", "correspondent"], "left"), spec or SliceSpec())
    first = cells.groupBy("person_id", *KEYS, "correspondent", "category").agg(*(F.sum(n).alias(n) for n in sums))
    total = []
    for group in ("all", *categories):
        mine = F.lit(True) if group == "all" else F.coalesce(F.col("category") == group, F.lit(False))
        for d in DIRECTIONS:
            total.append(F.sum(F.when(mine, F.col(f"n_{d}")).otherwise(0)).alias(f"n_{d}_{group}"))
            total.append(F.sum(F.when(mine, F.col(f"s_{d}")).otherwise(0.0)).alias(f"s_{d}_{group}"))
        total.append(F.count_if(mine).alias(f"people_{group}"))
    return first.groupBy("person_id", *KEYS).agg(*total)
