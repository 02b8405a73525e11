"""Variants of the methods and what they cost or gain, as queries: (name, columns, query, SQL body or None)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kinetrace.operators import calls, change, places, proximity, steps
from kinetrace.operators.feature_queries import CALL_SQL, FREE, _sliced
from kinetrace.oracles import sets as Q
from kinetrace.plans.slices import KEYS, SliceSpec, attach, in_slices
from kinetrace.sources import views as V

PERSON_FEATURE = ["person_id", "feature"]


def line_bic(weekly: DataFrame, min_weeks: int = 3) -> DataFrame:
    """BIC of one straight line through a series: the baseline of the two-piece model. One pass."""
    x, y = F.col("week").cast("double"), F.col("value")
    sums = change.numbered(weekly).groupBy(*PERSON_FEATURE).agg(F.count("*").alias("n"), F.regr_syy(y, x).alias("syy"), F.coalesce(F.regr_slope(y, x) * F.regr_sxy(y, x), F.lit(0.0)).alias("explained")).where(F.col("n") >= min_weeks)
    value = change.bic(F.greatest(F.col("syy") - F.col("explained"), F.lit(0.0)), F.col("n"), F.lit(2), 1e-12 * (1 + F.col("syy")))
    return sums.select(*PERSON_FEATURE, F.round(value, 6).alias("bic_line"))


def line_against_break(weekly: DataFrame, pieces: str = "free") -> DataFrame:
    """Series for which the break model has the smaller BIC, and those for which one line has it."""
    both = line_bic(weekly).join(change.breakpoints(weekly, pieces).select(*PERSON_FEATURE, "bic"), PERSON_FEATURE)
    return both.groupBy("feature").agg(F.count("*").alias("series"), F.count_if(F.col("bic") < F.col("bic_line") - 1e-5).alias("breaks"))


def planted(weekly: DataFrame) -> DataFrame:
    """person_id, feature, week, value, bend: a line that bends at a known week of a person's own observed weeks, with a steady noise of up to 5."""
    weeks = weekly.select("person_id", "week").distinct()
    bend = weeks.groupBy("person_id").agg(F.expr("percentile_disc(0.4) WITHIN GROUP (ORDER BY week)").alias("bend"), F.min("week").alias("first"))
    noise = ((F.col("week") * 7919 + F.col("person_id") * 104729) % 97 / 97.0 - 0.5) * 10
    value = (F.col("week") - F.col("first") + 0.5 * F.greatest(F.col("week") - F.col("bend"), F.lit(0))).cast("double") + noise
    return weeks.join(bend, "person_id").select("person_id", F.lit("planted").alias("feature"), "week", value.alias("value"), "bend")


def planted_break_error(weekly: DataFrame) -> DataFrame:
    """Mean weeks between the planted bend and the bend that is found, and persons for whom it is found within five weeks."""
    rows = planted(weekly)
    found = change.breakpoints(rows.drop("bend"), "joined").join(rows.select("person_id", "bend").distinct(), "person_id")
    away = F.abs(F.col("breakpoint") - F.col("bend"))
    return found.agg(F.count("*").alias("persons"), F.avg(away).alias("mean_error_weeks"), F.count_if(away <= 5).alias("near"))


def lloyd_against_exact(scores: DataFrame, k: int = 3) -> DataFrame:
    """Persons for whom the usual iteration ends above the exact optimum, and those (none) for whom it ends below."""
    exact = (proximity.best_split3 if k == 3 else proximity.best_split2)(scores).select("person_id", F.col("sse").alias("exact"))
    both = proximity.lloyd(scores, k).join(exact, "person_id")
    return both.agg(F.count("*").alias("persons"), F.count_if(F.col("sse") > F.col("exact") + 1e-6).alias("worse"), F.count_if(F.col("sse") < F.col("exact") - 1e-6).alias("better"))


def sketched_devices(scans: DataFrame, spec: SliceSpec | None = None, error: float = 0.02) -> DataFrame:
    """Number of devices of each slice from a sketch of bounded size, for persons with very many addresses."""
    return attach(scans, spec or SliceSpec()).groupBy("person_id", *KEYS).agg(F.approx_count_distinct("address", error).alias("devices"))


def bout_bands(bouts: DataFrame, spec: SliceSpec | None = None, edges: tuple[int, ...] = (10, 20, 30)) -> DataFrame:
    """Bouts by disjoint bands of length: each counts once, in the highest band that it reaches."""
    m, out = F.col("minutes"), []
    for low, high in zip((0, *edges), (*edges, None), strict=True):
        inside = m >= low if high is None else (m >= low) & (m < high)
        out.append(F.count_if(inside).alias(f"band_{low}"))
    return in_slices(bouts, spec or SliceSpec(), ("type",)).groupBy("person_id", *KEYS, "type").agg(*out)


def _scores(s, d):
    return proximity.device_scores(V.scan_events(s, d))


def _bouts(s, d):
    return places.space_bouts(places.label_spaces(V.point_events(s, d), V.places(s, d)))


PEOPLE = " ".join(f"people_{g}:b" for g in ("all", *calls.CATEGORIES))
TURNS = "(SELECT conv_id % 15 AS person_id, 1704067200000000 + conv_id * 3600000000 + turn * 60000000 AS us, CASE role WHEN 'user' THEN 'voice' WHEN 'assistant' THEN 'noise' WHEN 'system' THEN 'silence' END AS inference FROM conversations)"
FIXED = "SELECT d.person_id, d.address, CASE WHEN m.c2 IS NULL OR d.score > m.{high} THEN 'self' {low} ELSE 'others' END AS owner FROM dev d JOIN model m USING (person_id)"
LINE = "(SELECT person_id, feature, round(count(*) * ln(greatest(regr_syy(value, week) * (1 - coalesce(regr_r2(value, week), 0)), 1e-12 * (1 + regr_syy(value, week))) / count(*)) + 2 * ln(count(*)), 6) AS bic_line FROM weekly GROUP BY ALL HAVING count(*) >= 3)"

QUERIES = [
    ("bt_labels_fixed2", "person_id:b address:b owner:s", lambda s, d: proximity.label_devices(V.scan_events(s, d), rule="fixed2"), FIXED.format(high="cut", low="")),
    ("bt_labels_fixed3", "person_id:b address:b owner:s", lambda s, d: proximity.label_devices(V.scan_events(s, d), rule="fixed3"), FIXED.format(high="c2", low="WHEN m.c1 IS NOT NULL AND d.score > m.c1 THEN 'related'")),
    ("bt_choose_k_gain", "person_id:b k:b", lambda s, d: proximity.choose_k(_scores(s, d), rule="gain"), "SELECT person_id, CASE WHEN sse2 - sse3 > 0.75 * sse2 THEN 3 ELSE 2 END AS k FROM model"),
    ("bt_lloyd_vs_exact", "persons:b worse:b better:b", lambda s, d: lloyd_against_exact(_scores(s, d)), None),
    ("bt_devices_sketch", "person_id:b epoch:s devices:b", lambda s, d: sketched_devices(V.scan_lines(s, d)), None),
    ("call_correspondents", f"person_id:b epoch:s {PEOPLE}", lambda s, d: calls.call_features(V.call_events(s, d), V.contacts_of(V.call_events(s, d))), CALL_SQL.replace("{0}", "calls").replace("{1}", "contacts")),
    ("place_bout_bands", "person_id:b epoch:s type:s band_0:b band_10:b band_20:b band_30:b", lambda s, d: bout_bands(_bouts(s, d)),
     f"SELECT person_id, epoch, type, count(*) FILTER (minutes < 10) AS band_0, count(*) FILTER (minutes >= 10 AND minutes < 20) AS band_10, count(*) FILTER (minutes >= 20 AND minutes < 30) AS band_20, count(*) FILTER (minutes >= 30) AS band_30 FROM {Q.in_slices(Q.SPACE_BOUTS, Q.DAY, 'type')} GROUP BY ALL"),
    ("social_minutes_turns", "person_id:b social:d bouts:b", lambda s, d: places.total_minutes(places.social_bouts(_bouts(s, d), V.voice_turns(s, d)), "social"),
     Q.social(Q.FULL, TURNS)),
    ("step_max5_tumbling", "person_id:b epoch:s max5:b", lambda s, d: steps.totals(V.step_events(s, d)), f"SELECT person_id, epoch, max(steps) AS max5 FROM {_sliced('bin')} GROUP BY ALL"),
    ("chg_break_aic", "person_id:b feature:s breakpoint:b aic:d", lambda s, d: change.breakpoints(V.weekly_lines(s, d), "free", "aic"), f"SELECT person_id, feature, breakpoint, bic AS aic FROM ({FREE.replace('* ln(n), 6)', '* 2, 6)')})"),
    ("chg_line_bic", "person_id:b feature:s bic_line:d", lambda s, d: line_bic(V.weekly_lines(s, d)), f"SELECT * FROM {LINE}"),
    ("chg_line_vs_break", "feature:s series:b breaks:b", lambda s, d: line_against_break(V.weekly_lines(s, d)), f"SELECT feature, count(*) AS series, count(*) FILTER (bic < bic_line - 1e-5) AS breaks FROM {LINE} JOIN ({FREE}) USING (person_id, feature) GROUP BY ALL"),
    ("chg_break_error", "persons:b mean_error_weeks:d near:b", lambda s, d: planted_break_error(V.weekly_lines(s, d)), f"""WITH w AS (SELECT DISTINCT person_id, week FROM weekly), b AS (SELECT person_id, quantile_disc(week, 0.4) AS bend, min(week) AS first FROM w GROUP BY ALL),
      series AS MATERIALIZED (SELECT person_id, 'planted' AS feature, week, week - first + 0.5::DOUBLE * greatest(week - bend, 0) + ((week * 7919 + person_id * 104729) % 97 / 97.0::DOUBLE - 0.5::DOUBLE) * 10 AS value FROM w JOIN b USING (person_id))
      SELECT count(*) AS persons, avg(abs(breakpoint - bend)) AS mean_error_weeks, count(*) FILTER (abs(breakpoint - bend) <= 5) AS near FROM {Q.joined_breaks('series')} JOIN b USING (person_id)"""),
]
