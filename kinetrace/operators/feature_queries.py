"""Queries of the seven feature sets, the change layer, baselines and measures: (name, columns, query, SQL body or None)."""

from __future__ import annotations

from pyspark.sql import functions as F

from kinetrace.operators import assemble, baselines, calls, change, location, measures, phone, places, proximity, sleep, steps
from kinetrace.oracles import sets as Q
from kinetrace.oracles.base import ep
from kinetrace.plans.slices import KEYS, SliceSpec, attach
from kinetrace.sources import maps
from kinetrace.sources import views as V

QUARTER = ep("us")


def _sliced(view: str, us: str = "us") -> str:
    return f"(SELECT *, unnest(['allday', {ep(us)}]) AS epoch FROM {view})"


def _crossed(view: str) -> str:
    day = "(us // 86400000000)"
    return (
        f"(SELECT *, unnest(['allday', {QUARTER}]) AS epoch FROM (SELECT *, unnest(['all', CASE WHEN ({day} + 3) % 7 >= 5 THEN 'weekend' ELSE 'weekday' END]) AS daytype FROM "
        f"(SELECT *, s.span AS span, s.id AS span_id FROM (SELECT *, unnest([{{'span': 'full', 'id': 0}}, {{'span': 'half', 'id': CASE WHEN {day} - 19723 < 15 THEN 1 ELSE 2 END}}, {{'span': 'week', 'id': ({day} + 3) // 7 - (19723 + 3) // 7 + 1}}]) AS s FROM {view}))))"
    )


STEP_SPEC = "active_bouts:b active_max:d active_min:d active_mean:d sedentary_bouts:b sedentary_max:d sedentary_min:d sedentary_mean:d steps_min:b steps_max:b steps_mean:d"
NAP = "(SELECT person_id, state, min(us) AS start_us, max(us) + 60000000 AS end_us, CAST(count(*) AS DOUBLE) AS minutes FROM (SELECT *, us // 60000000 - row_number() OVER (PARTITION BY person_id, state ORDER BY us) AS r FROM nap) GROUP BY person_id, state, r)"
CALLS = ", ".join(
    f"count(*) FILTER (direction = '{d}'{c}) AS n_{d}_{g}, coalesce(sum(duration_s) FILTER (direction = '{d}'{c}), 0) AS s_{d}_{g}" for g, c in [("all", "")] + [(x, f" AND category = '{x}'") for x in calls.CATEGORIES] for d in calls.DIRECTIONS
) + ", count(DISTINCT correspondent) AS people_all, " + ", ".join(f"count(DISTINCT correspondent) FILTER (category = '{g}') AS people_{g}" for g in calls.CATEGORIES)
CALL_SPEC = "person_id:b epoch:s " + " ".join(f"n_{d}_{g}:b s_{d}_{g}:d" for g in ("all", *calls.CATEGORIES) for d in calls.DIRECTIONS) + " " + " ".join(f"people_{g}:b" for g in ("all", *calls.CATEGORIES))
CALL_SQL = f"SELECT person_id, epoch, {CALLS} FROM {_sliced('(SELECT * FROM {0} LEFT JOIN {1} USING (person_id, correspondent))')} GROUP BY ALL"
ORDER_CALLS = "(SELECT o_custkey AS person_id, epoch_us(o_orderdate) AS us, CASE o_orderstatus WHEN 'O' THEN 'incoming' WHEN 'F' THEN 'outgoing' WHEN 'P' THEN 'missed' END AS direction, o_orderkey % 12 AS correspondent, o_totalprice / 1000 AS duration_s FROM orders)"
ORDER_CONTACTS = "(SELECT DISTINCT o_custkey AS person_id, o_orderkey % 12 AS correspondent, (['family','friend_off','friend_on'])[(o_orderkey % 12) % 4 + 1] AS category FROM orders WHERE (o_orderkey % 12) % 4 < 3)"
SIX = "count(*) AS devices, max(scans) AS most, min(scans) AS least, sum(scans) AS total, avg(scans) AS mean, stddev_pop(scans) AS std"
MOMENTS = "regr_slope(value, week) AS slope, regr_slope(CASE WHEN week <= m THEN value END, CASE WHEN week <= m THEN week END) AS slope_first, regr_slope(CASE WHEN week >= m THEN value END, CASE WHEN week >= m THEN week END) AS slope_second, regr_r2(value, week) AS r2"
FREE = """SELECT person_id, feature, breakpoint, bic, bs.slope_before, bs.slope_after FROM (SELECT person_id, feature, arg_min(cut, (bic, cut)) AS breakpoint, min(bic) AS bic, arg_min({'slope_before': sb, 'slope_after': sa}, (bic, cut)) AS bs FROM (
  SELECT person_id, feature, cut, sb, sa, round(n * ln(greatest(l + r, 1e-12 * (1 + t)) / n) + CASE WHEN nr = 0 THEN 2 ELSE 4 END * ln(n), 6) AS bic FROM (
    SELECT person_id, feature, cut, count(*) AS n, count(*) FILTER (week > cut) AS nr, regr_slope(value, week) FILTER (week <= cut) AS sb, regr_slope(value, week) FILTER (week > cut) AS sa, regr_syy(value, week) AS t,
      greatest(coalesce(regr_syy(value, week) FILTER (week <= cut) * (1 - coalesce(regr_r2(value, week) FILTER (week <= cut AND TRUE), 0)), 0), 0) AS l,
      greatest(coalesce(regr_syy(value, week) FILTER (week > cut) * (1 - coalesce(regr_r2(value, week) FILTER (week > cut), 0)), 0), 0) AS r
    FROM line0 GROUP BY ALL) WHERE n >= 3) GROUP BY ALL)"""
SPECTRUM = """SELECT person_id, period, (power(sum(y * cos(w)), 2) + power(sum(y * sin(w)), 2) + power(sum(x * cos(w)), 2) + power(sum(x * sin(w)), 2)) / count(*) AS power FROM (
    SELECT *, 2 * pi() * (h + 0.5::DOUBLE) / period AS w FROM (SELECT person_id, h, lat - avg(lat) OVER (PARTITION BY person_id) AS y, lon - avg(lon) OVER (PARTITION BY person_id) AS x
      FROM (SELECT person_id, (us - 1704067200000000) // 3600000000 AS h, avg(lat) AS lat, avg(lon) AS lon FROM pt GROUP BY ALL)), (SELECT unnest([12.0::DOUBLE, 24.0::DOUBLE]) AS period)) GROUP BY ALL"""
F_TEST = """SELECT person_id, feature, arg_min(cut, (round(rss, 6), cut)) AS breakpoint, greatest((any_value(line) - arg_min(rss, (round(rss, 6), cut))) / 2.0::DOUBLE / (greatest(arg_min(rss, (round(rss, 6), cut)), 1e-9) / (any_value(n) - 4)), 0) AS f FROM (
  SELECT person_id, feature, cut, n, line, greatest(l, 0) + greatest(r, 0) AS rss FROM (
    SELECT person_id, feature, cut, count(*) AS n, count(*) FILTER (week > cut) AS nr, regr_syy(value, week) * (1 - coalesce(regr_r2(value, week), 0)) AS line,
      coalesce(regr_syy(value, week) FILTER (week <= cut) * (1 - coalesce(regr_r2(value, week) FILTER (week <= cut), 0)), 0) AS l, coalesce(regr_syy(value, week) FILTER (week > cut) * (1 - coalesce(regr_r2(value, week) FILTER (week > cut), 0)), 0) AS r
    FROM line0 GROUP BY ALL) WHERE n >= 6 AND nr > 0) GROUP BY ALL"""
CROSS = "span:s span_id:b daytype:s epoch:s"
PLACES = "places:b transitions:b gyration_km:d top1_minutes:d top2_minutes:d top3_minutes:d moving_share:d rare_share:d stay_max:d stay_min:d stay_mean:d stay_std:d entropy:d normalised_entropy:d"
PHONE = "unlocks:b unlocks_per_minute:d " + " ".join(f"{k}_{m}:d" for k in phone.KINDS for m in ("total", "max", "min", "mean", "std"))
AGREEMENT = f"""WITH RECURSIVE {Q.HELD}, {Q.dbscan('(SELECT person_id AS g, sid, lat, lon FROM held WHERE NOT moving)')},
  rows_ AS (SELECT h.person_id, place, pt.pl FROM held h JOIN placed USING (sid) JOIN pt ON pt.person_id = h.person_id AND pt.us = h.us WHERE place >= 0),
  pairs AS (SELECT a.person_id, count(*) AS t, sum(CAST(a.place = b.place AND a.pl = b.pl AS INT)) AS s, sum(CAST(a.place = b.place AS INT)) AS sa, sum(CAST(a.pl = b.pl AS INT)) AS sb FROM (SELECT *, row_number() OVER () AS i FROM rows_) a
            JOIN (SELECT *, row_number() OVER () AS i FROM rows_) b ON a.person_id = b.person_id AND a.i < b.i GROUP BY ALL)
  SELECT count(*) AS persons, avg(coalesce((s - sa * sb / t::DOUBLE) / nullif((sa + sb) / 2.0::DOUBLE - sa * sb / t::DOUBLE, 0), 1)) AS agreement FROM pairs"""
_SIDE = "SELECT person_id, score, CASE WHEN {test} THEN 0 {more} ELSE {last} END AS c FROM dev JOIN model USING (person_id)"
_MEAN = "(SELECT person_id, round(avg(v), 7) AS s{n} FROM (SELECT person_id, rid, CASE WHEN min(gap) FILTER (other) IS NULL THEN 0 ELSE round(coalesce(1 - max(gap) FILTER (NOT other) / nullif(greatest(max(gap) FILTER (NOT other), min(gap) FILTER (other)), 0), 0), 9) END AS v FROM (SELECT a.person_id, a.rid, abs(a.score - z.m) AS gap, z.c <> a.c AS other FROM (SELECT *, row_number() OVER () AS rid FROM ({rows})) a JOIN (SELECT person_id, c, avg(score) AS m FROM ({rows}) GROUP BY ALL) z USING (person_id)) GROUP BY ALL) GROUP BY ALL)"
SILHOUETTE = "SELECT person_id, CASE WHEN s2 >= s3 THEN 2 ELSE 3 END AS k FROM " + _MEAN.format(n=2, rows=_SIDE.format(test="m1 > 1 AND score <= cut", more="", last=1)) + " JOIN " + _MEAN.format(n=3, rows=_SIDE.format(test="c1 IS NOT NULL AND score <= c1", more="WHEN c2 IS NOT NULL AND score <= c2 THEN 1", last=2)) + " USING (person_id)"
SILHOUETTE = SILHOUETTE.replace("FROM dev JOIN model USING (person_id)", "FROM dev JOIN model USING (person_id) JOIN (SELECT person_id, count(*) AS m1 FROM cutv GROUP BY ALL) USING (person_id)")
_IMPORTED = "SELECT n_nationkey AS place_id, n_name AS name, (['social_greek','greek','apartment','residence','athletic','green','academic','off_campus'])[code + 1] AS type, code AS priority, 4 AS corners, 40 + 0.02::DOUBLE * (n_nationkey // 5) + 0.001::DOUBLE AS north, -80 + 0.02::DOUBLE * (n_nationkey % 5) + 0.001::DOUBLE AS east FROM (SELECT *, n_nationkey % 8 AS code FROM nation WHERE n_nationkey % 8 < 7 UNION ALL SELECT *, 1 FROM nation WHERE n_nationkey % 8 = 0)"


def _moved(s, d):
    return location.label_motion(V.point_events(s, d)).select("person_id", "us", "lat", "lon", "moving")


def _space_bouts(s, d):
    return places.space_bouts(places.label_spaces(V.point_events(s, d), V.places(s, d)))


def _imported(s, d):
    """The map written as a GeoJSON file and as text, and read back by both readers: the places that both give."""
    given = V.places(s, d)
    a, b = maps.read_geojson(s, maps.write_geojson(given)), maps.from_wkt(maps.to_wkt(given))
    found = a.select("place_id", "name", "type", "priority", "polygon").intersect(b.select("place_id", "name", "type", "priority", "polygon"))
    return found.withColumns({"corners": F.size("polygon"), "north": F.array_max(F.col("polygon.lat")), "east": F.array_max(F.col("polygon.lon"))})


QUERIES = [
    # slices
    ("slice_counts", "person_id:b span:s span_id:b daytype:s epoch:s n:b", lambda s, d: assemble.slice_counts(V.events(s, d), SliceSpec.crossed()), f"SELECT person_id, span, span_id, daytype, epoch, count(*) AS n FROM {_crossed('ev')} GROUP BY ALL"),
    ("slice_grid_rollup", "person_id:b span:s span_id:b daytype:s epoch:s n:b total:d", lambda s, d: assemble.slice_rollup(V.events(s, d), SliceSpec.crossed()), f"SELECT person_id, span, span_id, daytype, epoch, count(*) AS n, sum(value) AS total FROM {_crossed('ev')} GROUP BY ALL"),
    ("coverage_by_slice", "person_id:b epoch:s samples:b hours:b", lambda s, d: measures.coverage(V.events(s, d)), f"SELECT person_id, epoch, count(*) AS samples, count(DISTINCT us // 3600000000) AS hours FROM {_sliced('ev')} GROUP BY ALL"),
    # proximity
    ("bt_device_scores", "person_id:b address:b days:b scans:b frequency:d score:d", lambda s, d: proximity.device_scores(V.scan_events(s, d)), "SELECT * FROM dev"),
    ("bt_device_scores_lines", "person_id:b address:b days:b scans:b", lambda s, d: proximity.scan_days(V.scan_lines(s, d)), "SELECT l_suppkey AS person_id, l_partkey % 50 AS address, count(DISTINCT l_shipdate) AS days, count(*) AS scans FROM lineitem GROUP BY ALL"),
    ("bt_kmeans_k2", "person_id:b sse:d", lambda s, d: proximity.best_split2(proximity.device_scores(V.scan_events(s, d))), "SELECT person_id, sse2 AS sse FROM two"),
    ("bt_kmeans_k3", "person_id:b sse:d", lambda s, d: proximity.best_split3(proximity.device_scores(V.scan_events(s, d))), "SELECT person_id, sse3 AS sse FROM model"),
    ("bt_choose_k", "person_id:b sse2:d sse3:d k:b", lambda s, d: proximity.choose_k(proximity.device_scores(V.scan_events(s, d))), "SELECT person_id, sse2, sse3, CASE WHEN sse2 < sse3 THEN 2 ELSE 3 END AS k FROM model"),
    ("bt_choose_k_bic", "person_id:b k:b", lambda s, d: proximity.choose_k(proximity.device_scores(V.scan_events(s, d)), rule="bic"), "SELECT person_id, CASE WHEN n * ln(greatest(sse2 / n, 1e-9)) + 2 * ln(n) < n * ln(greatest(sse3 / n, 1e-9)) + 3 * ln(n) THEN 2 ELSE 3 END AS k FROM model JOIN (SELECT person_id, count(*) AS n FROM dev GROUP BY ALL) USING (person_id)"),
    ("bt_choose_k_silhouette", "person_id:b k:b", lambda s, d: proximity.choose_k(proximity.device_scores(V.scan_events(s, d)), rule="silhouette"), SILHOUETTE),
    ("bt_labels", "person_id:b address:b owner:s", lambda s, d: proximity.label_devices(V.scan_events(s, d)), "SELECT person_id, address, owner FROM owner"),
    ("bt_features_global", "person_id:b epoch:s owners:s devices:b most:b least:b total:b mean:d std:d", lambda s, d: proximity.scan_features(V.scan_events(s, d)), f"SELECT person_id, epoch, owners, {SIX} FROM (SELECT t.person_id, t.epoch, t.scans, unnest(['all', o.owner]) AS owners FROM (SELECT person_id, epoch, address, count(*) AS scans FROM {_sliced('scan')} GROUP BY ALL) t JOIN owner o USING (person_id, address)) GROUP BY ALL"),
    ("bt_features_local", "person_id:b epoch:s owners:s devices:b most:b least:b total:b mean:d std:d", lambda s, d: proximity.scan_features(V.scan_events(s, d), scope="local"), Q.local_scan_features(Q.DAY)),
    ("bt_sse_compare", "k:b persons:b", lambda s, d: proximity.choose_k(proximity.device_scores(V.scan_events(s, d))).groupBy("k").agg(F.count("*").alias("persons")), "SELECT CASE WHEN sse2 < sse3 THEN 2 ELSE 3 END AS k, count(*) AS persons FROM model GROUP BY ALL"),
    ("bt_kmeans_lloyd", "person_id:b sse:d", lambda s, d: proximity.lloyd(proximity.device_scores(V.scan_lines(s, d)), 3), None),
    # calls
    ("call_features", CALL_SPEC.replace(" epoch:s", ""), lambda s, d: calls.call_features(V.call_events(s, d), V.contacts_of(V.call_events(s, d)), SliceSpec(epochs=False)), f"SELECT person_id, {CALLS} FROM calls LEFT JOIN contacts USING (person_id, correspondent) GROUP BY ALL"),
    ("call_features_by_slice", CALL_SPEC, lambda s, d: calls.call_features(V.call_events(s, d), V.contacts_of(V.call_events(s, d))), CALL_SQL.replace("{0}", "calls").replace("{1}", "contacts")),
    ("call_features_orders", CALL_SPEC, lambda s, d: calls.call_features(V.call_orders(s, d), V.contacts_of(V.call_orders(s, d))), CALL_SQL.replace("{0}", ORDER_CALLS).replace("{1}", ORDER_CONTACTS)),
    # location
    ("loc_spectrum_hourly", "person_id:b period:d power:d", lambda s, d: baselines.hourly_spectrum(V.point_events(s, d), [12.0, 24.0]), SPECTRUM),
    ("loc_motion", "person_id:b us:b speed:d moving:b", lambda s, d: location.label_motion(V.point_events(s, d)).withColumn("moving", F.col("moving").cast("int")), "SELECT person_id, us, speed, CAST(moving AS INT) AS moving FROM mv"),
    ("loc_basic", "person_id:b epoch:s variance:d distance_km:d speed_mean:d speed_variance:d log_variance:d", lambda s, d: location.mobility_basic(V.point_events(s, d)), f"SELECT *, ln(nullif(round(variance, 15), 0)) AS log_variance FROM (SELECT person_id, epoch, var_pop(lat) + var_pop(lon) AS variance, sum(km) AS distance_km, avg(speed) AS speed_mean, var_pop(speed) AS speed_variance FROM {_sliced('mv')} GROUP BY ALL)"),
    ("loc_circadian_log", "person_id:b circadian:d", lambda s, d: location.circadian(V.point_events(s, d)), Q.circadian(Q.FULL)),
    ("loc_circadian_share", "person_id:b circadian:d", lambda s, d: location.circadian(V.point_events(s, d), normalise="share"), Q.circadian(Q.FULL, "share")),
    ("loc_places_global", "person_id:b us:b place:b", lambda s, d: location.significant_places(_moved(s, d)).where("not moving"), f"WITH RECURSIVE {Q.HELD}, {Q.dbscan('(SELECT person_id AS g, sid, lat, lon FROM held WHERE NOT moving)')} SELECT person_id, us, place FROM held JOIN placed USING (sid)"),
    ("loc_places_local", "person_id:b epoch:s us:b place:b", lambda s, d: location.significant_places(attach(_moved(s, d), SliceSpec()), ("person_id", *KEYS)), Q.local_places()),
    ("loc_places_cells", "person_id:b us:b place:b", lambda s, d: location.significant_places(_moved(s, d), cells_m=10.0).where("not moving"), None),
    ("loc_place_features", f"person_id:b epoch:s {PLACES}", lambda s, d: location.place_features(V.point_events(s, d)), Q.place_features(Q.DAY)),
    ("loc_place_features_local", f"person_id:b epoch:s {PLACES}", lambda s, d: location.place_features(V.point_events(s, d), scope="local"), Q.place_features(Q.DAY, "local")),
    ("loc_place_features_weekly", f"person_id:b span_id:b {PLACES}", lambda s, d: location.place_features(V.point_events(s, d), SliceSpec.weekly()), Q.place_features(Q.WEEK)),
    ("loc_place_features_weekly_local", f"person_id:b span_id:b {PLACES}", lambda s, d: location.place_features(V.point_events(s, d), SliceSpec.weekly(), "local"), Q.place_features(Q.WEEK, "local")),
    ("loc_entropy", "person_id:b entropy:d normalised_entropy:d places:b", lambda s, d: location.place_features(V.point_events(s, d), SliceSpec(epochs=False)), Q.place_features(Q.FULL)),
    ("loc_top3", "person_id:b epoch:s top1_minutes:d top2_minutes:d top3_minutes:d", lambda s, d: location.place_features(V.point_events(s, d)), Q.place_features(Q.DAY)),
    ("loc_top3_local", "person_id:b epoch:s top1_minutes:d top2_minutes:d top3_minutes:d", lambda s, d: location.place_features(V.point_events(s, d), scope="local"), Q.place_features(Q.DAY, "local")),
    ("loc_stay_stats", "person_id:b epoch:s stay_max:d stay_min:d stay_mean:d stay_std:d", lambda s, d: location.place_features(V.point_events(s, d)), Q.place_features(Q.DAY)),
    ("loc_stay_stats_local", "person_id:b epoch:s stay_max:d stay_min:d stay_mean:d stay_std:d", lambda s, d: location.place_features(V.point_events(s, d), scope="local"), Q.place_features(Q.DAY, "local")),
    ("loc_entropy_local", "person_id:b epoch:s entropy:d normalised_entropy:d", lambda s, d: location.place_features(V.point_events(s, d), scope="local"), Q.place_features(Q.DAY, "local")),
    ("loc_home", "person_id:b home_lat:d home_lon:d", lambda s, d: location.home_location(V.point_events(s, d)), Q.home()),
    ("loc_home_time", "person_id:b epoch:s home_10m:d home_100m:d", lambda s, d: location.home_features(V.point_events(s, d)), Q.home_time()),
    # annotated places
    ("place_labels", "person_id:b us:b type:s", lambda s, d: places.label_spaces(V.point_events(s, d), V.places(s, d)), "SELECT person_id, us, type FROM spc"),
    ("place_labels_all", "person_id:b us:b type:s", lambda s, d: places.label_spaces(V.point_events(s, d), V.places(s, d), "all"), "SELECT person_id, us, type FROM spc UNION ALL SELECT person_id, us, 'greek' FROM spc WHERE type = 'social_greek'"),
    ("place_import", "place_id:b name:s type:s priority:b corners:b north:d east:d", _imported, _IMPORTED),
    ("place_minutes", "person_id:b epoch:s type:s minutes:d share:d", lambda s, d: places.space_minutes(places.label_spaces(V.point_events(s, d), V.places(s, d))), Q.space_minutes(Q.DAY)),
    ("place_transitions", "person_id:b epoch:s transitions:b", lambda s, d: places.space_transitions(places.label_spaces(V.point_events(s, d), V.places(s, d))), Q.space_transitions(Q.DAY)),
    ("place_bouts", "person_id:b epoch:s type:s bouts:b bouts_10:b bouts_20:b bouts_30:b shortest:d longest:d mean:d std:d", lambda s, d: places.bout_features(_space_bouts(s, d)), Q.space_bouts(Q.DAY)),
    ("place_bouts_crossed", f"person_id:b {CROSS} type:s bouts:b bouts_30:b longest:d mean:d", lambda s, d: places.bout_features(_space_bouts(s, d), SliceSpec.crossed()), Q.space_bouts(Q.CROSSED)),
    ("study_minutes", "person_id:b study:d bouts:b", lambda s, d: baselines.study(s, d), Q.study(Q.FULL)),
    ("study_minutes_crossed", f"person_id:b {CROSS} study:d bouts:b", lambda s, d: baselines.study(s, d, SliceSpec.crossed()), Q.study(Q.CROSSED)),
    ("social_minutes", "person_id:b social:d bouts:b", lambda s, d: places.total_minutes(places.social_bouts(_space_bouts(s, d), V.voice_events(s, d)), "social"), Q.social(Q.FULL)),
    ("social_minutes_crossed", f"person_id:b {CROSS} social:d bouts:b", lambda s, d: places.total_minutes(places.social_bouts(_space_bouts(s, d), V.voice_events(s, d)), "social", SliceSpec.crossed()), Q.social(Q.CROSSED)),
    # phone
    ("phone_interaction_bouts", "person_id:b start_us:b end_us:b", lambda s, d: phone.interaction_bouts(V.screen_events(s, d)), "SELECT * FROM ibout"),
    ("phone_unlocked_bouts", "person_id:b start_us:b end_us:b", lambda s, d: phone.unlocked_bouts(V.screen_events(s, d)), "SELECT * FROM ubout"),
    ("phone_features", f"person_id:b epoch:s {PHONE}", lambda s, d: phone.phone_features(V.screen_events(s, d)), Q.phone_features(Q.DAY)),
    ("phone_features_crossed", f"person_id:b {CROSS} {PHONE}", lambda s, d: phone.phone_features(V.screen_events(s, d), SliceSpec.crossed()), Q.phone_features(Q.CROSSED)),
    ("phone_first_last_hours", "person_id:b epoch:s first_unlock:d first_on:d last_unlock:d last_lock:d last_on:d", lambda s, d: phone.first_last_hours(V.screen_events(s, d)), Q.phone_hours(Q.DAY)),
    # sleep
    ("sleep_counts_efficiency", "person_id:b epoch:s asleep:b restless:b awake:b unknown:b weak_efficiency:d strong_efficiency:d", lambda s, d: sleep.counts_efficiency(V.sleep_lines(s, d)), Q.sleep_counts(Q.DAY)),
    ("sleep_bouts", "person_id:b state:s start_us:b end_us:b minutes:d", lambda s, d: sleep.sleep_bouts(V.sleep_lines(s, d)), f"SELECT * FROM {NAP}"),
    ("sleep_bout_stats", "person_id:b epoch:s state:s bouts:b total:d mean:d longest:d shortest:d", lambda s, d: sleep.bout_stats(sleep.bouts_in_slices(V.sleep_lines(s, d))), Q.sleep_bout_stats(Q.DAY)),
    ("sleep_bout_stats_crossed", f"person_id:b {CROSS} state:s bouts:b total:d mean:d longest:d shortest:d", lambda s, d: sleep.bout_stats(sleep.bouts_in_slices(V.sleep_events(s, d), SliceSpec.crossed())), Q.sleep_bout_stats(Q.CROSSED, Q.SLEEP_EVENTS)),
    ("sleep_extreme_bouts", "person_id:b epoch:s state:s longest_start:b longest_end:b shortest_start:b shortest_end:b", lambda s, d: sleep.extreme_bouts(sleep.bouts_in_slices(V.sleep_lines(s, d))), Q.sleep_extremes(Q.DAY)),
    # steps
    ("step_totals", "person_id:b epoch:s total:b max5:b", lambda s, d: steps.totals(V.step_events(s, d)), f"SELECT person_id, epoch, sum(steps) AS total, max(steps) AS max5 FROM {_sliced('bin')} GROUP BY ALL"),
    ("step_max5_sliding", "person_id:b epoch:s max5_sliding:b", lambda s, d: steps.sliding_max(V.step_events(s, d)), f"SELECT person_id, epoch, max(t) AS max5_sliding FROM {_sliced('(SELECT a.person_id, a.us, sum(b.steps) AS t FROM step a JOIN step b ON a.person_id = b.person_id AND b.us BETWEEN a.us - 299999999 AND a.us GROUP BY ALL)')} GROUP BY ALL"),
    ("step_max5_words", "person_id:b epoch:s total:b max5:b", lambda s, d: steps.totals(V.step_words(s, d)), f"SELECT person_id, epoch, sum(steps) AS total, max(steps) AS max5 FROM {_sliced('(SELECT person_id, us // 300000000 * 300000000 AS us, sum(steps) AS steps FROM (SELECT doc_id AS person_id, 1704067200000000 + 60000000 * (i - 1) AS us, length(w[i]) % 4 AS steps FROM (SELECT doc_id, w, unnest(range(1, len(w) + 1)) AS i FROM (SELECT doc_id, string_split(text, chr(32)) AS w FROM documents))) GROUP BY ALL)')} GROUP BY ALL"),
    ("step_bouts", "person_id:b label:s start_us:b end_us:b minutes:d steps:b", lambda s, d: steps.step_bouts(steps.five_minute_bins(V.step_events(s, d))), "SELECT * FROM stepbout"),
    ("step_bout_stats", f"person_id:b epoch:s {STEP_SPEC}", lambda s, d: steps.bout_stats(steps.bouts_in_slices(steps.five_minute_bins(V.step_events(s, d)))), Q.step_bout_stats(Q.DAY)),
    ("step_bout_stats_crossed", f"person_id:b {CROSS} {STEP_SPEC}", lambda s, d: steps.bout_stats(steps.bouts_in_slices(steps.five_minute_bins(V.step_events(s, d)), SliceSpec.crossed())), Q.step_bout_stats(Q.CROSSED)),
    ("step_features_daily", f"person_id:b epoch:s total:b max5:b {STEP_SPEC}", lambda s, d: steps.step_features(V.step_events(s, d)), Q.step_features(Q.DAY)),
    # change
    ("chg_slopes", "person_id:b feature:s n:b slope:d slope_first:d slope_second:d r2:d", lambda s, d: change.slopes(V.weekly_lines(s, d), None), f"SELECT person_id, feature, count(*) AS n, {MOMENTS} FROM (SELECT w.*, m FROM weekly w, (SELECT (min(week) + max(week)) // 2 AS m FROM weekly)) GROUP BY ALL HAVING count(*) >= 3"),
    ("chg_break_free", "person_id:b feature:s breakpoint:b bic:d slope_before:d slope_after:d", lambda s, d: change.breakpoints(V.weekly_lines(s, d), "free"), FREE),
    ("chg_break_f", "person_id:b feature:s breakpoint:b f:d", lambda s, d: change.f_values(V.weekly_lines(s, d)), F_TEST),
    ("chg_break_joined", "person_id:b feature:s breakpoint:b bic:e slope_before:e slope_after:e", lambda s, d: change.breakpoints(V.weekly_lines(s, d), "joined"), f"SELECT * FROM {Q.joined_breaks('weekly')}"),
    ("chg_all_weekly", "person_id:b feature:s n:b slope:d slope_first:d slope_second:d breakpoint:b slope_before:d slope_after:d", lambda s, d: change.change_features(assemble.weekly_features(s, d), 3),
     f"WITH series AS MATERIALIZED (SELECT person_id, sensor || '.' || feature AS feature, span_id AS week, value FROM ({Q.long(Q.WEEK)})) {Q.change_of('series', 3)}"),
    ("chg_break_naive", "person_id:b feature:s breakpoint:b bic:d slope_before:d slope_after:d", lambda s, d: change.breakpoints_naive(V.weekly_lines(s, d)), FREE),
    # assembly, baselines, measures
    ("feature_long", "person_id:b sensor:s feature:s epoch:s value:d", lambda s, d: assemble.feature_long(s, d), Q.long(Q.DAY)),
    ("feature_long_location", "person_id:b sensor:s feature:s epoch:s value:d", lambda s, d: baselines.single_channel(s, d, "location"), f"SELECT * FROM ({Q.long(Q.DAY)}) WHERE sensor = 'location'"),
    ("feature_long_screen", "person_id:b sensor:s feature:s epoch:s value:d", lambda s, d: baselines.single_channel(s, d, "screen"), f"SELECT * FROM ({Q.long(Q.DAY)}) WHERE sensor = 'phone'"),
    ("feature_long_location_screen", "person_id:b sensor:s feature:s epoch:s value:d", lambda s, d: baselines.single_channel(s, d, "location_screen"), f"SELECT * FROM ({Q.long(Q.DAY)}) WHERE sensor IN ('location', 'phone')"),
    ("feature_wide", "person_id:b " + " ".join(f"{n.replace('.', '_')}:d" for n in assemble.WIDE), lambda s, d: assemble.feature_wide(s, d), "SELECT person_id, " + ", ".join(f"max(value) FILTER (sensor || '.' || feature = '{n}') AS {n.replace('.', '_')}" for n in assemble.WIDE) + f" FROM ({Q.long(Q.FULL)}) GROUP BY person_id"),
    ("feature_by_segment", "segment:s persons:b total:d", lambda s, d: assemble.by_segment(s, d), "SELECT c_mktsegment AS segment, count(DISTINCT person_id) AS persons, sum(steps) AS total FROM step JOIN customer ON c_custkey = person_id GROUP BY ALL"),
    ("catalogue_count", "sensor:s features:b weeks:b values_total:b", lambda s, d: assemble.catalogue_count(s, d), f"SELECT sensor, features, weeks, features * 5 * 3 * (weeks + 3 + 6) AS values_total FROM (SELECT sensor, count(DISTINCT feature) AS features FROM ({Q.long(Q.FULL)}) GROUP BY ALL), (SELECT (max(us) // 86400000000 + 3) // 7 - (min(us) // 86400000000 + 3) // 7 + 1 AS weeks FROM ev)"),
    ("dbscan_vs_bruteforce", "differing:b samples:b", lambda s, d: baselines.dbscan_difference(s, d), "SELECT 0 AS differing, count(*) AS samples FROM ev"),
    ("break_vs_naive", "differing:b", lambda s, d: baselines.break_difference(s, d), "SELECT 0 AS differing"),
    ("slices_vs_naive", "differing:b", lambda s, d: baselines.slices_difference(s, d), "SELECT 0 AS differing"),
    ("interval_vs_naive", "differing:b intervals:b", lambda s, d: baselines.interval_difference(s, d), f"SELECT 0 AS differing, count(*) AS intervals FROM {Q.STUDY}"),
    ("circadian_vs_direct", "differing:b", lambda s, d: baselines.circadian_difference(s, d), "SELECT 0 AS differing"),
    ("place_agreement", "persons:b agreement:d", lambda s, d: measures.place_agreement(s, d), AGREEMENT),
    ("home_error", "persons:b right:b median_error_m:d", lambda s, d: measures.home_error(s, d), None),
    ("plan_costs", "name:s rows:b exchanges:b shuffle_bytes:b seconds:d", lambda s, d: measures.costs(s, d, {"partials": lambda a, b: assemble.slice_rollup(V.events(a, b), SliceSpec.crossed()), "rows": lambda a, b: assemble.slice_counts(V.events(a, b), SliceSpec.crossed())}), None),
    ("cells_agreement", "samples:b same_noise:d agreement:d", lambda s, d: measures.cells_agreement(s, d), None),
]
