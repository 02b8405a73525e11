"""Slices' borders, clustering anywhere on the globe, maps, and the smaller additions, by hand and by plain counting."""

import math
from collections import Counter

import numpy as np
import pytest
from conftest import SF
from pyspark.sql import functions as F

from kinetrace import registry
from kinetrace.operators import assemble, baselines, change, location, places, proximity
from kinetrace.plans.slices import KEYS, SliceSpec, attach, in_slices
from kinetrace.sources import maps
from kinetrace.sources import views as V

MINUTE, DAY, START = 60_000_000, 86_400_000_000, 1704067200000000


def nominal(first=19723, days=35):
    """Minutes of every slice in the data's weeks, counted by parts of days."""
    out = Counter()
    for d in range(first, first + days):
        kind = "weekend" if (d + 3) % 7 >= 5 else "weekday"
        for span, number in (("full", 0), ("half", 1 if d - first < 15 else 2), ("week", (d + 3) // 7 - (first + 3) // 7 + 1)):
            for daytype in ("all", kind):
                for epoch in ("night", "morning", "afternoon", "evening"):
                    out[span, number, daytype, epoch] += 360
                out[span, number, daytype, "allday"] += 1440
    return out


def test_no_slice_holds_more_than_its_time(spark):
    """Sums of times of one person in a slice, over types that exclude each other, and the longest bouts."""
    room, spec = nominal(), SliceSpec.crossed()
    points, spaces = V.point_events(spark, SF), places.label_spaces(V.point_events(spark, SF), V.places(spark, SF))
    sums = {
        "places": places.space_minutes(spaces, spec).groupBy("person_id", *KEYS).agg(F.sum("minutes").alias("m")),
        "visits": location.visits(points, spec).groupBy("person_id", *KEYS).agg(F.sum("minutes").alias("m")),
        "local": location.visits(points, spec, "local").groupBy("person_id", *KEYS).agg(F.sum("minutes").alias("m")),
        "bouts": in_slices(places.space_bouts(spaces), spec, ("type",)).groupBy("person_id", *KEYS).agg(F.sum("minutes").alias("m")),
        "phone": assemble.phone.phone_features(V.screen_events(spark, SF), spec).select("person_id", *KEYS, F.greatest("interaction_total", "unlocked_total").alias("m")),
        "home": location.home_features(points, spec).select("person_id", *KEYS, F.col("home_100m").alias("m")),
    }
    for name, frame in sums.items():
        rows = frame.where("m is not null").collect()
        assert len(rows) > 500 and all(r.m <= room[r.span, r.span_id, r.daytype, r.epoch] + 1e-6 for r in rows), name
    longest = in_slices(places.space_bouts(spaces), spec).where("epoch <> 'allday'").agg(F.max("minutes")).first()[0]
    assert longest == 360


def test_parts_of_the_day_add_up(spark):
    rows = location.visits(V.point_events(spark, SF), SliceSpec()).groupBy("person_id", (F.col("epoch") == "allday").alias("whole")).agg(F.sum("minutes").alias("m")).collect()
    whole, parts = ({r.person_id: r.m for r in rows if r.whole == w} for w in (True, False))
    assert whole.keys() == parts.keys() and all(abs(whole[p] - parts[p]) < 1e-6 for p in whole)


def test_bouts_break_only_at_their_slices_borders(spark):
    friday = START + 4 * DAY + 22 * 60 * MINUTE  # to Monday, two in the morning
    bout = spark.createDataFrame([(1, friday, friday + 52 * 60 * MINUTE)], "person_id int, start_us bigint, end_us bigint")
    found = in_slices(bout, SliceSpec(("full", "week"), True, True))
    lengths = lambda span, daytype, epoch: sorted(r.minutes for r in found.where((F.col("span") == span) & (F.col("daytype") == daytype) & (F.col("epoch") == epoch)).collect())
    assert lengths("full", "all", "allday") == [52 * 60] and lengths("full", "weekend", "allday") == [48 * 60] and lengths("full", "weekday", "allday") == [120, 120]
    assert lengths("week", "all", "allday") == [120, 50 * 60] and lengths("full", "all", "night") == [120, 360, 360] and lengths("full", "weekend", "evening") == [360, 360]


@pytest.mark.parametrize("centre", [(0.0, 0.0), (65.0, 10.0), (89.9995, 0.0), (-40.0, 179.9999), (40.0, -80.0)])
def test_clusters_anywhere(centre):
    """Two ways to the same labels; groups 30 m wide and 300 m apart are found at every latitude and across the date line."""
    rng = np.random.default_rng(3)
    lat, lon = [], []
    for east in (0, 300, 600):
        m = rng.uniform(-15, 15, (40, 2)) + (0, east)
        lat += (centre[0] + np.degrees(m[:, 0] / 6371008.8)).tolist()
        lon += (centre[1] + np.degrees(m[:, 1] / 6371008.8 / math.cos(math.radians(centre[0])))).tolist()
    lat, lon = np.array(lat), (np.array(lon) + 180) % 360 - 180
    args = (lat, lon, np.ones(120, np.int64), rng.permutation(120), 60.0, 3)
    a, b = location.cluster_dense(*args), location.cluster_cells(*args)
    assert np.array_equal(a, b)
    if abs(centre[0]) < 89:
        assert len(set(a.tolist())) == 3 and -1 not in a and all(len(set(a[i : i + 40].tolist())) == 1 for i in (0, 40, 80))


@pytest.mark.parametrize("seed", range(6))
def test_cells_equal_all_distances(seed):
    rng = np.random.default_rng(seed)
    n = 400
    spread = rng.choice([40, 150, 600])
    lat, lon = 52 + rng.normal(size=n) * spread / 111_000, 4 + rng.normal(size=n) * spread / 68_000
    lat[:20], lon[:20] = lat[0], lon[0]
    args = (lat, lon, rng.integers(1, 3, n), rng.integers(0, 50, n), 60.0, int(rng.choice([3, 5, 9])))
    assert np.array_equal(location.cluster_dense(*args), location.cluster_cells(*args))


def test_samples_of_equal_time_stay_apart(spark):
    rows = [(1, START + i * MINUTE, 40.0, -80.0) for i in (0, 10, 10, 20)] + [(1, START + 30 * MINUTE, 40.1, -80.0)]
    frame = spark.createDataFrame(rows, "person_id int, us bigint, lat double, lon double")
    assert location.visits(frame, SliceSpec(epochs=False)).count() == 5
    assert places.label_spaces(frame, V.places(spark, SF)).count() == 5
    assert location.home_features(frame, SliceSpec(epochs=False)).first().home_10m == 30


def test_neighbours_far_from_the_equator(spark):
    step = math.degrees(20 / 6371008.8)
    rows = [(1, i, 80.0 + i * step, 179.99995 if i % 2 else -179.99995) for i in range(6)]
    frame = spark.createDataFrame(rows, "person_id int, us bigint, lat double, lon double")
    assert baselines._differing(location.neighbours_by_grid(frame), baselines.neighbours_naive(frame)).first()[0] == 0
    assert {r.n for r in location.neighbours_by_grid(frame).collect()} != {1}


def test_maps_are_read_as_written(spark, tmp_path):
    given = V.places(spark, SF)
    back = maps.read_geojson(spark, maps.write_geojson(given))
    key = lambda f: sorted((r.place_id, r.type, r.priority, tuple(map(tuple, r.polygon))) for r in f.collect())
    assert key(back) == key(given) == key(maps.from_wkt(maps.to_wkt(given)))
    collection = '{"type": "FeatureCollection", "features": [{"type": "Feature", "properties": {"place_id": 1, "name": "a", "type": "green", "priority": 5}, "geometry": {"type": "Polygon", "coordinates": [[[0, 0], [1, 0], [1, 2], [0, 0]]]}}, {"type": "Feature", "properties": {"place_id": 2}, "geometry": {"type": "Point", "coordinates": [0, 0]}}]}'
    (tmp_path / "map.json").write_text(collection)
    row = maps.read_geojson(spark, f"file://{tmp_path}/map.json").collect()
    assert len(row) == 1 and [tuple(p) for p in row[0].polygon] == [(0, 0), (0, 1), (2, 1)]
    texts = spark.createDataFrame([("polygon((0 0, 1.5 0, 1 2))",), ("POINT (1 2)",), (None,)], "wkt string")
    assert [r.polygon and [tuple(p) for p in r.polygon] for r in maps.from_wkt(texts).collect()] == [[(0, 0), (0, 1.5), (2, 1)], None, None]


def test_three_clusters_by_halving(monkeypatch):
    rng = np.random.default_rng(2)
    for _ in range(20):
        v = np.unique(rng.normal(size=rng.integers(3, 60)).round(2))
        n = rng.integers(1, 4, len(v)).astype(float)
        if len(v) < 3:
            continue
        whole = proximity.three_clusters(v, n)
        monkeypatch.setattr(proximity, "PAIRS", 0)
        assert abs(proximity.three_clusters(v, n)[0] - whole[0]) < 1e-6
        monkeypatch.undo()


def test_silhouette_rule(spark):
    values = {1: [0.0, 0.1, 5.0, 5.1, 9.0, 9.1], 2: [0.0, 0.1, 0.2, 10.0, 10.1, 10.2]}
    scores = spark.createDataFrame([(p, i, v) for p, vs in values.items() for i, v in enumerate(vs)], "person_id int, address int, score double")
    assert {r.person_id: r.k for r in proximity.choose_k(scores, rule="silhouette").collect()} == {1: 3, 2: 2}


def test_f_values(spark):
    noise = [0.3, -0.2, 0.1, -0.4, 0.2, 0.0, -0.1, 0.3, -0.3, 0.1, 0.2, -0.2]
    rows = [(1, "f", w, float(w if w <= 6 else 30 - 2 * w) + noise[w]) for w in range(12)] + [(2, "f", w, 2.0 * w + noise[w]) for w in range(12)]
    found = {r.person_id: r for r in change.f_values(spark.createDataFrame(rows, "person_id int, feature string, week int, value double")).collect()}
    assert found[1].breakpoint == 6 and found[1].f > 50 > 10 > found[2].f


def test_hourly_spectrum_sees_a_daily_cycle(spark):
    rows = [(1, START + h * 60 * MINUTE, 40 + 0.1 * math.sin(2 * math.pi * h / 24), -80.0) for h in range(240)]
    power = {r.period: r.power for r in baselines.hourly_spectrum(spark.createDataFrame(rows, "person_id int, us bigint, lat double, lon double"), [12.0, 24.0]).collect()}
    assert power[24.0] > 100 * power[12.0]


def test_catalogue():
    names = assemble.features()
    assert len(names) == len(set(names)) > 230 and {n.split(".")[0] for n in names} == set(assemble.CATALOGUE)
    assert [(s, f) for s, _, f in assemble.select(["sleep.awake.m*"])] == [("sleep", ["awake.mean"])]
    with pytest.raises(ValueError):
        assemble.feature_long(None, None, ("nothing",))


def test_measured_plans(spark):
    rows = {r.name: r for r in registry.queries()["plan_costs"](spark, SF).collect()}
    assert rows["partials"].shuffle_bytes > 0 and rows["rows"].exchanges >= 1


def test_labels_are_made_without_a_shuffle(spark):
    plan = places.label_spaces(V.point_events(spark, SF), V.places(spark, SF))._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and plan.count("Exchange hashpartitioning") <= 1  # of the map's cells


def test_cells_agree_with_exact_places(spark):
    row = registry.queries()["cells_agreement"](spark, SF).first()
    assert row.same_noise > 0.95 and row.agreement > 0.95


def test_slices_of_attach_hold_their_rows(spark):
    from kinetrace.plans.slices import lies_in

    spec = SliceSpec.crossed()
    rows = attach(V.events(spark, SF).select("person_id", "us"), spec)
    assert rows.where(~lies_in(spec)).count() == 0
