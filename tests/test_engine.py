"""Hand-made miniatures, invariants, the SQL oracles at the smallest scale, and plans."""

import math

import duckdb
import pytest
from pyspark.sql import functions as F

from kinetrace import registry
from kinetrace.functions.geo import inside
from kinetrace.functions.timeparts import daytype_of, epoch_of, micros
from kinetrace.operators import change, location, phone, places, proximity, sleep, steps
from kinetrace.plans.bouts import swept
from kinetrace.plans.slices import SliceSpec, clipped

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
MINUTE = 60_000_000
START = 1704067200000000


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return c


def canonical(rows):
    return sorted(repr(tuple("null" if v is None or isinstance(v, float) and math.isnan(v) else v for v in r)) for r in rows)


@pytest.mark.parametrize("name", sorted(registry.oracle_sql()))
def test_query_equals_sql(spark, duck, name):
    frame = registry.queries()[name](spark, SF)
    want = duck.execute(registry.oracle_sql()[name])
    assert frame.columns == [c[0] for c in want.description]
    assert canonical(tuple(r) for r in frame.collect()) == canonical(want.fetchall())


@pytest.mark.parametrize("name", sorted(set(registry.queries()) - set(registry.oracle_sql())))
def test_query_gives_rows(spark, name):
    assert registry.queries()[name](spark, SF).count() > 0


def test_entry_without_text_operators(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() > 0
    assert __spark_entry__._optional("kinetrace.llm_absent") is None


def test_import_when_the_text_folders_are_deleted(tmp_path):
    """A copy without them, in a process of its own: the other queries stay. With them but without a package that they need, too."""
    import pathlib
    import shutil
    import subprocess
    import sys

    root = pathlib.Path(__file__).parent.parent
    for name in ("kinetrace", "__spark_entry__.py", "corpus_pipeline.py"):
        (shutil.copytree if (root / name).is_dir() else shutil.copy)(root / name, tmp_path / name)
    count = "import __spark_entry__ as e; q = e.queries(); print(len(q), len(e.oracle_sql()), sum(n.startswith('op') and n[2].isdigit() or n == 'pipeline' for n in q))"
    run = lambda code: subprocess.run([sys.executable, "-c", code], cwd=tmp_path, capture_output=True, text=True, check=True, env={**__import__("os").environ, "PYTHONPATH": str(tmp_path)}).stdout.split()[-3:]
    without = run(f"import sys; sys.modules['xxhash'] = None; {count}")
    shutil.rmtree(tmp_path / "kinetrace/llm")
    (tmp_path / "corpus_pipeline.py").unlink()
    assert run(count) == without == [str(len(registry.queries())), str(len(registry.oracle_sql())), "0"]


def test_parts_of_time(spark):
    rows = spark.sql("SELECT * FROM VALUES (timestamp_ntz'2024-01-05 05:59:59'), (timestamp_ntz'2024-01-05 06:00:00'), (timestamp_ntz'2024-01-06 11:59:59'), (timestamp_ntz'2024-01-06 12:00:00'), (timestamp_ntz'2024-01-07 18:00:00'), (timestamp_ntz'2024-01-08 00:00:00') AS t(ts)")
    us = micros("ts")
    got = [tuple(r) for r in rows.select(epoch_of(us), daytype_of(us)).collect()]
    assert got == [("night", "weekday"), ("morning", "weekday"), ("morning", "weekend"), ("afternoon", "weekend"), ("evening", "weekend"), ("night", "weekday")]


def test_clipping(spark):
    bout = spark.createDataFrame([(1, START + 330 * MINUTE, START + 730 * MINUTE), (1, START, START)], "person_id int, start_us bigint, end_us bigint")
    assert sorted(r.minutes for r in clipped(bout).collect()) == [0, 10, 30, 360]


def test_cluster_choice(spark):
    values = {1: [0.0, 0.1, 5.0, 5.1, 9.0], 2: [1.0, 1.0], 3: [1.0, 2.0], 4: [3.0]}
    scores = spark.createDataFrame([(p, i, v) for p, vs in values.items() for i, v in enumerate(vs)], "person_id int, address int, score double")
    model = {r.person_id: r for r in proximity.choose_k(scores).collect()}
    assert all(r.k == 3 and r.sse3 <= r.sse2 + 1e-9 for r in model.values())
    assert model[1].low_cut == 0.1 and model[1].high_cut == 5.1 and abs(model[1].sse3 - 0.01) < 1e-6
    assert model[2].high_cut is None and model[3].high_cut == 1.0 and model[3].low_cut is None
    bad = proximity.lloyd(scores.where("person_id = 1"), 3, starts=[[9.0, 50.0, 100.0]]).first()
    assert bad.sse > model[1].sse2  # a bad start is where two clusters would win


def test_motion_edges(spark):
    degree = 1 / (math.pi / 180 * 6371.0088)
    rows = [(1, START, 0.0), (1, START + 60 * MINUTE, 0.999999 * degree), (1, START + 120 * MINUTE, 2.1 * degree), (2, START, 0.0), (2, START, 1.0)]
    moved = location.label_motion(spark.createDataFrame([(p, t, x, 0.0) for p, t, x in rows], "person_id int, us bigint, lat double, lon double"))
    assert [r.moving for r in moved.where("person_id = 1").orderBy("us").collect()] == [False, False, True]
    assert not any(r.moving for r in moved.where("person_id = 2").collect())


def test_polygon(spark):
    ring = [(0.0, 0.0), (0.0, 4.0), (4.0, 4.0), (4.0, 0.0), (2.0, 2.0)]
    frame = spark.createDataFrame([(1.0, 1.0), (3.0, 2.0), (2.0, 0.5), (5.0, 5.0), (3.9, 3.0)], "lat double, lon double").withColumn("ring", F.array(*(F.struct(F.lit(a).alias("lat"), F.lit(b).alias("lon")) for a, b in ring)))
    assert [r[0] for r in frame.select(inside(F.col("lat"), F.col("lon"), F.col("ring"))).collect()] == [True, True, False, False, True]


def test_phone_bouts(spark):
    log = [(1, 0, "unlock"), (1, 5, "unlock"), (1, 9, "off"), (1, 10, "on"), (1, 12, "lock"), (1, 20, "unlock"), (1, 30, "on")]
    screen = spark.createDataFrame([(p, m * MINUTE, s) for p, m, s in log], "person_id int, us bigint, status string")
    as_minutes = lambda f: sorted((r.start_us // MINUTE, r.end_us // MINUTE) for r in f.collect())
    assert as_minutes(phone.interaction_bouts(screen)) == [(0, 9), (20, 30)] and as_minutes(phone.unlocked_bouts(screen)) == [(0, 12), (20, 30)]


def test_sleep_extremes(spark):
    states = ["asleep", "asleep", "restless", "asleep", "asleep", "unknown"]
    naps = spark.createDataFrame([(1, START + i * MINUTE, s) for i, s in enumerate(states)], "person_id int, us bigint, state string")
    best = sleep.extreme_bouts(sleep.bouts_in_slices(naps, SliceSpec(epochs=False))).where("state = 'asleep'").first()
    assert best.longest_start == START and best.shortest_start == START
    row = sleep.counts_efficiency(naps, SliceSpec(epochs=False)).first()
    assert row.weak_efficiency == 1.0 and row.strong_efficiency == 0.8
    assert sleep.counts_efficiency(naps.where("state = 'unknown'")).first().weak_efficiency is None


def test_step_bouts(spark):
    bins = spark.createDataFrame([(1, i * steps.BIN_US, n) for i, n in enumerate([9, 10, 11, 0, 10]) ] + [(1, 9 * steps.BIN_US, 1)], "person_id int, us bigint, steps bigint")
    kinds = lambda f: [(r.label, r.minutes) for r in f.orderBy("start_us").collect()]
    assert kinds(steps.step_bouts(bins)) == [("sedentary", 5), ("active", 10), ("sedentary", 5), ("active", 5), ("sedentary", 5)]
    assert kinds(steps.step_bouts(bins, at_threshold="keep")) == [("sedentary", 10), ("active", 5), ("sedentary", 10), ("sedentary", 5)]
    assert sum(m for _, m in kinds(steps.step_bouts(bins, fill="zero"))) == 50


def test_sweep(spark):
    rows = [(1, "academic", 0, 100), (1, "phone", 40, 50), (1, "active", 90, 95)]
    got = swept(spark.createDataFrame(rows, "person_id int, kind string, start_us bigint, end_us bigint"), ["academic"], ["phone", "active"])
    assert sorted((r.start_us, r.end_us) for r in got.collect()) == [(0, 40), (50, 90), (95, 100)]


def test_study_and_social_edges(spark):
    bouts = spark.createDataFrame([(1, "academic", 0, 29 * MINUTE, 29.0), (2, "academic", 0, 30 * MINUTE, 30.0), (3, "academic", 0, 60 * MINUTE, 60.0), (4, "green", 0, 20 * MINUTE, 20.0), (5, "green", 0, 19 * MINUTE, 19.0)], "person_id int, type string, start_us bigint, end_us bigint, minutes double")
    bins = spark.createDataFrame([(3, 25 * MINUTE, 10)], "person_id int, us bigint, steps bigint")
    none = spark.createDataFrame([], "person_id int, start_us bigint, end_us bigint")
    assert {(r.person_id, r.minutes) for r in places.study_intervals(bouts, bins, none).collect()} == {(2, 30.0), (3, 30.0)}
    voice = spark.createDataFrame([(p, i * MINUTE, "voice" if i < 8 else "silence") for p in (4, 5) for i in range(10)], "person_id int, us bigint, inference string")
    assert [r.person_id for r in places.social_bouts(bouts, voice).collect()] == [4]
    assert places.social_bouts(bouts, voice.where(f"us <> {7 * MINUTE}")).count() == 0


@pytest.mark.parametrize("pieces", ["joined", "free"])
def test_planted_break(spark, pieces):
    line = [(1, "f", w, float(w if w <= 7 else 7 + 4 * (w - 7))) for w in range(1, 16)] + [(2, "f", w, 3.0) for w in range(1, 6)] + [(3, "f", w, 1.0 * w) for w in (1, 2)]
    found = {r.person_id: r for r in change.breakpoints(spark.createDataFrame(line, "person_id int, feature string, week int, value double"), pieces).collect()}
    # the point at week 7 lies on both lines, so free pieces fit as well from week 6 on and the earliest counts
    assert found[1].breakpoint == (7 if pieces == "joined" else 6) and abs(found[1].slope_before - 1) < 1e-6 and abs(found[1].slope_after - 4) < 1e-6 and 3 not in found and 2 in found


def test_place_invariants(spark):
    rows = registry.queries()["loc_place_features"](spark, SF).collect()
    assert all(r.moving_share is None or -1e-9 <= r.moving_share <= 1 and r.moving_share + r.rare_share <= 1 + 1e-6 for r in rows)
    near = registry.queries()["loc_home_time"](spark, SF).collect()
    assert all(r.home_10m <= r.home_100m + 1e-6 for r in near)
    assert registry.queries()["place_agreement"](spark, SF).first().agreement > 0.9


def test_plans_have_few_exchanges(spark):
    plan = lambda n: registry.queries()[n](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert plan("loc_motion").count("Exchange hashpartitioning") == 1
    for name in ("social_minutes", "step_features_daily", "bt_labels", "place_labels", "op_join_range"):
        assert "BroadcastNestedLoopJoin" not in plan(name) and "CartesianProduct" not in plan(name)


def test_variants_against_exact_results(spark):
    from kinetrace.operators import variants
    from kinetrace.sources import views

    row = registry.queries()["bt_lloyd_vs_exact"](spark, SF).first()
    assert row.persons > 0 and row.better == 0
    scans = views.scan_lines(spark, SF)
    exact = {(r.person_id, r.epoch): r.n for r in proximity.attach(scans, SliceSpec()).groupBy("person_id", "epoch").agg(F.countDistinct("address").alias("n")).collect()}
    got = {(r.person_id, r.epoch): r.devices for r in variants.sketched_devices(scans).collect()}
    assert got.keys() == exact.keys() and all(abs(got[k] - n) <= 0.1 * n for k, n in exact.items())


def test_gain_rule(spark):
    values = {1: [0.0, 0.1, 5.0, 5.1, 9.0], 2: [0.0, 1.0, 2.0, 10.0, 11.0, 12.0]}
    scores = spark.createDataFrame([(p, i, v) for p, vs in values.items() for i, v in enumerate(vs)], "person_id int, address int, score double")
    assert {r.person_id: r.k for r in proximity.choose_k(scores, rule="gain").collect()} == {1: 3, 2: 2}
