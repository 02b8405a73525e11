"""Sensor streams as views of the given tables. They stand in for sensors; they aren't sensor data."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kinetrace.functions.timeparts import day_of, div, micros, week_of

TYPES = ["social_greek", "greek", "apartment", "residence", "athletic", "green", "academic", "off_campus"]
MINUTE = 60_000_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "events")
    return rows.select("event_id", F.col("user_id").alias("person_id"), "ts", micros("ts").alias("us"), "event_type", "value", F.get_json_object("props", "$.k").cast("int").alias("k"))


def scan_events(spark, sf_dir):
    return events(spark, sf_dir).select("person_id", "us", (F.col("k") % 10).alias("address"))


def scan_lines(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("person_id"), micros("l_shipdate").alias("us"), (F.col("l_partkey") % 50).cast("int").alias("address"))


def call_events(spark, sf_dir):
    kind = F.create_map(*map(F.lit, ("click", "incoming", "view", "outgoing", "error", "missed")))[F.col("event_type")]
    return events(spark, sf_dir).select("person_id", "us", kind.alias("direction"), F.col("k").alias("correspondent"), F.col("value").alias("duration_s")).where("direction is not null")


def call_orders(spark, sf_dir):
    kind = F.create_map(*map(F.lit, ("O", "incoming", "F", "outgoing", "P", "missed")))[F.col("o_orderstatus")]
    return table(spark, sf_dir, "orders").select(
        F.col("o_custkey").alias("person_id"), micros("o_orderdate").alias("us"), kind.alias("direction"), (F.col("o_orderkey") % 12).cast("int").alias("correspondent"), (F.col("o_totalprice") / 1000).alias("duration_s")
    ).where("direction is not null")


def contacts_of(calls: DataFrame) -> DataFrame:
    kind = F.element_at(F.array(F.lit("family"), F.lit("friend_off"), F.lit("friend_on")), F.col("correspondent") % 4 + 1)
    return calls.select("person_id", "correspondent").distinct().where("correspondent % 4 < 3").withColumn("category", kind)


def point_events(spark, sf_dir):
    e = events(spark, sf_dir).withColumn("pl", F.when(F.col("k") < 90, (F.col("person_id") + F.col("k") % 4) % 25).otherwise(F.col("k") % 25))
    cents = F.round(F.col("value") * 100).cast("bigint")
    lat = 40 + 0.02 * F.floor(F.col("pl") / 5) + (cents % 97 / 97.0 - 0.5) * 0.0008
    lon = -80 + 0.02 * (F.col("pl") % 5) + (cents % 89 / 89.0 - 0.5) * 0.0008
    return e.select("person_id", "us", lat.alias("lat"), lon.alias("lon"), "pl")


def places(spark, sf_dir):
    n = F.col("n_nationkey")
    lat, lon = 40 + 0.02 * F.floor(n / 5), -80 + 0.02 * (n % 5)
    corner = lambda a, b: F.struct((lat + a).alias("lat"), (lon + b).alias("lon"))
    ring = F.array(corner(-0.001, -0.001), corner(-0.001, 0.001), corner(0.001, 0.001), corner(0.001, -0.001))
    base = table(spark, sf_dir, "nation").where(n % 8 < 7).select(n.alias("place_id"), F.col("n_name").alias("name"), (n % 8).alias("code"), ring.alias("polygon"))
    both = base.unionByName(base.where("code = 0").withColumn("code", F.lit(1)))
    return both.select("place_id", "name", F.element_at(F.array(*map(F.lit, TYPES)), F.col("code") + 1).alias("type"), F.col("code").alias("priority"), "polygon")


def screen_events(spark, sf_dir):
    kind = F.create_map(*map(F.lit, ("click", "unlock", "view", "on", "error", "off", "purchase", "lock")))[F.col("event_type")]
    return events(spark, sf_dir).select("person_id", "us", kind.alias("status")).where("status is not null")


def voice_events(spark, sf_dir):
    v = F.col("value")
    return events(spark, sf_dir).select("person_id", "us", F.when(v < 15, "silence").when(v < 50, "voice").when(v < 80, "noise").otherwise("unknown").alias("inference"))


def voice_turns(spark, sf_dir):
    kind = F.create_map(*map(F.lit, ("user", "voice", "assistant", "noise", "system", "silence")))[F.col("role")]
    start = 1704067200000000
    return table(spark, sf_dir, "conversations").select((F.col("conv_id") % 15).alias("person_id"), (start + F.col("conv_id") * 60 * MINUTE + F.col("turn") * MINUTE).alias("us"), kind.alias("inference"))


def sleep_events(spark, sf_dir):
    kind = F.when(F.col("event_type") == "click", "asleep").when(F.col("event_type") == "view", "restless").when(F.col("event_type") == "error", "awake").otherwise("unknown")
    return events(spark, sf_dir).select("person_id", "us", kind.alias("state"))


def sleep_lines(spark, sf_dir):
    from pyspark.sql import Window

    order = Window.partitionBy("l_suppkey").orderBy("l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_quantity", "l_extendedprice")
    q = F.col("l_quantity")
    kind = F.when(q <= 30, "asleep").when(q <= 40, "restless").when(q <= 47, "awake").otherwise("unknown")
    minute = (F.row_number().over(order) - 1).cast("bigint")
    return table(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("person_id"), (1704067200000000 + minute * MINUTE).alias("us"), kind.alias("state"))


def step_events(spark, sf_dir):
    return events(spark, sf_dir).select("person_id", "us", F.floor("value").alias("steps"))


def step_words(spark, sf_dir):
    words = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("person_id"), F.posexplode(F.split("text", " ")).alias("i", "word"))
    return words.select("person_id", (1704067200000000 + F.col("i").cast("bigint") * MINUTE).alias("us"), (F.length("word") % 4).cast("bigint").alias("steps"))


def weekly_lines(spark, sf_dir):
    rows = table(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("person_id"), week_of(micros("l_shipdate")).alias("week"), "l_quantity", "l_discount")
    wide = rows.groupBy("person_id", "week").agg(F.count("*").cast("double").alias("lines"), F.sum("l_quantity").alias("quantity"), F.avg("l_discount").alias("discount"))
    return wide.unpivot(["person_id", "week"], ["lines", "quantity", "discount"], "feature", "value")


def person_dim(spark, sf_dir):
    c, n, r = (table(spark, sf_dir, x) for x in ("customer", "nation", "region"))
    joined = c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).join(F.broadcast(r), n.n_regionkey == r.r_regionkey)
    return joined.select(F.col("c_custkey").alias("person_id"), F.col("c_mktsegment").alias("segment"), F.col("n_name").alias("nation"), F.col("r_name").alias("region"))
