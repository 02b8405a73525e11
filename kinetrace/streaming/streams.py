"""The event table as a stream of files, and queries over it; state is bounded by a watermark.

Uploads wait for Wi-Fi, so rows come late and in bursts: the default watermark is 48 hours.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

LATE = "48 hours"
#: Event time of the row that ends a finite run, and a watermark that only this row brings about (ms).
END, ENDED = "2200-01-01 00:00:00", 7_226_000_000_000
HOUR_US = 3_600_000_000


def shared(spark: SparkSession) -> str:
    """The folder that the cluster shares: that of checkpoints, or the warehouse."""
    return (spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.sql.warehouse.dir")).rstrip("/") + "/kinetrace"


def _end_row(spark: SparkSession, like: DataFrame) -> DataFrame:
    """A stream of one row of nobody, which moves the watermark past all others when the run's only batch ends."""
    path = f"{shared(spark)}/end-{uuid.uuid4().hex}"
    given = {"person_id": F.lit(-1), "at": F.lit(END), "event_type": F.lit("click")}
    spark.range(1).select(*(given.get(f.name, F.lit(None)).cast(f.dataType).alias(f.name) for f in like.schema)).write.parquet(path)
    return spark.readStream.schema(like.schema).parquet(path)


def stream_of(spark: SparkSession, sf_dir: str, late: str = LATE, ends: bool = False) -> DataFrame:
    """Events as a stream with an event-time column of type timestamp; `ends`: what a state holds is flushed after the last row."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    rows = spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet").option("recursiveFileLookup", "true").parquet(f"{sf_dir}/events.parquet*")
    k = F.get_json_object("props", "$.k").cast("int").alias("k")
    rows = rows.select("event_id", F.col("user_id").alias("person_id"), F.col("ts").cast("timestamp").alias("at"), "event_type", "value", k)
    return (rows.union(_end_row(spark, rows)) if ends else rows).withWatermark("at", late)


def finished(stream: DataFrame) -> DataFrame:
    """Everything the stream holds now, run once through the engine, appended to a Parquet sink and read back: neither results nor state stay in the driver."""
    spark, name = stream.sparkSession, f"kinetrace_{uuid.uuid4().hex}"
    path = f"{shared(spark)}/{name}"
    stream.writeStream.format("parquet").option("path", f"{path}/rows").option("checkpointLocation", f"{path}/state").outputMode("append").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/rows")


def steps_tumbling(stream: DataFrame) -> DataFrame:
    return stream.groupBy("person_id", F.window("at", "5 minutes").alias("w")).agg(F.sum(F.floor("value")).alias("steps")).select("person_id", F.unix_micros("w.start").alias("us"), "steps")


def scans_sliding(stream: DataFrame) -> DataFrame:
    return stream.groupBy("person_id", F.window("at", "1 hour", "15 minutes").alias("w")).agg(F.count("*").alias("scans")).select("person_id", F.unix_micros("w.start").alias("us"), "scans")


def session_bouts(stream: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return stream.groupBy("person_id", F.session_window("at", gap).alias("w")).agg(F.count("*").alias("n")).select("person_id", F.unix_micros("w.start").alias("start_us"), "n")


def deduplicated(stream: DataFrame) -> DataFrame:
    """Re-uploaded rows go: each event once within the watermark."""
    return stream.union(stream).dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "person_id")


def with_contacts(stream: DataFrame, contacts: DataFrame) -> DataFrame:
    """Calls with their contact's category: a stream joined to a table."""
    calls = stream.where("event_type in ('click', 'view', 'error')").select("event_id", "person_id", F.col("k").alias("correspondent"))
    return calls.join(contacts, ["person_id", "correspondent"], "left").select("event_id", "person_id", "category")


def late_accounts(spark: SparkSession, sf_dir: str, late: str = LATE) -> DataFrame:
    """arrived, late, repeated, accepted: rows of a stream that uploads rows again and rows beyond the watermark, none lost without a count.

    Two runs of one query: the table's rows, then a tenth of them again and a tenth 90 days too late. Arrivals are observed metrics of the
    progress, late rows those that the deduplication drops by the watermark."""
    path = f"{shared(spark)}/late-{uuid.uuid4().hex}"
    rows = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", F.col("user_id").alias("person_id"), F.col("ts").cast("timestamp").alias("at"), F.get_json_object("props", "$.k").cast("int").alias("k"))
    arrived = dropped = 0

    def run() -> None:
        nonlocal arrived, dropped
        stream = spark.readStream.schema(rows.schema).parquet(f"{path}/in").withWatermark("at", late).observe("arrivals", F.count(F.lit(1)).alias("n"))
        query = stream.dropDuplicatesWithinWatermark(["event_id"]).writeStream.format("parquet").option("path", f"{path}/out").option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start()
        query.awaitTermination()
        for p in query.recentProgress:
            arrived += p.observedMetrics["arrivals"]["n"] if "arrivals" in p.observedMetrics else 0
            dropped += sum(o.numRowsDroppedByWatermark for o in p.stateOperators)

    rows.write.mode("append").parquet(f"{path}/in")
    run()
    newest = rows.agg(F.max("at").alias("newest"))
    again = rows.join(F.broadcast(newest), F.col("at") > F.col("newest") - F.expr(f"interval {late}")).drop("newest").where("k >= 50")
    old = rows.where("k < 10").withColumns({"event_id": -F.col("event_id") - 1, "at": F.col("at") - F.expr("interval 90 days")})
    again.union(old).write.mode("append").parquet(f"{path}/in")
    run()
    accepted = spark.read.schema(rows.schema).parquet(f"{path}/out").agg(F.count("*").alias("accepted"))
    return accepted.select(F.lit(arrived).alias("arrived"), F.lit(dropped).alias("late"), (F.lit(arrived - dropped) - F.col("accepted")).alias("repeated"), "accepted")


def upserted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """person_id, day, quarter, n, total kept up to date batch by batch: a batch's partial sums are merged with the table's last version.

    A version is written whole under its batch's number, so a batch that is run again after a failure gives the same."""
    path = f"{shared(spark)}/partials-{uuid.uuid4().hex}"
    key = ["person_id", "day", "quarter"]

    def merge(batch: DataFrame, number: int) -> None:
        session = batch.sparkSession
        hour = F.floor(F.unix_micros("at") / 3.6e9)
        new = batch.groupBy("person_id", F.floor(hour / 24).alias("day"), F.floor(F.pmod(hour, F.lit(24)) / 6).alias("quarter")).agg(F.count("*").alias("n"), F.sum("value").alias("total"))
        if number:
            new = session.read.parquet(f"{path}/v{number - 1}").union(new).groupBy(*key).agg(F.sum("n").alias("n"), F.sum("total").alias("total"))
        new.write.mode("overwrite").parquet(f"{path}/v{number}")

    query = stream_of(spark, sf_dir).writeStream.foreachBatch(merge).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.parquet(f"{path}/v{query.lastProgress.batchId}")


def unlock_to_close(stream: DataFrame, hours: int = 6) -> DataFrame:
    """Unlocks joined with closings within some hours: two streams with time bounds, so state ends."""
    a = stream.where("event_type = 'click'").select("person_id", F.col("at").alias("opened"))
    b = stream.where("event_type in ('error', 'purchase')").select(F.col("person_id").alias("p"), F.col("at").alias("closed"))
    joined = a.join(b, (F.col("person_id") == F.col("p")) & (F.col("closed") > F.col("opened")) & (F.col("closed") <= F.col("opened") + F.expr(f"interval {hours} hours")))
    return joined.select("person_id", F.unix_micros("opened").alias("opened_us"), F.unix_micros("closed").alias("closed_us"))


def screen_states(stream: DataFrame, cap_hours: int = 24) -> DataFrame:
    """Interaction bouts by a state machine: rows wait until the watermark has passed them and are then taken in order.

    A bout that nothing closes within `cap_hours` ends there, by the next row or by a timer. After the last row of a
    stream that `ends`, an open bout ends with the person's last sample, if that is sooner.
    """
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    cap, ended = cap_hours * HOUR_US, ENDED

    def step(key, batches, state: GroupState):
        held, opened, last = state.get if state.exists else ([], -1, -1)
        held = [tuple(x) for x in held]
        for p in batches:
            held += [(int(t), str(s)) for t, s in zip(p["us"], p["status"], strict=True)]
        mark = state.getCurrentWatermarkMs() * 1000
        held.sort()
        ready, held = [r for r in held if r[0] < mark], [r for r in held if r[0] >= mark]
        out = []
        for us, status in ready:
            if opened >= 0 and us > opened + cap:
                out.append((key[0], opened, opened + cap))
                opened = -1
            if status == "unlock":
                opened = us if opened < 0 else opened
            elif opened >= 0 and status in ("off", "lock"):
                out.append((key[0], opened, us))
                opened = -1
            last = us
        if opened >= 0 and mark >= ended * 1000:
            out.append((key[0], opened, last))
            opened = -1
        elif opened >= 0 and mark > opened + cap:
            out.append((key[0], opened, opened + cap))
            opened = -1
        state.update(([(a, b) for a, b in held], opened, last))
        due = [us for us, _ in held[:1]] + [opened + cap] * (opened >= 0)
        if due:
            state.setTimeoutTimestamp(max(min(due) // 1000 + 1, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame(out, columns=["person_id", "start_us", "end_us"])

    status = F.when(F.col("event_type") == "click", "unlock").when(F.col("event_type") == "view", "on").when(F.col("event_type") == "error", "off").when(F.col("event_type") == "purchase", "lock")
    rows = stream.select("person_id", "at", F.unix_micros("at").alias("us"), status.alias("status")).where("status is not null")
    return rows.groupBy("person_id").applyInPandasWithState(step, "person_id bigint, start_us bigint, end_us bigint", "held array<struct<us:bigint,status:string>>, opened bigint, last bigint", "append", GroupStateTimeout.EventTimeTimeout)
