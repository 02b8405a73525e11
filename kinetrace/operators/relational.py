"""Operators around the methods: joins, aggregates, windows, sets and functions on the given tables."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kinetrace.functions.timeparts import daytype_of, epoch_of, hour_of, micros
from kinetrace.operators import phone, places
from kinetrace.oracles.base import ep
from kinetrace.plans.bouts import ordered
from kinetrace.sources import views as V

E = V.events
DT = "CASE WHEN (us // 86400000000 + 3) % 7 >= 5 THEN 'weekend' ELSE 'weekday' END"


def _cells(s, d):
    return E(s, d).withColumns({"epoch": epoch_of(F.col("us")), "daytype": daytype_of(F.col("us"))})


def as_of(left: DataFrame, right: DataFrame, columns: list[str]) -> DataFrame:
    """Each row of `left` with the person's last `right` columns before or at its time: a union and one ordered window."""
    key = ["person_id", "us"]
    a = left.select(*key, *(F.lit(None).cast(right.schema[c].dataType).alias(c) for c in columns), F.lit(1).alias("_side"), F.struct(*left.columns).alias("_row"))
    b = right.select(*key, *columns, F.lit(0).alias("_side"), F.lit(None).cast(a.schema["_row"].dataType).alias("_row"))
    w = Window.partitionBy("person_id").orderBy("us", "_side").rowsBetween(Window.unboundedPreceding, 0)
    seen = a.union(b).select("_side", "_row", *(F.last(c, ignorenulls=True).over(w).alias(c) for c in columns))
    return seen.where("_side = 1").select("_row.*", *columns)


def range_join(intervals: DataFrame, samples: DataFrame, bucket_us: int = 3_600_000_000) -> DataFrame:
    """person_id, start_us, end_us, us: samples inside half-open intervals by an equi-join on time buckets."""
    at = lambda c: F.floor(c / float(bucket_us))
    left = intervals.where("end_us > start_us").select("person_id", "start_us", "end_us", F.explode(F.sequence(at(F.col("start_us")), at(F.col("end_us") - 1))).alias("_b"))
    right = samples.select("person_id", "us", at(F.col("us")).alias("_b"))
    return left.join(right, ["person_id", "_b"]).where("us >= start_us and us < end_us").drop("_b")


def overlap_join(a: DataFrame, b: DataFrame, bucket_us: int = 86_400_000_000) -> DataFrame:
    """Pairs of overlapping intervals of a person, each once: in the bucket in which the overlap begins."""
    spread = lambda x, n: x.where("end_us > start_us").select("person_id", F.col("start_us").alias(f"{n}_start"), F.col("end_us").alias(f"{n}_end"), F.explode(F.sequence(F.floor(F.col("start_us") / float(bucket_us)), F.floor((F.col("end_us") - 1) / float(bucket_us)))).alias("_b"))
    both = spread(a, "a").join(spread(b, "b"), ["person_id", "_b"])
    start, end = F.greatest("a_start", "b_start"), F.least("a_end", "b_end")
    return both.where((start < end) & (F.floor(start / float(bucket_us)) == F.col("_b"))).withColumn("minutes", (end - start) / 60e6).drop("_b")


def _spaces(s, d):
    return places.space_bouts(places.label_spaces(V.point_events(s, d), V.places(s, d)))


def _lateral(s, d):
    c, o = V.table(s, d, "customer"), V.table(s, d, "orders")
    top = o.where(F.col("o_custkey") == F.col("c_custkey").outer()).orderBy(F.desc("o_totalprice"), "o_orderkey").limit(3).select("o_orderkey", "o_totalprice")
    return c.lateralJoin(top).select(F.col("c_custkey").alias("person_id"), "o_orderkey", "o_totalprice")


def cleaned(rows: DataFrame, key: list[str]) -> DataFrame:
    """Records with a time, a value that isn't negative, and each key once (the earliest of equals)."""
    first = F.row_number().over(Window.partitionBy(*key).orderBy("us"))
    return rows.where(F.col("us").isNotNull() & (F.col("value") >= 0)).withColumn("_nth", first).where("_nth = 1").drop("_nth")


def _cleaning(s, d):
    """The events with rows uploaded twice, negative values and missing times, cleaned; what went and why."""
    e = E(s, d).select("event_id", "us", "value", "k")
    dirty = e.union(e.where("k < 20")).union(e.where("k = 30").withColumn("value", F.lit(-1.0))).union(e.where("k = 40").withColumn("us", F.lit(None).cast("bigint")))
    bad = dirty.agg(F.count("*").alias("given"), F.count_if(F.col("us").isNull()).alias("missing"), F.count_if(F.col("value") < 0).alias("negative"))
    kept = cleaned(dirty, ["event_id"]).agg(F.count("*").alias("kept"), F.sum("value").alias("total"))
    return bad.join(F.broadcast(kept)).withColumn("repeated", F.col("given") - F.col("missing") - F.col("negative") - F.col("kept"))


def _sketches(s, d):
    """Estimates of sketches of bounded size beside the exact values; ok: within the sketch's error."""
    li = V.table(s, d, "lineitem").select("l_partkey", F.col("l_extendedprice").alias("p"))
    kll = F.kll_sketch_agg_double("p")
    r = li.agg(
        F.approx_count_distinct("l_partkey", 0.02).cast("double").alias("hll"), F.count_distinct("l_partkey").cast("double").alias("distinct"), F.percentile_approx("p", 0.5, 10000).alias("gk"), kll.alias("sketch"), F.percentile("p", 0.5).alias("median"), F.stddev_pop("p").alias("sd"),
    )
    near = lambda e, x, most: (F.abs(F.col(e) - F.col(x)) <= most).cast("int")
    r = r.withColumn("kll", F.kll_sketch_get_quantile_double("sketch", F.lit(0.5)))
    rows = F.array(*(F.struct(F.lit(n).alias("sketch"), F.col(x).alias("exact"), ok.alias("ok")) for n, x, ok in (("hll", "distinct", near("hll", "distinct", 0.1 * F.col("distinct"))), ("gk", "median", near("gk", "median", 0.05 * F.col("sd"))), ("kll", "median", near("kll", "median", 0.1 * F.col("sd"))))))
    return r.select(F.explode(rows).alias("x")).select("x.*")


def _bucketed(s, d):
    """Steps written as a table bucketed by person and joined with itself by day: the join reads the buckets without a shuffle."""
    import uuid

    name = f"kinetrace_steps_{uuid.uuid4().hex}"
    V.step_events(s, d).withColumn("day", F.floor(F.col("us") / 86_400_000_000.0)).write.bucketBy(8, "person_id").sortBy("person_id", "us").format("parquet").saveAsTable(name)
    rows = s.table(name)
    return rows.groupBy("person_id").agg(F.sum("steps").alias("total")).join(rows.groupBy("person_id").agg(F.count_distinct("day").alias("days")).hint("merge"), "person_id")


def _roundtrip(s, d):
    """Rows that differ after writing in each file format and reading back."""
    import uuid

    base = s.conf.get("spark.checkpoint.dir", None) or s.conf.get("spark.sql.warehouse.dir")
    rows = V.step_events(s, d).groupBy("person_id").agg(F.sum("steps").alias("total"))
    out = None
    for kind in ("parquet", "orc", "json", "csv"):
        path = f"{base.rstrip('/')}/kinetrace/sink-{uuid.uuid4().hex}"
        rows.write.format(kind).save(path)
        back = s.read.schema(rows.schema).format(kind).load(path)
        one = back.exceptAll(rows).union(rows.exceptAll(back)).agg(F.lit(kind).alias("kind"), F.count("*").alias("differing"))
        out = one if out is None else out.union(one)
    return out


def _sql_view(s, d):
    V.step_events(s, d).createOrReplaceTempView("kinetrace_steps")
    return s.sql("SELECT person_id, sum(steps) AS total, max(steps) AS most FROM kinetrace_steps GROUP BY person_id")


def _udf(s, d):
    @F.pandas_udf("double")
    def km(lat: pd.Series, lon: pd.Series) -> pd.Series:
        import numpy as np

        a = np.sin(np.radians(lat - 40) / 2) ** 2 + np.cos(np.radians(40)) * np.cos(np.radians(lat)) * np.sin(np.radians(lon + 80) / 2) ** 2
        return pd.Series(2 * 6371.0088 * np.arcsin(np.sqrt(a)))

    return V.point_events(s, d).select("person_id", "us", km("lat", "lon").alias("km"))


def _udtf(s, d):
    from pyspark.sql.functions import udtf

    @udtf(returnType="us: bigint, minutes: double")
    class Clip:
        def eval(self, start: int, end: int):
            step = 21_600_000_000
            at = start
            while at < end:
                to = min(end, at - at % step + step)
                yield at, (to - at) / 60e6
                at = to

    s.udtf.register("kinetrace_clip", Clip)
    phone.interaction_bouts(V.screen_events(s, d)).createOrReplaceTempView("kinetrace_bouts")
    return s.sql("SELECT b.person_id, c.us, c.minutes FROM kinetrace_bouts b, LATERAL kinetrace_clip(b.start_us, b.end_us) c")


def _udaf(s, d):
    @F.pandas_udf("double")
    def spread(v: pd.Series) -> float:
        return float(v.max() - v.min())

    return E(s, d).groupBy("person_id").agg(spread("value").alias("spread"))


COLS = "person_id:b us:b "
QUERIES = [
    ("op_scan_filter_project", "event_id:b k:b value:d", lambda s, d: _cells(s, d).where("epoch = 'morning' and value between 20 and 80").select("event_id", "k", "value"), f"SELECT event_id, k, value FROM ev WHERE {ep('us')} = 'morning' AND value BETWEEN 20 AND 80"),
    ("op_clean_records", "given:b missing:b negative:b repeated:b kept:b total:d", _cleaning, "SELECT n + twice + neg + gone AS given, gone AS missing, neg AS negative, twice AS repeated, n AS kept, total FROM (SELECT count(*) AS n, count(*) FILTER (k < 20) AS twice, count(*) FILTER (k = 30) AS neg, count(*) FILTER (k = 40) AS gone, sum(value) AS total FROM ev)"),
    ("op_join_broadcast", "nation:s n:b", lambda s, d: E(s, d).join(V.person_dim(s, d), "person_id").groupBy("nation").agg(F.count("*").alias("n")), "SELECT n_name AS nation, count(*) AS n FROM ev JOIN customer ON c_custkey = person_id JOIN nation ON n_nationkey = c_nationkey GROUP BY ALL"),
    ("op_join_sort_merge", "status:s n:b total:d", lambda s, d: V.table(s, d, "orders").hint("merge").join(V.table(s, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy(F.col("o_orderstatus").alias("status")).agg(F.count("*").alias("n"), F.sum("l_quantity").alias("total")), "SELECT o_orderstatus AS status, count(*) AS n, sum(l_quantity) AS total FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY ALL"),
    ("op_join_shuffle_hash", "segment:s n:b", lambda s, d: V.table(s, d, "orders").join(V.table(s, d, "customer").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).groupBy(F.col("c_mktsegment").alias("segment")).agg(F.count("*").alias("n")), "SELECT c_mktsegment AS segment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY ALL"),
    ("op_join_outer", "person_id:b calls:b", lambda s, d: V.table(s, d, "customer").select(F.col("c_custkey").alias("person_id")).join(V.call_orders(s, d).groupBy("person_id").agg(F.count("*").alias("calls")), "person_id", "left").fillna(0, ["calls"]), "SELECT c_custkey AS person_id, count(o_orderkey) AS calls FROM customer LEFT JOIN (SELECT * FROM orders WHERE o_orderstatus IN ('O','F','P')) ON o_custkey = c_custkey GROUP BY ALL"),
    ("op_join_full_outer", "person_id:b events:b calls:b", lambda s, d: E(s, d).where("k < 3").groupBy("person_id").agg(F.count("*").alias("events")).join(V.call_orders(s, d).where("correspondent < 2").groupBy("person_id").agg(F.count("*").alias("calls")), "person_id", "full"), "SELECT person_id, events, calls FROM (SELECT person_id, count(*) AS events FROM ev WHERE k < 3 GROUP BY ALL) FULL JOIN (SELECT o_custkey AS person_id, count(*) AS calls FROM orders WHERE o_orderstatus IN ('O','F','P') AND o_orderkey % 12 < 2 GROUP BY ALL) USING (person_id)"),
    ("op_join_semi", "doc_id:b", lambda s, d: V.table(s, d, "documents").join(V.table(s, d, "labels"), "doc_id", "left_semi").select("doc_id"), "SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)"),
    ("op_join_anti", "doc_id:b", lambda s, d: V.table(s, d, "documents").join(V.table(s, d, "labels"), "doc_id", "left_anti").select("doc_id"), "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)"),
    ("op_join_range", "person_id:b start_us:b us:b", lambda s, d: range_join(phone.interaction_bouts(V.screen_events(s, d)), V.step_events(s, d)), "SELECT b.person_id, b.start_us, s.us FROM ibout b JOIN step s ON s.person_id = b.person_id AND s.us >= b.start_us AND s.us < b.end_us"),
    ("op_join_asof", "person_id:b us:b lat:d lon:d", lambda s, d: as_of(V.call_events(s, d), V.point_events(s, d).select("person_id", "us", "lat", "lon"), ["lat", "lon"]), "SELECT c.person_id, c.us, p.lat, p.lon FROM calls c ASOF LEFT JOIN pt p ON p.person_id = c.person_id AND p.us <= c.us"),
    ("op_join_interval_overlap", "person_id:b minutes:d", lambda s, d: overlap_join(_spaces(s, d), phone.interaction_bouts(V.screen_events(s, d))).groupBy("person_id").agg(F.sum("minutes").alias("minutes")), "SELECT a.person_id, sum((least(a.end_us, b.end_us) - greatest(a.start_us, b.start_us)) / 60e6::DOUBLE) AS minutes FROM spb a JOIN ibout b ON a.person_id = b.person_id AND a.start_us < b.end_us AND b.start_us < a.end_us AND a.end_us > a.start_us AND b.end_us > b.start_us GROUP BY ALL"),
    ("op_join_lateral_topk", "person_id:b o_orderkey:b o_totalprice:d", _lateral, "SELECT o_custkey AS person_id, o_orderkey, o_totalprice FROM orders JOIN customer ON c_custkey = o_custkey QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 3"),
    ("op_join_cross_grid", "person_id:b epoch:s n:b", lambda s, d: E(s, d).select("person_id").distinct().crossJoin(F.broadcast(s.createDataFrame([(e,) for e in ("night", "morning", "afternoon", "evening")], "epoch string"))).join(_cells(s, d).groupBy("person_id", "epoch").agg(F.count("*").alias("n")), ["person_id", "epoch"], "left").fillna(0, ["n"]), f"SELECT g.person_id, g.epoch, count(us) AS n FROM (SELECT DISTINCT person_id, unnest(['night','morning','afternoon','evening']) AS epoch FROM ev) g LEFT JOIN (SELECT *, {ep('us')} AS epoch FROM ev) e ON e.person_id = g.person_id AND e.epoch = g.epoch GROUP BY ALL"),
    ("op_agg_distinct", "event_type:s persons:b", lambda s, d: E(s, d).groupBy("event_type", "person_id").count().groupBy("event_type").agg(F.count("*").alias("persons")), "SELECT event_type, count(DISTINCT person_id) AS persons FROM ev GROUP BY ALL"),
    ("op_agg_conditional", "event_type:s big:b total:d", lambda s, d: E(s, d).groupBy("event_type").agg(F.count_if(F.col("value") > 50).alias("big"), F.sum(F.when(F.col("value") > 50, F.col("value"))).alias("total")), "SELECT event_type, count(*) FILTER (value > 50) AS big, sum(value) FILTER (value > 50) AS total FROM ev GROUP BY ALL"),
    ("op_agg_moments", "event_type:s m:d v:d sd:d", lambda s, d: E(s, d).groupBy("event_type").agg(F.avg("value").alias("m"), F.var_pop("value").alias("v"), F.stddev_samp("value").alias("sd")), "SELECT event_type, avg(value) AS m, var_pop(value) AS v, stddev_samp(value) AS sd FROM ev GROUP BY ALL"),
    ("op_agg_regr", "event_type:s slope:d r2:d", lambda s, d: E(s, d).groupBy("event_type").agg(F.regr_slope("value", "k").alias("slope"), F.regr_r2("value", "k").alias("r2")), "SELECT event_type, regr_slope(value, k) AS slope, regr_r2(value, k) AS r2 FROM ev GROUP BY ALL"),
    ("op_agg_cube", "epoch:s daytype:s n:b", lambda s, d: _cells(s, d).cube("epoch", "daytype").agg(F.count("*").alias("n")), f"SELECT epoch, daytype, count(*) AS n FROM (SELECT {ep('us')} AS epoch, {DT} AS daytype FROM ev) GROUP BY CUBE (epoch, daytype)"),
    ("op_agg_rollup", "epoch:s event_type:s n:b", lambda s, d: _cells(s, d).rollup("epoch", "event_type").agg(F.count("*").alias("n")), f"SELECT epoch, event_type, count(*) AS n FROM (SELECT {ep('us')} AS epoch, event_type FROM ev) GROUP BY ROLLUP (epoch, event_type)"),
    ("op_agg_grouping_sets", "epoch:s daytype:s n:b", lambda s, d: _cells(s, d).groupingSets([["epoch"], ["daytype"]], "epoch", "daytype").agg(F.count("*").alias("n")), f"SELECT epoch, daytype, count(*) AS n FROM (SELECT {ep('us')} AS epoch, {DT} AS daytype FROM ev) GROUP BY GROUPING SETS ((epoch), (daytype))"),
    ("op_agg_percentiles", "event_type:s median:d p90:d", lambda s, d: E(s, d).groupBy("event_type").agg(F.percentile("value", 0.5).alias("median"), F.percentile("value", 0.9).alias("p90")), "SELECT event_type, quantile_cont(value, 0.5) AS median, quantile_cont(value, 0.9) AS p90 FROM ev GROUP BY ALL"),
    ("op_agg_sketches", "sketch:s exact:d ok:b", _sketches, "SELECT 'hll' AS sketch, count(DISTINCT l_partkey) AS exact, 1 AS ok FROM lineitem UNION ALL SELECT unnest(['gk', 'kll']), median(l_extendedprice), 1 FROM lineitem"),
    ("op_agg_collect_map", "person_id:b places:b entropy:d", lambda s, d: V.point_events(s, d).groupBy("person_id", "pl").count().groupBy("person_id").agg(F.map_from_entries(F.collect_list(F.struct("pl", "count"))).alias("m")).select("person_id", F.size("m").alias("places"), F.aggregate(F.map_values("m"), F.lit(0.0), lambda a, n: a + n * F.log(n.cast("double")), lambda a: F.log(F.aggregate(F.map_values("m"), F.lit(0.0), lambda x, n: x + n)) - a / F.aggregate(F.map_values("m"), F.lit(0.0), lambda x, n: x + n)).alias("entropy")), "SELECT person_id, count(*) AS places, ln(sum(n)) - sum(n * ln(n)) / sum(n) AS entropy FROM (SELECT person_id, pl, count(*) AS n FROM pt GROUP BY ALL) GROUP BY ALL"),
    ("op_pivot", "person_id:b night:b morning:b afternoon:b evening:b", lambda s, d: _cells(s, d).groupBy("person_id").pivot("epoch", ["night", "morning", "afternoon", "evening"]).count().fillna(0), "SELECT person_id, " + ", ".join(f"count(*) FILTER ({ep('us')} = '{e}') AS {e}" for e in ("night", "morning", "afternoon", "evening")) + " FROM ev GROUP BY ALL"),
    ("op_unpivot", "c_custkey:b field:s v:s", lambda s, d: V.table(s, d, "customer").select("c_custkey", "c_name", "c_mktsegment").unpivot("c_custkey", ["c_name", "c_mktsegment"], "field", "v"), "SELECT c_custkey, 'c_name' AS field, c_name AS v FROM customer UNION ALL SELECT c_custkey, 'c_mktsegment', c_mktsegment FROM customer"),
    ("op_win_rank", COLS + "r:b dr:b", lambda s, d: E(s, d).select("person_id", "us", F.rank().over(Window.partitionBy("person_id").orderBy("k")).alias("r"), F.dense_rank().over(Window.partitionBy("person_id").orderBy("k")).alias("dr")), "SELECT person_id, us, rank() OVER w AS r, dense_rank() OVER w AS dr FROM ev WINDOW w AS (PARTITION BY person_id ORDER BY k)"),
    ("op_win_analytic", COLS + "before:d after:d first:d", lambda s, d: E(s, d).select("person_id", "us", F.lag("value").over(ordered()).alias("before"), F.lead("value").over(ordered()).alias("after"), F.first("value").over(ordered()).alias("first")), "SELECT person_id, us, lag(value) OVER w AS before, lead(value) OVER w AS after, first_value(value) OVER w AS first FROM ev WINDOW w AS (PARTITION BY person_id ORDER BY us)"),
    ("op_win_rows", COLS + "moving:d running:d", lambda s, d: E(s, d).select("person_id", "us", F.avg("value").over(ordered().rowsBetween(-2, 0)).alias("moving"), F.sum("value").over(ordered().rowsBetween(Window.unboundedPreceding, 0)).alias("running")), "SELECT person_id, us, avg(value) OVER (PARTITION BY person_id ORDER BY us ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS moving, sum(value) OVER (PARTITION BY person_id ORDER BY us ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS running FROM ev"),
    ("op_win_range", COLS + "day_total:d", lambda s, d: E(s, d).select("person_id", "us", F.sum("value").over(ordered().rangeBetween(-86_400_000_000, 0)).alias("day_total")), "SELECT person_id, us, sum(value) OVER (PARTITION BY person_id ORDER BY us RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS day_total FROM ev"),
    ("op_win_ntile", COLS + "q:b pr:d", lambda s, d: E(s, d).select("person_id", "us", F.ntile(4).over(ordered()).alias("q"), F.percent_rank().over(ordered()).alias("pr")), "SELECT person_id, us, ntile(4) OVER w AS q, percent_rank() OVER w AS pr FROM ev WINDOW w AS (PARTITION BY person_id ORDER BY us)"),
    ("op_topk_global", "l_orderkey:b l_linenumber:b l_extendedprice:d", lambda s, d: V.table(s, d, "lineitem").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber", "l_partkey").limit(50), "SELECT * FROM lineitem ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber, l_partkey LIMIT 50"),
    ("op_topk_group", "person_id:b event_id:b r:b", lambda s, d: E(s, d).withColumn("r", F.row_number().over(Window.partitionBy("person_id").orderBy(F.desc("value"), "event_id"))).where("r <= 3"), "SELECT person_id, event_id, row_number() OVER (PARTITION BY person_id ORDER BY value DESC, event_id) AS r FROM ev QUALIFY r <= 3"),
    ("op_set_union", "person_id:b", lambda s, d: E(s, d).select("person_id").union(V.call_orders(s, d).select("person_id")).distinct(), "SELECT person_id FROM ev UNION SELECT o_custkey FROM orders WHERE o_orderstatus IN ('O','F','P')"),
    ("op_set_intersect", "person_id:b", lambda s, d: E(s, d).select("person_id").intersect(V.call_orders(s, d).select("person_id")), "SELECT person_id FROM ev INTERSECT SELECT o_custkey FROM orders WHERE o_orderstatus IN ('O','F','P')"),
    ("op_set_except", "person_id:b", lambda s, d: V.call_orders(s, d).select("person_id").exceptAll(E(s, d).select("person_id")).distinct(), "SELECT DISTINCT o_custkey AS person_id FROM (SELECT o_custkey, row_number() OVER (PARTITION BY o_custkey) AS i FROM orders WHERE o_orderstatus IN ('O','F','P')) o LEFT JOIN (SELECT person_id, count(*) AS n FROM ev GROUP BY ALL) e ON e.person_id = o.o_custkey WHERE i > coalesce(n, 0)"),
    ("op_fn_string", "page_id:b host:s bytes:b hash:s", lambda s, d: V.table(s, d, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host"), F.octet_length("html").alias("bytes"), F.sha2("url", 256).alias("hash")), "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, strlen(html) AS bytes, sha256(url) AS hash FROM pages"),
    ("op_fn_date", "event_id:b hour:b epoch:s daytype:s", lambda s, d: _cells(s, d).withColumn("hour", hour_of(F.col("us"))), f"SELECT event_id, us // 3600000000 % 24 AS hour, {ep('us')} AS epoch, {DT} AS daytype FROM ev"),
    ("op_fn_math", "vec_id:b norm:d", lambda s, d: V.table(s, d, "embeddings").select("vec_id", F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))).alias("norm")), "SELECT vec_id, sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE))) AS norm FROM embeddings"),
    ("op_fn_array_map", "vec_id:b positive:b top:d", lambda s, d: V.table(s, d, "embeddings").select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.array_max("embedding").alias("top")), "SELECT vec_id, len(list_filter(embedding, lambda x: x > 0)) AS positive, list_max(embedding) AS top FROM embeddings"),
    ("op_fn_json", "event_id:b k:b", lambda s, d: V.table(s, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k")), "SELECT event_id, k FROM ev"),
    ("op_udf_arrow", "person_id:b us:b km:d", _udf, "SELECT person_id, us, 2 * 6371.0088::DOUBLE * asin(sqrt(power(sin(radians(lat - 40) / 2), 2) + cos(radians(40)) * cos(radians(lat)) * power(sin(radians(lon + 80) / 2), 2))) AS km FROM pt"),
    ("op_udaf_grouped", "person_id:b spread:d", _udaf, "SELECT person_id, max(value) - min(value) AS spread FROM ev GROUP BY ALL"),
    ("op_udtf_clip", "person_id:b us:b minutes:d", _udtf, "SELECT person_id, greatest(start_us, f) AS us, (least(end_us, f + 21600000000) - greatest(start_us, f)) / 60e6::DOUBLE AS minutes FROM (SELECT *, unnest(range(start_us // 21600000000 * 21600000000, end_us, 21600000000)) AS f FROM ibout WHERE end_us > start_us)"),
    ("op_sql_view", "person_id:b total:b most:b", _sql_view, "SELECT person_id, sum(steps) AS total, max(steps) AS most FROM step GROUP BY ALL"),
    ("op_sink_bucketed", "person_id:b total:b days:b", _bucketed, "SELECT person_id, sum(steps) AS total, count(DISTINCT us // 86400000000) AS days FROM step GROUP BY ALL"),
    ("op_sink_roundtrip", "kind:s differing:b", _roundtrip, None),
    ("op_text_passthrough", "kind:s texts:b rows:b", lambda s, d: V.table(s, d, "documents").select("text", F.lit("document").alias("kind")).union(V.table(s, d, "benchmark").select("text", F.lit("benchmark"))).groupBy("kind", "text").agg(F.count("*").alias("n")).join(V.table(s, d, "documents").groupBy("text").agg(F.count("*").alias("held")), "text", "left").groupBy("kind").agg(F.count_if(F.coalesce("held", F.lit(0)) > F.when(F.col("kind") == "document", 1).otherwise(0)).alias("texts"), F.sum("n").alias("rows")), "SELECT kind, count(*) FILTER (held > CASE kind WHEN 'document' THEN 1 ELSE 0 END) AS texts, sum(n) AS rows FROM (SELECT 'document' AS kind, text, count(*) AS n FROM documents GROUP BY ALL UNION ALL SELECT 'benchmark', text, count(*) FROM benchmark GROUP BY ALL) LEFT JOIN (SELECT text, count(*) AS held FROM documents GROUP BY ALL) USING (text) GROUP BY ALL"),
    ("op_dim_names", "person:s device:s scans:b", lambda s, d: V.table(s, d, "lineitem").groupBy("l_suppkey", "l_partkey").agg(F.count("*").alias("scans")).join(V.table(s, d, "supplier"), F.col("l_suppkey") == F.col("s_suppkey")).join(V.table(s, d, "part"), F.col("l_partkey") == F.col("p_partkey")).groupBy(F.col("s_name").alias("person"), F.col("p_name").alias("device")).agg(F.sum("scans").alias("scans")), "SELECT s_name AS person, p_name AS device, count(*) AS scans FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN part ON l_partkey = p_partkey GROUP BY ALL"),
]
