"""Change of a weekly feature: slopes and the week at which a two-piece line fits best."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

SERIES = ["person_id", "feature"]


def numbered(weekly: DataFrame) -> DataFrame:
    """The series' values as numbers; weeks keep their numbers, only their differences count."""
    return weekly.select(*SERIES, "week", F.col("value").cast("double").alias("value")).where("value is not null")


def slopes(weekly: DataFrame, middle: int | None, min_weeks: int = 3) -> DataFrame:
    """Least-squares slope over all weeks, the weeks up to `middle`, and those from `middle` on (None: the middle of all weeks of the data); one pass."""
    if middle is None:
        first, last = weekly.agg(F.min("week"), F.max("week")).first()
        middle = ((first or 0) + (last or 0)) // 2
    x, y = F.col("week").cast("double"), F.col("value")
    part = lambda c: F.regr_slope(F.when(c, y), F.when(c, x))
    rows = numbered(weekly).groupBy(*SERIES).agg(F.count("*").alias("n"), F.regr_slope(y, x).alias("slope"), part(F.col("week") <= middle).alias("slope_first"), part(F.col("week") >= middle).alias("slope_second"), F.regr_r2(y, x).alias("r2"))
    return rows.where(F.col("n") >= min_weeks)


def bic(rss: Column, n: Column, parameters: Column, floor: Column) -> Column:
    return n * F.log(F.greatest(rss, floor) / n) + parameters * F.log(n)


def candidates(weekly: DataFrame, pieces: str = "joined", min_weeks: int = 3) -> DataFrame:
    """Every week as the break: slopes before and after, rss, bic. Prefix sums make it one ordered pass over a series.

    pieces: joined (one hinge) or free (two lines). Sums are of values centred on the series' means.
    """
    whole = Window.partitionBy(*SERIES)
    upto = whole.orderBy("week").rowsBetween(Window.unboundedPreceding, 0)
    rows = numbered(weekly).withColumn("week0", F.avg(F.col("week")).over(whole)).withColumn("value0", F.avg("value").over(whole))
    x, y = F.col("week") - F.col("week0"), F.col("value") - F.col("value0")
    moments = {"n": F.lit(1.0), "x": x, "y": y, "xx": x * x, "xy": x * y, "yy": y * y}
    sums = rows.select(*SERIES, "week", (F.col("week") - F.col("week0")).alias("b"), *(F.sum(e).over(upto).alias(f"l_{k}") for k, e in moments.items()), *(F.sum(e).over(whole).alias(f"t_{k}") for k, e in moments.items()))
    sums = sums.where(F.col("t_n") >= min_weeks)
    for k in moments:
        sums = sums.withColumn(f"r_{k}", F.col(f"t_{k}") - F.col(f"l_{k}"))
    t = lambda k: F.col(f"t_{k}")
    floor = F.lit(1e-12) * (1 + t("yy"))
    line = F.try_divide(t("xy"), t("xx"))
    line_rss = F.greatest(t("yy") - line * t("xy"), F.lit(0.0))
    if pieces == "joined":
        b = F.col("b")
        r = lambda k: F.col(f"r_{k}")
        h, hh, xh, hy = r("x") - b * r("n"), r("xx") - 2 * b * r("x") + b * b * r("n"), r("xx") - b * r("x"), r("xy") - b * r("y")
        chh, cxh, chy = hh - h * h / t("n"), xh, hy
        det = t("xx") * chh - cxh * cxh
        two = det > 1e-9 * (1 + t("xx") * t("xx"))
        beta, gamma = (t("xy") * chh - chy * cxh) / F.when(two, det), (chy * t("xx") - t("xy") * cxh) / F.when(two, det)
        rss = F.when(two, F.greatest(t("yy") - beta * t("xy") - gamma * chy, F.lit(0.0))).otherwise(line_rss)
        before, after, p = F.coalesce(beta, line), F.coalesce(beta + gamma, line), F.when(two, 3).otherwise(2)
    else:
        def side(s: str):
            c = lambda k: F.col(f"{s}_{k}")
            cxx = c("xx") - F.coalesce(F.try_divide(c("x") * c("x"), c("n")), F.lit(0.0))
            cxy = c("xy") - F.coalesce(F.try_divide(c("x") * c("y"), c("n")), F.lit(0.0))
            cyy = c("yy") - F.coalesce(F.try_divide(c("y") * c("y"), c("n")), F.lit(0.0))
            some = (c("n") >= 2) & (cxx > 1e-9)
            return F.when(some, cxy / cxx), F.when(c("n") >= 1.5, F.greatest(cyy - F.when(some, cxy * cxy / cxx).otherwise(0.0), F.lit(0.0))).otherwise(0.0)

        (before, left), (after, right) = side("l"), side("r")
        rss, p = left + right, F.when(F.col("r_n") < 0.5, 2).otherwise(4)
    out = sums.select(*SERIES, "week", before.alias("slope_before"), after.alias("slope_after"), rss.alias("rss"), p.alias("parameters"), t("n").alias("n"), floor.alias("_floor"))
    return out.withColumn("bic", bic(F.col("rss"), F.col("n"), F.col("parameters"), F.col("_floor"))).drop("_floor")


def breakpoints(weekly: DataFrame, pieces: str = "joined", criterion: str = "bic", min_weeks: int = 3) -> DataFrame:
    """The best week by the criterion (bic or aic), the earliest of equals, with the slopes around it."""
    rows = candidates(weekly, pieces, min_weeks)
    rank = F.round(F.col("bic") - (F.col("parameters") * (F.log("n") - 2) if criterion == "aic" else F.lit(0.0)), 6)
    best = rows.groupBy(*SERIES).agg(F.min(F.struct(rank.alias("measure"), "week", "slope_before", "slope_after", "rss", "parameters")).alias("b"))
    return best.select(*SERIES, F.col("b.week").alias("breakpoint"), "b.slope_before", "b.slope_after", "b.rss", F.col("b.measure").alias(criterion))


def f_values(weekly: DataFrame, pieces: str = "free", min_weeks: int = 6) -> DataFrame:
    """The week whose two pieces fit best, and F: by how much they beat one line, in units of what the pieces leave unexplained."""
    rows = candidates(weekly, pieces, min_weeks)
    line = F.max(F.when(F.col("parameters") == 2, F.col("rss"))).alias("line")  # a break at the last week is one line
    two = F.col("parameters") > 2
    best = rows.groupBy(*SERIES).agg(line, F.min(F.when(two, F.struct(F.round("rss", 6).alias("r"), "week", "rss", "parameters", "n"))).alias("b"))
    b = lambda c: F.col(f"b.{c}")
    f = F.try_divide((F.col("line") - b("rss")) / (b("parameters") - 2), F.greatest(b("rss"), F.lit(1e-9)) / (b("n") - b("parameters")))
    return best.select(*SERIES, b("week").alias("breakpoint"), F.greatest(f, F.lit(0.0)).alias("f"))


def change_features(weekly: DataFrame, middle: int, pieces: str = "joined") -> DataFrame:
    """All six change values of every series."""
    found = breakpoints(weekly, pieces).select(*SERIES, "breakpoint", "slope_before", "slope_after", "bic")
    return slopes(weekly, middle).join(found, SERIES, "left")


def breakpoints_naive(weekly: DataFrame, pieces: str = "free", min_weeks: int = 3) -> DataFrame:
    """Baseline: one regression for each series, week and side, by a range self join (quadratic in the weeks)."""
    rows = numbered(weekly)
    cut = rows.select(*SERIES, F.col("week").alias("cut"))
    both = rows.join(cut, SERIES)
    x, y, left = F.col("week").cast("double"), F.col("value"), F.col("week") <= F.col("cut")
    fit = lambda c, n: (F.regr_slope(F.when(c, y), F.when(c, x)).alias(f"slope_{n}"), (F.regr_syy(F.when(c, y), F.when(c, x)) - F.coalesce(F.regr_slope(F.when(c, y), F.when(c, x)) * F.regr_sxy(F.when(c, y), F.when(c, x)), F.lit(0.0))).alias(f"rss_{n}"), F.count(F.when(c, y)).alias(f"n_{n}"))
    fits = both.groupBy(*SERIES, "cut").agg(*fit(left, "before"), *fit(~left, "after"), F.count("*").cast("double").alias("n"), (F.regr_syy(y, x) * 1e-12 + 1e-12).alias("_floor"))
    rss = F.greatest(F.coalesce("rss_before", F.lit(0.0)), F.lit(0.0)) + F.greatest(F.coalesce("rss_after", F.lit(0.0)), F.lit(0.0))
    scored = fits.where(F.col("n") >= min_weeks).withColumn("bic", F.round(bic(rss, F.col("n"), F.when(F.col("n_after") == 0, 2).otherwise(4), F.col("_floor")), 6))
    best = scored.groupBy(*SERIES).agg(F.min(F.struct("bic", "cut", "slope_before", "slope_after")).alias("b"))
    return best.select(*SERIES, F.col("b.cut").alias("breakpoint"), "b.slope_before", "b.slope_after", "b.bic")
