"""Devices near a person: scores, exact one-dimensional clusters, owners, and statistics of scans."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kinetrace.functions.timeparts import day_of
from kinetrace.plans.slices import KEYS, SliceSpec, attach, part_of

GROUPS = ("all", "self", "related", "others")


def scan_days(scans: DataFrame, keys: tuple[str, ...] = ("person_id",)) -> DataFrame:
    """Days seen, scans and scans per day seen of each address; two levels, so no distinct sets are held."""
    daily = scans.groupBy(*keys, "address", day_of(F.col("us")).alias("day")).count()
    found = daily.groupBy(*keys, "address").agg(F.count("*").alias("days"), F.sum("count").alias("scans"))
    return found.withColumn("frequency", F.col("scans") / F.col("days"))


def device_scores(scans: DataFrame, keys: tuple[str, ...] = ("person_id",)) -> DataFrame:
    """Sum of the two z-values (population deviation within a person; no spread counts as 0)."""
    w = Window.partitionBy(*keys)
    z = lambda c: F.coalesce(F.try_divide(F.col(c) - F.avg(c).over(w), F.stddev_pop(c).over(w)), F.lit(0.0))
    return scan_days(scans, keys).withColumn("score", F.round(z("days") + z("frequency"), 9))


def _prefix(scores: DataFrame, keys: tuple[str, ...]) -> DataFrame:
    points = scores.groupBy(*keys, F.col("score").alias("v")).agg(F.count("*").alias("n"))
    w = Window.partitionBy(*keys).orderBy("v").rowsBetween(Window.unboundedPreceding, 0)
    whole = Window.partitionBy(*keys)
    n, v = F.col("n"), F.col("v")
    moments = {"W": n, "S": n * v, "Q": n * v * v}
    return points.select(*keys, "v", *(F.sum(e).over(w).alias(k) for k, e in moments.items()), *(F.sum(e).over(whole).alias(f"T{k}") for k, e in moments.items()), F.count("*").over(whole).alias("m"))


def _cost(w, s, q):
    return F.greatest(q - F.coalesce(F.try_divide(s * s, w), F.lit(0.0)), F.lit(0.0))


def best_split2(scores: DataFrame, keys: tuple[str, ...] = ("person_id",)) -> DataFrame:
    """keys, cut (last value of the low cluster), sse of the best two clusters; cut is null with one value only."""
    p = _prefix(scores, keys)
    sse = F.round(_cost(F.col("W"), F.col("S"), F.col("Q")) + _cost(F.col("TW") - F.col("W"), F.col("TS") - F.col("S"), F.col("TQ") - F.col("Q")), 7)
    best = p.where("W < TW or m = 1").groupBy(*keys).agg(F.min(F.struct(sse.alias("sse"), F.when(F.col("m") > 1, F.col("v")).alias("cut"))).alias("b"))
    return best.select(*keys, "b.cut", "b.sse")


#: Distinct scores up to which all pairs of cuts are tried at once; beyond, best first cuts are found by halving, since they don't fall as the second cut rises.
PAIRS = 1500


def three_clusters(v: np.ndarray, n: np.ndarray) -> tuple[float, int, int]:
    """(error, last index of the low cluster, of the middle one) of the best three clusters of sorted values with multiplicity; the least cuts of equals."""
    w, s, q = (np.concatenate(([0.0], np.cumsum(x))) for x in (n, n * v, n * v * v))
    m = len(v)

    def cost(i, j):  # values i to j - 1
        mass = w[j] - w[i]
        return np.maximum(q[j] - q[i] - (s[j] - s[i]) ** 2 / np.where(mass > 0, mass, 1), 0)

    if m <= PAIRS:
        i, j = np.triu_indices(m - 1, 1)
        total = np.round(cost(0, i + 1) + cost(i + 1, j + 1) + cost(j + 1, m), 7)
        best = int(np.lexsort((j, i, total))[0])
        return float(total[best]), int(i[best]), int(j[best])
    first, error = np.zeros(m, np.int64), np.full(m, np.inf)
    todo = [(1, m - 2, 0, m - 3)]
    while todo:
        a, b, low, high = todo.pop()
        if a > b:
            continue
        j = (a + b) // 2
        i = np.arange(low, min(high, j - 1) + 1)
        total = cost(0, i + 1) + cost(i + 1, j + 1)
        first[j], error[j] = i[int(total.argmin())], total.min() + cost(j + 1, m)
        todo += [(a, j - 1, low, int(first[j])), (j + 1, b, int(first[j]), high)]
    j = int(error.argmin())
    return float(np.round(error[j], 7)), int(first[j]), j


def best_split3(scores: DataFrame, keys: tuple[str, ...] = ("person_id",)) -> DataFrame:
    """keys, cut1, cut2, sse of the best three clusters; fewer distinct values give fewer cuts and no error."""
    points = scores.groupBy(*keys, F.col("score").alias("v")).agg(F.count("*").alias("n"))

    def run(t: pa.Table) -> pa.Table:
        order = np.argsort(t.column("v").to_numpy())
        v, n = t.column("v").to_numpy()[order], t.column("n").to_numpy()[order].astype(float)
        sse, cut1, cut2 = 0.0, None, None
        if len(v) >= 3:
            sse, i, j = three_clusters(v, n)
            cut1, cut2 = float(v[i]), float(v[j])
        elif len(v) == 2:
            cut2 = float(v[0])
        given = [t.column(k).slice(0, 1).combine_chunks() for k in keys]
        return pa.Table.from_arrays([*given, pa.array([cut1], pa.float64()), pa.array([cut2], pa.float64()), pa.array([sse], pa.float64())], [*keys, "cut1", "cut2", "sse"])

    kinds = ", ".join(f"{k} {points.schema[k].dataType.simpleString()}" for k in keys)
    return points.groupBy(*keys).applyInArrow(run, f"{kinds}, cut1 double, cut2 double, sse double")


def choose_k(scores: DataFrame, keys: tuple[str, ...] = ("person_id",), rule: str = "sse") -> DataFrame:
    """keys, sse2, sse3, k, low_cut, high_cut. rule: sse (two clusters only if strictly better), bic, gain (three if they take off
    more than three quarters of the error of two), silhouette (the larger mean silhouette to cluster centres), fixed2, fixed3."""
    two = best_split2(scores, keys).select(*keys, "cut", F.col("sse").alias("sse2"))
    three = best_split3(scores, keys).select(*keys, "cut1", "cut2", F.col("sse").alias("sse3"))
    joined = two.join(three, [*keys])
    if rule == "bic":
        size = scores.groupBy(*keys).agg(F.count("*").alias("n"))
        joined = joined.join(size, [*keys])
        bic = lambda sse, k: F.col("n") * F.log(F.greatest(F.col(sse) / F.col("n"), F.lit(1e-9))) + k * F.log("n")
        pick = bic("sse2", 2) < bic("sse3", 3)
    elif rule == "silhouette":
        joined = joined.join(silhouettes(scores.join(joined, [*keys]), keys), [*keys])
        pick = F.col("silhouette2") >= F.col("silhouette3")
    else:
        pick = {"sse": F.col("sse2") < F.col("sse3"), "gain": F.col("sse2") - F.col("sse3") <= 0.75 * F.col("sse2"), "fixed2": F.lit(True), "fixed3": F.lit(False)}[rule]
    return joined.select(*keys, "sse2", "sse3", F.when(pick, 2).otherwise(3).alias("k"), F.when(~pick, F.col("cut1")).alias("low_cut"), F.when(pick, F.col("cut")).otherwise(F.col("cut2")).alias("high_cut"))


def silhouettes(rows: DataFrame, keys: tuple[str, ...]) -> DataFrame:
    """keys, silhouette2, silhouette3: mean over devices (score, cut, cut1, cut2) of 1 - distance to the own cluster's centre / distance to the nearest other;
    0 where a model has one cluster."""
    out = rows
    for name, side in (("2", F.when(F.col("score") <= F.col("cut"), 0).otherwise(1)), ("3", F.when(F.col("score") <= F.col("cut1"), 0).when(F.col("score") <= F.col("cut2"), 1).otherwise(2))):
        out = out.withColumn(f"_s{name}", side)
        for c in range(int(name)):
            out = out.withColumn(f"_c{name}{c}", F.avg(F.when(F.col(f"_s{name}") == c, F.col("score"))).over(Window.partitionBy(*keys)))
        away = [F.abs(F.col("score") - F.col(f"_c{name}{c}")) for c in range(int(name))]
        own = F.element_at(F.array(*away), F.col(f"_s{name}") + 1)
        other = F.array_min(F.array(*(F.when(F.col(f"_s{name}") != c, away[c]) for c in range(int(name)))))
        out = out.withColumn(f"_v{name}", F.round(F.coalesce(1 - F.try_divide(own, F.greatest(own, other)), F.lit(0.0)), 9))
        out = out.withColumn(f"_v{name}", F.when(other.isNull(), 0.0).otherwise(F.col(f"_v{name}")))
    return out.groupBy(*keys).agg(F.round(F.avg("_v2"), 7).alias("silhouette2"), F.round(F.avg("_v3"), 7).alias("silhouette3"))


def label_devices(scans: DataFrame, keys: tuple[str, ...] = ("person_id",), rule: str = "sse") -> DataFrame:
    """Each address with its score and owner: a model is only two cuts, so labels are comparisons."""
    scores = device_scores(scans, keys)
    model = choose_k(scores, keys, rule)
    own = F.when(F.col("high_cut").isNull() | (F.col("score") > F.col("high_cut")), "self").when(F.col("low_cut").isNotNull() & (F.col("score") > F.col("low_cut")), "related").otherwise("others")
    return scores.join(model, [*keys]).select(*keys, "address", "days", "scans", "score", "k", own.alias("owner"))


def scan_features(scans: DataFrame, spec: SliceSpec | None = None, scope: str = "global") -> DataFrame:
    """Six statistics of scans per device for all devices and for each owner. scope: clusters of all data or of each slice."""
    parts = scans.groupBy("person_id", "address", part_of()).agg(F.count("*").alias("scans"))
    cells = attach(parts, spec or SliceSpec())
    keys = ("person_id",) if scope == "global" else ("person_id", *KEYS)
    labels = label_devices(scans if scope == "global" else attach(scans, spec or SliceSpec()), keys).select(*keys, "address", "owner")
    counts = cells.groupBy("person_id", *KEYS, "address").agg(F.sum("scans").alias("scans"))
    grouped = counts.join(labels, [*keys, "address"]).withColumn("owners", F.explode(F.array(F.lit("all"), "owner")))
    return grouped.groupBy("person_id", *KEYS, "owners").agg(
        F.count("*").alias("devices"), F.max("scans").alias("most"), F.min("scans").alias("least"), F.sum("scans").alias("total"), F.avg("scans").alias("mean"), F.stddev_pop("scans").alias("std")
    )


def lloyd(scores: DataFrame, k: int, restarts: int = 8, rounds: int = 50, seed: int = 11, starts: list[list[float]] | None = None) -> DataFrame:
    """person_id, centres, sse by the usual iteration with seeded restarts; `starts` fixes the first centres."""

    def run(t: pa.Table) -> pa.Table:
        x = np.sort(t.column("score").to_numpy())
        rng, best = np.random.default_rng(seed), (np.inf, np.zeros(0))
        for first in starts or [rng.choice(x, min(k, len(x)), replace=False) for _ in range(restarts)]:
            c = np.asarray(first, float)
            for _ in range(rounds):
                near = np.abs(x[:, None] - c).argmin(1)
                new = np.array([x[near == j].mean() if (near == j).any() else c[j] for j in range(len(c))])
                if np.array_equal(new, c):
                    break
                c = new
            sse = float(((x[:, None] - c) ** 2).min(1).sum())
            if sse < best[0]:
                best = (sse, np.sort(c))
        return pa.table({"person_id": [t.column("person_id")[0].as_py()], "centres": pa.array([best[1].tolist()], pa.list_(pa.float64())), "sse": [best[0]]})

    return scores.select("person_id", "score").groupBy("person_id").applyInArrow(run, "person_id bigint, centres array<double>, sse double")
