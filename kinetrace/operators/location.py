"""Mobility: motion, circadian rhythm, significant places, and what time at them tells."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kinetrace.functions.geo import RADIUS_KM, haversine_km
from kinetrace.functions.timeparts import HOUR, epoch_of
from kinetrace.plans.bouts import ordered
from kinetrace.plans.slices import KEYS, SliceSpec, attach, clipped, lies_in, stretch, time_in_slices

EPS_M, MIN_POINTS, MOVING_KMH = 60.0, 3, 1.0
PERIODS_H = (6.0, 48.0)
BAND_H = (23.5, 24.5)


def label_motion(points: DataFrame, threshold: float = MOVING_KMH) -> DataFrame:
    """km and hours since the person's sample before, speed, and whether it moves (faster than the threshold)."""
    last = lambda c: F.lag(c).over(ordered())
    rows = points.withColumn("km", haversine_km(last("lat"), last("lon"), F.col("lat"), F.col("lon"))).withColumn("hours", (F.col("us") - last("us")) / 3.6e9)
    rows = rows.withColumn("speed", F.try_divide("km", "hours"))
    return rows.withColumn("moving", F.coalesce(F.col("speed") > threshold, F.lit(False)))


def mobility_basic(points: DataFrame, spec: SliceSpec | None = None) -> DataFrame:
    """Location variance and its log, distance, mean and variance of speed."""
    rows = attach(label_motion(points), spec or SliceSpec()).groupBy("person_id", *KEYS)
    out = rows.agg((F.var_pop("lat") + F.var_pop("lon")).alias("variance"), F.sum("km").alias("distance_km"), F.avg("speed").alias("speed_mean"), F.var_pop("speed").alias("speed_variance"))
    return out.withColumn("log_variance", F.log(F.nullif(F.round("variance", 15), F.lit(0.0))))


def periodogram(points: DataFrame, periods: list[float], spec: SliceSpec | None = None) -> DataFrame:
    """Lomb-Scargle power of latitude and longitude at each period (hours), from one pass of mergeable sums.

    The phase that makes sines and cosines orthogonal is applied to the sums afterwards.
    """
    spec = spec or SliceSpec(epochs=False)
    rows = attach(points, spec)
    grid = rows.withColumn("period", F.explode(F.array(*map(F.lit, periods))))
    angle = F.lit(2 * math.pi) * (F.col("us") - spec.origin * 86_400_000_000) / 3.6e9 / F.col("period")
    c, s = F.cos(angle), F.sin(angle)
    sums = {"n": F.lit(1.0), "C": c, "S": s, "C2": F.cos(2 * angle), "S2": F.sin(2 * angle)}
    for axis, base in (("lat", 40.0), ("lon", -80.0)):
        y = F.col(axis) - base
        sums |= {f"{axis}_y": y, f"{axis}_c": y * c, f"{axis}_s": y * s}
    g = grid.groupBy("person_id", *KEYS, "period").agg(*(F.sum(e).alias(k) for k, e in sums.items()))
    theta, r = F.atan2("S2", "C2") / 2, F.sqrt(F.col("C2") ** 2 + F.col("S2") ** 2)
    power = F.lit(0.0)
    for axis in ("lat", "lon"):
        mean = F.col(f"{axis}_y") / F.col("n")
        yc, ys = F.col(f"{axis}_c") - mean * F.col("C"), F.col(f"{axis}_s") - mean * F.col("S")
        a, b = yc * F.cos(theta) + ys * F.sin(theta), ys * F.cos(theta) - yc * F.sin(theta)
        power = power + a * a / (F.col("n") + r) + F.when(F.col("n") - r > 1e-6, b * b / F.when(F.col("n") - r > 1e-6, F.col("n") - r)).otherwise(0.0)
    return g.select("person_id", *KEYS, "period", "n", power.alias("power"))


def circadian(points: DataFrame, spec: SliceSpec | None = None, band: tuple[float, float] = BAND_H, normalise: str = "log", step: float = 0.1) -> DataFrame:
    """Energy around 24 hours: its log, or its share of the energy of all periods from 6 to 48 hours."""
    near = [round(band[0] + step * i, 6) for i in range(round((band[1] - band[0]) / step) + 1)]
    if normalise == "log":
        p = periodogram(points, near, spec)
        return p.groupBy("person_id", *KEYS).agg(F.sum("power").alias("e"), F.max("n").alias("n")).select("person_id", *KEYS, F.log(F.nullif(F.round("e", 12), F.lit(0.0))).alias("circadian"))
    far = sorted({*near, *(float(h) for h in range(int(PERIODS_H[0]), int(PERIODS_H[1]) + 1))})
    p = periodogram(points, far, spec)
    inside = F.col("period").between(*band)
    return p.groupBy("person_id", *KEYS).agg(F.try_divide(F.sum(F.when(inside, F.col("power")).otherwise(0.0)), F.sum("power")).alias("circadian"))


#: Points up to which all distances are taken at once; more are sorted into cells.
DENSE = 300


def _metres(lat1, lon1, lat2, lon2) -> np.ndarray:
    p1, p2, dl = np.radians(lat1), np.radians(lat2), np.radians(lon2 - lon1)
    h = np.sin((p2 - p1) / 2) ** 2 + np.cos(p1) * np.cos(p2) * np.sin(dl / 2) ** 2
    return 2000 * RADIUS_KM * np.arcsin(np.minimum(np.sqrt(h), 1))


def _roots(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The least row that each row reaches over the pairs."""
    root = np.arange(n)
    while len(a):
        low = np.minimum(root[a], root[b])
        new = root.copy()
        np.minimum.at(new, root[a], low)
        np.minimum.at(new, root[b], low)
        while not np.array_equal(new, new[new]):
            new = new[new]
        if np.array_equal(new, root):
            break
        root = new
    return root


def _numbered(root: np.ndarray, core: np.ndarray, rank: np.ndarray) -> np.ndarray:
    """Labels of core rows, numbered by the earliest core row of each cluster; -1 for others."""
    label = np.full(len(root), -1)
    if core.any():
        groups, back = np.unique(root[core], return_inverse=True)
        position = np.empty(len(root), np.int64)
        position[np.lexsort((np.arange(len(root)), rank))] = np.arange(len(root))
        first = np.full(len(groups), len(root))
        np.minimum.at(first, back, position[core])
        number = np.empty(len(groups), np.int64)
        number[np.argsort(first)] = np.arange(len(groups))
        label[core] = number[back]
    return label


def cluster_dense(lat: np.ndarray, lon: np.ndarray, weight: np.ndarray, rank: np.ndarray, eps_m: float, least: int) -> np.ndarray:
    """DBSCAN from all distances: labels by the earliest core sample, -1 for the rest; a border point goes to its nearest core."""
    n = len(lat)
    if not n:
        return np.zeros(0, np.int64)
    d = _metres(lat[:, None], lon[:, None], lat[None, :], lon[None, :])
    near = d <= eps_m
    core = near @ weight >= least
    a, b = np.nonzero(near & core[:, None] & core[None, :])
    label = _numbered(_roots(n, a, b), core, rank)
    for i in np.flatnonzero(~core & (near & core[None, :]).any(1)):
        js = np.flatnonzero(near[i] & core)
        label[i] = label[js[np.lexsort((label[js], np.round(d[i, js], 6)))[0]]]
    return label


def cluster_cells(lat: np.ndarray, lon: np.ndarray, weight: np.ndarray, rank: np.ndarray, eps_m: float, least: int) -> np.ndarray:
    """The same in memory that grows with the number of points only.

    Points on the sphere fall into cubes whose diagonal is below eps, at any latitude and across the date line. All points of a cube are
    neighbours, so a cube of enough weight is all core and one cluster; only sparse cubes' points are counted out, and pairs of
    nearby cubes are linked by the first pair of core points that is found near."""
    n, side = len(lat), eps_m * 0.999 / math.sqrt(3)
    p, q, r = np.radians(lat), np.radians(lon), 1000 * RADIUS_KM
    xyz = np.floor(np.stack([r * np.cos(p) * np.cos(q), r * np.cos(p) * np.sin(q), r * np.sin(p)], 1) / side).astype(np.int64)
    cells, cell = np.unique(xyz, axis=0, return_inverse=True)
    cell = cell.reshape(-1)
    order = np.argsort(cell, kind="stable")
    begin = np.searchsorted(cell[order], np.arange(len(cells) + 1))
    members = [order[x:y] for x, y in zip(begin[:-1], begin[1:], strict=True)]
    number = {tuple(c): i for i, c in enumerate(cells.tolist())}
    steps = [(x, y, z) for x in range(-2, 3) for y in range(-2, 3) for z in range(-2, 3)]
    around = [[j for x, y, z in steps if (j := number.get((a + x, b + y, c + z))) is not None] for a, b, c in cells.tolist()]
    mass = np.bincount(cell, weight, len(cells))
    core = (mass >= least)[cell]
    for c in np.flatnonzero(mass < least).tolist():
        js = np.concatenate([members[j] for j in around[c]])
        for i in members[c].tolist():
            core[i] = weight[js[_metres(lat[i], lon[i], lat[js], lon[js]) <= eps_m]].sum() >= least
    cores = [m[core[m]] for m in members]
    a, b = [], []
    for c, mine in enumerate(cores):
        if not len(mine):
            continue
        a += [int(mine[0])] * (len(mine) - 1)
        b += mine[1:].tolist()
        for j in around[c]:
            if j <= c or not len(cores[j]):
                continue
            for at in range(0, len(mine), 512):
                part = mine[at : at + 512]
                hit = np.argwhere(_metres(lat[part, None], lon[part, None], lat[cores[j]], lon[cores[j]]) <= eps_m)
                if len(hit):
                    a.append(int(part[hit[0, 0]]))
                    b.append(int(cores[j][hit[0, 1]]))
                    break
    label = _numbered(_roots(n, np.array(a, np.int64), np.array(b, np.int64)), core, rank)
    for i in np.flatnonzero(~core).tolist():
        js = np.concatenate([cores[j] for j in around[cell[i]]])
        d = _metres(lat[i], lon[i], lat[js], lon[js])
        js, d = js[d <= eps_m], d[d <= eps_m]
        if len(js):
            label[i] = label[js[np.lexsort((label[js], np.round(d, 6)))[0]]]
    return label


def significant_places(points: DataFrame, keys: tuple[str, ...] = ("person_id",), eps_m: float = EPS_M, min_points: int = MIN_POINTS, cells_m: float | None = None, dense: int = DENSE) -> DataFrame:
    """`points` with place: DBSCAN of the samples within each group of keys; samples that are `moving`, if there is such a column, get -2.

    Rows pass through one task for each group, so samples of equal time stay apart. Memory grows with a group's samples; cells_m: join
    samples to cells of this size first, with multiplicity, so a person's state is bounded (approximate).
    """
    moves = "moving" in points.columns
    if cells_m:
        size = cells_m / (math.radians(1) * RADIUS_KM * 1000)
        rows = points.withColumns({"lat_cell": F.round(F.col("lat") / size), "lon_cell": F.round(F.col("lon") * F.cos(F.radians(F.round(F.col("lat") / size) * size)) / size)})
        static = rows.where(~F.col("moving")) if moves else rows
        grouped = static.groupBy(*keys, "lat_cell", "lon_cell").agg(F.min("us").alias("us"), F.avg("lat").alias("lat"), F.avg("lon").alias("lon"), F.count("*").alias("w"))
        placed = significant_places(grouped, keys, eps_m, min_points, dense=dense).select(*keys, "lat_cell", "lon_cell", "place")
        joined = rows.join(placed, [*keys, "lat_cell", "lon_cell"], "left")
        place = F.when(F.col("moving"), -2).otherwise(F.col("place")) if moves else F.col("place")
        return joined.withColumn("place", place).select(*points.columns, "place")

    def run(t: pa.Table) -> pa.Table:
        still = np.flatnonzero(~t.column("moving").to_numpy()) if moves else np.arange(len(t))
        lat, lon, us = (t.column(c).to_numpy()[still] for c in ("lat", "lon", "us"))
        w = t.column("w").to_numpy()[still] if "w" in t.column_names else np.ones(len(still), np.int64)
        place = np.full(len(t), -2)
        place[still] = (cluster_dense if len(still) <= dense else cluster_cells)(lat, lon, w, us, eps_m, min_points)
        return t.append_column("place", pa.array(place, pa.int32()))

    return points.groupBy(*keys).applyInArrow(run, _with(points, "place int"))


def _with(frame: DataFrame, more: str) -> str:
    return ", ".join([*(f"{f.name} {f.dataType.simpleString()}" for f in frame.schema), more])


def dwell(points: DataFrame, max_gap_min: float | None = None) -> DataFrame:
    """Minutes that each sample holds: until the person's next one, at most `max_gap_min`; the last holds none."""
    m = F.coalesce((F.lead("us").over(ordered()) - F.col("us")) / 60e6, F.lit(0.0))
    return points.withColumn("minutes", F.least(m, F.lit(max_gap_min)) if max_gap_min else m)


def visits(points: DataFrame, spec: SliceSpec | None = None, scope: str = "global", **dbscan) -> DataFrame:
    """Pieces of time (us, minutes) with position and place (-1 insignificant, -2 moving) in every slice, cut at its borders.

    scope global: clusters of all samples; what a sample holds beyond a border counts in the next slice. local: clusters of the samples
    taken in the slice, and only their time in it."""
    held, spec = dwell(label_motion(points)).select("person_id", "us", "lat", "lon", "minutes", "moving"), spec or SliceSpec()
    if scope == "global":
        return time_in_slices(significant_places(held, **dbscan), spec)
    placed = significant_places(attach(held, spec), ("person_id", *KEYS), **dbscan)
    ends = placed.withColumn("_end", (F.col("us") + F.round(F.col("minutes") * 60e6)).cast("bigint")).withColumnRenamed("us", "_start").drop("minutes")
    return clipped(ends, "_start", "_end").where(lies_in(spec)).drop("to_us", "_end")


def place_features(points: DataFrame, spec: SliceSpec | None = None, scope: str = "global", **dbscan) -> DataFrame:
    """Number of places, transitions, gyration, top three, moving and insignificant shares, stays, entropy."""
    rows = visits(points, spec, scope, **dbscan).withColumn("_stretch", stretch())
    key = ["person_id", *KEYS]
    w = Window.partitionBy(*key).orderBy("us")
    known = F.when(F.col("place") >= 0, F.col("place"))
    before = F.last(known, ignorenulls=True).over(w.rowsBetween(Window.unboundedPreceding, -1))
    marked = rows.withColumn("change", (known != before).cast("int")).withColumn("visit", (~(F.col("place").eqNullSafe(F.lag("place").over(w)) & F.col("_stretch").eqNullSafe(F.lag("_stretch").over(w)))).cast("int")).withColumn("visit", F.sum("visit").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    stays = marked.groupBy(*key, "visit", "place").agg(F.sum("minutes").alias("minutes"), F.sum("change").alias("changes"), F.sum(F.col("lat") * F.col("minutes")).alias("lat"), F.sum(F.col("lon") * F.col("minutes")).alias("lon"))
    stay = F.when(F.col("place") >= 0, F.col("minutes"))
    by_place = stays.groupBy(*key, "place").agg(
        F.sum("minutes").alias("m"), F.sum("changes").alias("c"), F.try_divide(F.sum("lat"), F.sum("minutes")).alias("lat"), F.try_divide(F.sum("lon"), F.sum("minutes")).alias("lon"),
        F.max(stay).alias("smax"), F.min(stay).alias("smin"), F.sum(stay).alias("ssum"), F.sum(stay * stay).alias("ssq"), F.count(stay).alias("sn"),
    )
    real, over = F.col("place") >= 0, Window.partitionBy(*key)
    mass = F.sum(F.when(real, F.col("m"))).over(over)
    lat0, lon0 = F.try_divide(F.sum(F.when(real, F.col("m") * F.col("lat"))).over(over), mass), F.try_divide(F.sum(F.when(real, F.col("m") * F.col("lon"))).over(over), mass)
    order = Window.partitionBy(*key).orderBy(F.when(real, 0).otherwise(1), F.desc(F.round("m", 6)), "place")
    wide = by_place.withColumns({"p": F.try_divide(F.when(real, F.col("m")), mass), "d": haversine_km(F.col("lat"), F.col("lon"), lat0, lon0), "rank": F.row_number().over(order)})
    top = [F.coalesce(F.max(F.when(real & (F.col("rank") == i), F.col("m"))), F.lit(0.0)).alias(f"top{i}_minutes") for i in (1, 2, 3)]
    out = wide.groupBy(*key).agg(
        F.count_if(real).alias("places"), F.coalesce(F.sum("c"), F.lit(0)).alias("transitions"), F.sqrt(F.sum(F.col("p") * F.col("d") ** 2)).alias("gyration_km"), *top,
        F.try_divide(F.sum(F.when(F.col("place") == -2, F.col("m")).otherwise(0.0)), F.sum("m")).alias("moving_share"), F.try_divide(F.sum(F.when(F.col("place") == -1, F.col("m")).otherwise(0.0)), F.sum("m")).alias("rare_share"),
        F.max("smax").alias("stay_max"), F.min("smin").alias("stay_min"), F.try_divide(F.sum("ssum"), F.sum("sn")).alias("stay_mean"), F.when(F.sum("sn") > 0, F.sqrt(F.greatest(F.sum("ssq") / F.sum("sn") - (F.sum("ssum") / F.sum("sn")) ** 2, F.lit(0.0)))).alias("stay_std"),
        F.sum(-F.col("p") * F.log(F.nullif(F.col("p"), F.lit(0.0)))).alias("entropy"), F.count_if(F.col("p") > 0).alias("_k"),
    )
    return out.withColumn("normalised_entropy", F.when(F.col("_k") > 1, F.col("entropy") / F.log("_k")).when(F.col("_k") == 1, 0.0)).drop("_k")


def home_location(points: DataFrame, **dbscan) -> DataFrame:
    """person_id, lat, lon: the centre of the place with most night time; motion and places are those of the night samples alone."""
    border = (6 * HOUR - F.pmod(F.col("us"), F.lit(6 * HOUR))) / 60e6
    night = dwell(points).where(epoch_of(F.col("us")) == "night").withColumn("minutes", F.least("minutes", border))
    placed = significant_places(label_motion(night).select("person_id", "us", "lat", "lon", "minutes", "moving"), **dbscan).where("place >= 0")
    centres = placed.groupBy("person_id", "place").agg(F.sum("minutes").alias("minutes"), F.avg("lat").alias("lat"), F.avg("lon").alias("lon"))
    best = centres.groupBy("person_id").agg(F.max_by(F.struct("lat", "lon"), F.struct(F.round("minutes", 6), -F.col("place"))).alias("h"))
    return best.select("person_id", F.col("h.lat").alias("home_lat"), F.col("h.lon").alias("home_lon"))


def home_features(points: DataFrame, spec: SliceSpec | None = None, radii_m: tuple[int, ...] = (10, 100), **dbscan) -> DataFrame:
    """Minutes within each radius of the home, cut at slice borders."""
    near = dwell(points).select("person_id", "us", "lat", "lon", "minutes").join(home_location(points, **dbscan), "person_id")
    near = near.withColumn("m", haversine_km(F.col("lat"), F.col("lon"), F.col("home_lat"), F.col("home_lon")) * 1000)
    return time_in_slices(near, spec or SliceSpec()).groupBy("person_id", *KEYS).agg(*(F.sum(F.when(F.col("m") <= r, F.col("minutes")).otherwise(0.0)).alias(f"home_{r}m") for r in radii_m))


def neighbours_by_grid(points: DataFrame, eps_m: float = EPS_M) -> DataFrame:
    """person_id, us, n: samples within eps of each, by equi-joins on cubes of eps instead of all pairs; cubes are the same size at every latitude.

    A person's occupied cubes find those beside them first, so samples aren't copied for cubes that hold none. No side is broadcast:
    Spark takes their sizes from the file and doesn't know by how much they grow."""
    r, p, q = 1000 * RADIUS_KM / eps_m, F.radians("lat"), F.radians("lon")
    axes = {"cx": F.floor(F.cos(p) * F.cos(q) * r), "cy": F.floor(F.cos(p) * F.sin(q) * r), "cz": F.floor(F.sin(p) * r)}
    cell = points.select("person_id", "us", "lat", "lon", *(e.alias(c) for c, e in axes.items()))
    cubes = cell.select("person_id", *axes).distinct()
    beside = cubes.withColumns({f"{c}2": F.col(c) for c in axes})
    for c in axes:
        beside = beside.withColumn(f"{c}2", F.explode(F.sequence(F.col(c) - 1, F.col(c) + 1)))
    beside = beside.join(cubes.select("person_id", *(F.col(c).alias(f"{c}2") for c in axes)).hint("merge"), ["person_id", *(f"{c}2" for c in axes)])
    others = cell.select("person_id", F.col("lat").alias("lat2"), F.col("lon").alias("lon2"), *(F.col(c).alias(f"{c}2") for c in axes))
    pairs = cell.join(beside.hint("merge"), ["person_id", *axes]).join(others.hint("merge"), ["person_id", *(f"{c}2" for c in axes)])
    pairs = pairs.where(haversine_km(F.col("lat"), F.col("lon"), F.col("lat2"), F.col("lon2")) * 1000 <= eps_m)
    return pairs.groupBy("person_id", "us").agg(F.count("*").alias("n"))
