"""SQL of the seven feature sets over any kind of slices, written apart from the engine: it cuts, groups and clusters in its own way."""

from __future__ import annotations

from kinetrace.oracles.base import ep

#: Kinds of slices: parts of the day of all data; all data; weeks; spans, day types and parts of the day crossed.
DAY, FULL, WEEK, CROSSED = "day", "full", "week", "crossed"
K = "span, span_id, daytype, epoch"
ORIGIN, SIX_HOURS, ONE_DAY = 19723, 21_600_000_000, 86_400_000_000
ON = f"USING (person_id, {K})"


def cells(view: str, kind: str = DAY, us: str = "us") -> str:
    day = f"({us} // {ONE_DAY})"
    week = f"({day} + 3) // 7 - {(ORIGIN + 3) // 7} + 1"
    if kind == CROSSED:
        half = f"CASE WHEN {day} - {ORIGIN} < 15 THEN 1 ELSE 2 END"
        spans = f"(SELECT * EXCLUDE (cell_), cell_.span AS span, cell_.id AS span_id FROM (SELECT *, unnest([{{'span': 'full', 'id': 0}}, {{'span': 'half', 'id': {half}}}, {{'span': 'week', 'id': {week}}}]) AS cell_ FROM {view}))"
        types = f"(SELECT *, unnest(['all', CASE WHEN ({day} + 3) % 7 >= 5 THEN 'weekend' ELSE 'weekday' END]) AS daytype FROM {spans})"
        return f"(SELECT *, unnest(['allday', {ep(us)}]) AS epoch FROM {types})"
    if kind == WEEK:
        return f"(SELECT *, 'week' AS span, {week} AS span_id, 'all' AS daytype, 'allday' AS epoch FROM {view})"
    epoch = f"unnest(['allday', {ep(us)}])" if kind == DAY else "'allday'"
    return f"(SELECT *, 'full' AS span, 0 AS span_id, 'all' AS daytype, {epoch} AS epoch FROM {view})"


def stretch(us: str = "us") -> str:
    return f"CASE WHEN epoch <> 'allday' THEN {us} // {SIX_HOURS} WHEN daytype <> 'all' THEN ({us} // {ONE_DAY} + 3) // 7 ELSE 0 END"


def pieces(view: str) -> str:
    """Intervals (start_us, end_us) cut at the borders of the day's parts: us, to_us, minutes; the interval's own bounds are b0 and b1."""
    return (
        f"(SELECT * EXCLUDE (start_us, end_us, f), start_us AS b0, end_us AS b1, greatest(start_us, f) AS us, least(end_us, f + {SIX_HOURS}) AS to_us, (least(end_us, f + {SIX_HOURS}) - greatest(start_us, f)) / 60e6::DOUBLE AS minutes "
        f"FROM (SELECT *, unnest(range(start_us // {SIX_HOURS} * {SIX_HOURS}, greatest(end_us, start_us + 1), {SIX_HOURS})) AS f FROM {view}))"
    )


def in_slices(view: str, kind: str, extra: str = "") -> str:
    more = f", {extra}" if extra else ""
    return f"(SELECT person_id, {K}{more}, min(us) AS start_us, max(to_us) AS end_us, sum(minutes) AS minutes FROM (SELECT *, {stretch()} AS st FROM {cells(pieces(view), kind)}) GROUP BY person_id, {K}{more}, b0, b1, st)"


def runs_of(view: str, label: str) -> str:
    """Rows with the number of their run of one label."""
    return f"(SELECT *, sum(s) OVER (PARTITION BY person_id ORDER BY us) AS r FROM (SELECT *, CASE WHEN lag({label}) OVER (PARTITION BY person_id ORDER BY us) = {label} THEN 0 ELSE 1 END AS s FROM {view}))"


# steps
def step_totals(kind: str) -> str:
    return f"SELECT person_id, {K}, sum(steps) AS total, max(steps) AS max5 FROM {cells('bin', kind)} GROUP BY ALL"


def step_bout_stats(kind: str) -> str:
    one = "count(*) FILTER (label = '{0}') AS {0}_bouts, max(minutes) FILTER (label = '{0}') AS {0}_max, min(minutes) FILTER (label = '{0}') AS {0}_min, avg(minutes) FILTER (label = '{0}') AS {0}_mean"
    bouts = f"(SELECT person_id, {K}, label, count(*) * 5.0 AS minutes, sum(steps) AS steps FROM (SELECT *, {stretch()} AS st FROM {cells('bin2', kind)}) GROUP BY person_id, {K}, label, r, st)"
    return f"SELECT person_id, {K}, {one.format('active')}, {one.format('sedentary')}, min(steps) FILTER (label = 'active') AS steps_min, max(steps) FILTER (label = 'active') AS steps_max, avg(steps) FILTER (label = 'active') AS steps_mean FROM {bouts} GROUP BY ALL"


def step_features(kind: str) -> str:
    return f"SELECT * FROM ({step_totals(kind)}) LEFT JOIN ({step_bout_stats(kind)}) {ON}"


# sleep
NAPS = "nap"
SLEEP_EVENTS = "(SELECT person_id, us, CASE event_type WHEN 'click' THEN 'asleep' WHEN 'view' THEN 'restless' WHEN 'error' THEN 'awake' ELSE 'unknown' END AS state FROM ev)"


def sleep_counts(kind: str, view: str = NAPS) -> str:
    counts = ", ".join(f"count(*) FILTER (state = '{x}') AS {x}" for x in ("asleep", "restless", "awake", "unknown"))
    rated = "nullif(asleep + restless + awake, 0)::DOUBLE"
    return f"SELECT *, (asleep + restless) / {rated} AS weak_efficiency, asleep / {rated} AS strong_efficiency FROM (SELECT person_id, {K}, {counts} FROM {cells(view, kind)} GROUP BY ALL)"


def sleep_bouts(kind: str, view: str = NAPS) -> str:
    return f"(SELECT person_id, {K}, state, min(us) AS start_us, max(us) + 60000000 AS end_us, CAST(count(*) AS DOUBLE) AS minutes FROM (SELECT *, {stretch()} AS st FROM {cells(runs_of(view, 'state'), kind)}) WHERE state <> 'unknown' GROUP BY person_id, {K}, state, r, st)"


def sleep_bout_stats(kind: str, view: str = NAPS) -> str:
    return f"SELECT person_id, {K}, state, count(*) AS bouts, sum(minutes) AS total, avg(minutes) AS mean, max(minutes) AS longest, min(minutes) AS shortest FROM {sleep_bouts(kind, view)} GROUP BY ALL"


def sleep_extremes(kind: str, view: str = NAPS) -> str:
    pick = ", ".join(f"arg_min({c}_us, ({sign}minutes, start_us)) AS {name}_{c}" for name, sign in (("longest", "-"), ("shortest", "")) for c in ("start", "end"))
    return f"SELECT person_id, {K}, state, {pick} FROM {sleep_bouts(kind, view)} GROUP BY ALL"


def sleep_extreme_minutes(kind: str) -> str:
    """Times in minutes since the study's first day."""
    names = [f"{x}_{c}" for x in ("longest", "shortest") for c in ("start", "end")]
    return f"SELECT person_id, {K}, state, {', '.join(f'({n} - {ORIGIN * ONE_DAY}) / 60e6::DOUBLE AS {n}' for n in names)} FROM ({sleep_extremes(kind, SLEEP_EVENTS)})"


# phone
SCREEN_BOUTS = "(SELECT 'interaction' AS kind, * FROM ibout UNION ALL SELECT 'unlocked', * FROM ubout)"
NOMINAL = "(CASE span WHEN 'full' THEN 30 WHEN 'half' THEN 15 ELSE 7 END * CASE daytype WHEN 'weekday' THEN 5 / 7.0::DOUBLE WHEN 'weekend' THEN 2 / 7.0::DOUBLE ELSE 1.0::DOUBLE END * CASE epoch WHEN 'allday' THEN 1440.0::DOUBLE ELSE 360.0::DOUBLE END)"


def phone_features(kind: str) -> str:
    stats = ", ".join(f"{f}(minutes) FILTER (kind = '{x}') AS {x}_{n}" for x in ("interaction", "unlocked") for f, n in (("sum", "total"), ("max", "max"), ("min", "min"), ("avg", "mean"), ("stddev_pop", "std")))
    counts = f"(SELECT person_id, {K}, count(*) FILTER (status = 'unlock') AS unlocks FROM {cells('screen', kind)} GROUP BY ALL)"
    return f"SELECT *, unlocks / {NOMINAL} AS unlocks_per_minute FROM {counts} LEFT JOIN (SELECT person_id, {K}, {stats} FROM {in_slices(SCREEN_BOUTS, kind, 'kind')} GROUP BY ALL) {ON}"


def phone_hours(kind: str) -> str:
    asked = [("first", "unlock", "min"), ("first", "on", "min"), ("last", "unlock", "max"), ("last", "lock", "max"), ("last", "on", "max")]
    daily = ", ".join(f"{f}(us // 3600000000 % 24) FILTER (status = '{x}') AS {w}_{x}" for w, x, f in asked)
    return f"SELECT person_id, {K}, {', '.join(f'avg({w}_{x}) AS {w}_{x}' for w, x, _ in asked)} FROM (SELECT person_id, {K}, us // {ONE_DAY} AS day, {daily} FROM {cells('screen', kind)} GROUP BY ALL) GROUP BY ALL"


# calls
CATEGORIES, DIRECTIONS = ("family", "friend_off", "friend_on"), ("incoming", "outgoing", "missed")


def call_features(kind: str, calls: str = "calls", contacts: str = "contacts") -> str:
    groups = [("all", ""), *((g, f" AND category = '{g}'") for g in CATEGORIES)]
    sums = ", ".join(f"count(*) FILTER (direction = '{d}'{c}) AS n_{d}_{g}, coalesce(sum(duration_s) FILTER (direction = '{d}'{c}), 0) AS s_{d}_{g}" for g, c in groups for d in DIRECTIONS)
    people = "count(DISTINCT correspondent) AS people_all, " + ", ".join(f"count(DISTINCT correspondent) FILTER (category = '{g}') AS people_{g}" for g in CATEGORIES)
    return f"SELECT person_id, {K}, {sums}, {people} FROM {cells(f'(SELECT * FROM {calls} LEFT JOIN {contacts} USING (person_id, correspondent))', kind)} GROUP BY ALL"


# proximity
SIX = "count(*) AS devices, max(scans) AS most, min(scans) AS least, sum(scans) AS total, avg(scans) AS mean, stddev_pop(scans) AS std"


def scan_features(kind: str) -> str:
    counts = f"(SELECT person_id, {K}, address, count(*) AS scans FROM {cells('scan', kind)} GROUP BY ALL)"
    return f"SELECT person_id, {K}, owners, {SIX} FROM (SELECT t.* EXCLUDE (address), unnest(['all', o.owner]) AS owners FROM {counts} t JOIN owner o USING (person_id, address)) GROUP BY ALL"


def local_scan_features(kind: str) -> str:
    """Clusters of each slice: the scores, splits and owners of `owner`, by slice."""
    g = f"person_id, {K}"
    return f"""WITH sc AS MATERIALIZED (SELECT * FROM {cells('scan', kind)}),
      d0 AS (SELECT {g}, address, count(DISTINCT us // {ONE_DAY}) AS days, count(*) AS scans FROM sc GROUP BY ALL),
      d1 AS (SELECT *, scans / days::DOUBLE AS frequency FROM d0),
      d AS MATERIALIZED (SELECT *, round(coalesce((days - avg(days) OVER p) / nullif(stddev_pop(days) OVER p, 0), 0) + coalesce((frequency - avg(frequency) OVER p) / nullif(stddev_pop(frequency) OVER p, 0), 0), 9) AS score
            FROM d1 WINDOW p AS (PARTITION BY {g})),
      c AS (SELECT DISTINCT {g}, score AS cut FROM d), m AS (SELECT {g}, count(*) AS m FROM c GROUP BY ALL),
      t0 AS (SELECT {', '.join('d.' + x for x in g.split(', '))}, cut, score <= cut AS side, var_pop(score) * count(*) AS sse FROM d JOIN c USING ({g}) GROUP BY ALL),
      t1 AS (SELECT {g}, cut, round(sum(sse), 7) AS sse FROM t0 GROUP BY ALL HAVING count(*) = 2),
      t AS (SELECT {g}, min(sse) AS sse2, arg_min(cut, (sse, cut)) AS cut FROM t1 GROUP BY ALL),
      r0 AS (SELECT {', '.join('d.' + x for x in g.split(', '))}, a.cut AS c1, b.cut AS c2, CASE WHEN score <= a.cut THEN 0 WHEN score <= b.cut THEN 1 ELSE 2 END AS side, var_pop(score) * count(*) AS sse
             FROM d JOIN c a USING ({g}) JOIN c b USING ({g}) WHERE a.cut < b.cut GROUP BY ALL),
      r1 AS (SELECT {g}, c1, c2, round(sum(sse), 7) AS sse FROM r0 GROUP BY ALL HAVING count(*) = 3),
      r AS (SELECT {g}, min(sse) AS sse3, arg_min(c1, (sse, c1, c2)) AS c1, arg_min(c2, (sse, c1, c2)) AS c2 FROM r1 GROUP BY ALL),
      o AS (SELECT d.*, CASE WHEN m.m = 1 THEN 'self' WHEN m.m = 2 THEN CASE WHEN score > t.cut THEN 'self' ELSE 'others' END
            WHEN t.sse2 < r.sse3 THEN CASE WHEN score > t.cut THEN 'self' ELSE 'others' END
            WHEN score > r.c2 THEN 'self' WHEN score > r.c1 THEN 'related' ELSE 'others' END AS owner
            FROM d JOIN m USING ({g}) LEFT JOIN t USING ({g}) LEFT JOIN r USING ({g}))
      SELECT {g}, owners, {SIX} FROM (SELECT * EXCLUDE (owner), unnest(['all', owner]) AS owners FROM o) GROUP BY ALL"""


# location
def basic(kind: str) -> str:
    return f"SELECT *, ln(nullif(round(variance, 15), 0)) AS log_variance FROM (SELECT person_id, {K}, var_pop(lat) + var_pop(lon) AS variance, sum(km) AS distance_km, avg(speed) AS speed_mean, var_pop(speed) AS speed_variance FROM {cells('mv', kind)} GROUP BY ALL)"


def circadian(kind: str, normalise: str = "log") -> str:
    """The direct form: centred values, phase, then power."""
    periods = "(SELECT 23.5 + 0.1 * i AS p FROM range(11) t(i))" if normalise == "log" else "(SELECT DISTINCT p FROM (SELECT round(23.5 + 0.1 * i, 6) AS p FROM range(11) t(i) UNION SELECT i FROM range(6, 49) t(i)))"
    last = "ln(nullif(round(sum(power), 12), 0))" if normalise == "log" else "sum(power) FILTER (p BETWEEN 23.5 AND 24.5) / nullif(sum(power), 0)"
    g = f"person_id, {K}"
    return f"""SELECT {g}, {last} AS circadian FROM (
      SELECT {g}, p, (power(sum(y * cos(w - tau)), 2) + power(sum(x * cos(w - tau)), 2)) / (2 * sum(power(cos(w - tau), 2)))
             + CASE WHEN sum(power(sin(w - tau), 2)) > 5e-7 THEN (power(sum(y * sin(w - tau)), 2) + power(sum(x * sin(w - tau)), 2)) / (2 * sum(power(sin(w - tau), 2))) ELSE 0 END AS power
      FROM (SELECT *, atan2(sum(sin(2 * w)) OVER q, sum(cos(2 * w)) OVER q) / 2 AS tau FROM (
        SELECT {g}, p, lat - avg(lat) OVER g AS y, lon - avg(lon) OVER g AS x, 2 * pi() * (us - 1704067200000000) / 3.6e9::DOUBLE / p::DOUBLE AS w
        FROM {cells('pt', kind)} CROSS JOIN (SELECT CAST(p AS DOUBLE) AS p FROM {periods}) z WINDOW g AS (PARTITION BY {g}, p)) WINDOW q AS (PARTITION BY {g}, p)) GROUP BY ALL) GROUP BY ALL"""


def dbscan(source: str, n: str = "") -> str:
    """CTEs that cluster `source` (g, sid, lat, lon): `placed{n}` (g, sid, place), places by the earliest sid, -1 for the rest."""
    return f"""st{n} AS MATERIALIZED (SELECT g, sid, lat, lon FROM {source}),
  nb{n} AS MATERIALIZED (SELECT * FROM (SELECT a.g, a.sid AS u, b.sid AS v, 2000 * 6371.0088::DOUBLE * asin(least(1.0::DOUBLE, sqrt(power(sin(radians(b.lat - a.lat) / 2), 2) + cos(radians(a.lat)) * cos(radians(b.lat)) * power(sin(radians(b.lon - a.lon) / 2), 2)))) AS m
           FROM st{n} a JOIN st{n} b USING (g)) WHERE m <= 60),
  core{n} AS MATERIALIZED (SELECT g, u FROM nb{n} GROUP BY ALL HAVING count(*) >= 3),
  ce{n} AS MATERIALIZED (SELECT x.g, x.u, x.v FROM nb{n} x JOIN core{n} a ON a.g = x.g AND a.u = x.u JOIN core{n} b ON b.g = x.g AND b.u = x.v),
  reach{n} AS (SELECT g, u, u AS root FROM core{n} UNION SELECT e.g, e.v, r.root FROM reach{n} r JOIN ce{n} e ON e.g = r.g AND e.u = r.u),
  comp{n} AS (SELECT g, u, min(root) AS root FROM reach{n} GROUP BY ALL),
  num{n} AS MATERIALIZED (SELECT *, dense_rank() OVER (PARTITION BY g ORDER BY root) - 1 AS place FROM comp{n}),
  border{n} AS (SELECT x.g, x.u, arg_min(y.place, (round(x.m, 6), y.place)) AS place FROM nb{n} x JOIN num{n} y ON y.g = x.g AND y.u = x.v GROUP BY ALL),
  placed{n} AS MATERIALIZED (SELECT s.g, s.sid, coalesce(y.place, b.place, -1) AS place FROM st{n} s LEFT JOIN num{n} y ON y.g = s.g AND y.u = s.sid LEFT JOIN border{n} b ON b.g = s.g AND b.u = s.sid)"""


HELD = "held AS MATERIALIZED (SELECT row_number() OVER (ORDER BY person_id, us) AS sid, person_id, us AS start_us, coalesce(lead(us) OVER (PARTITION BY person_id ORDER BY us), us) AS end_us, lat, lon, moving, us FROM mv)"


def visits(kind: str, scope: str) -> str:
    """CTEs that end in `vis`: pieces of time with place in every slice."""
    if scope == "global":
        labels = "(SELECT h.* EXCLUDE (us), CASE WHEN moving THEN -2 ELSE p.place END AS place FROM held h LEFT JOIN placed p ON p.sid = h.sid)"
        return f"{HELD}, {dbscan('(SELECT person_id AS g, sid, lat, lon FROM held WHERE NOT moving)')}, vis AS MATERIALIZED (SELECT * FROM {cells(pieces(labels), kind)})"
    g = "concat_ws('|', person_id, span, span_id, daytype, epoch)"
    mine = f"(SELECT *, {g} AS g FROM {cells('held', kind)})"
    own = pieces(f"(SELECT o.* EXCLUDE (us), CASE WHEN moving THEN -2 ELSE p.place END AS place FROM own o LEFT JOIN placed p ON p.g = o.g AND p.sid = o.sid)")
    # a piece counts where its own slices include the sample's
    back = cells(f"(SELECT * EXCLUDE ({K}), span AS s0, span_id AS i0, daytype AS d0, epoch AS e0 FROM {own})", kind)
    return (
        f"{HELD}, own AS MATERIALIZED (SELECT * FROM {mine}), {dbscan('(SELECT * FROM own WHERE NOT moving)')}, "
        f"vis AS MATERIALIZED (SELECT * EXCLUDE (s0, i0, d0, e0) FROM {back} WHERE span = s0 AND span_id = i0 AND daytype = d0 AND epoch = e0)"
    )


def place_features(kind: str, scope: str = "global") -> str:
    g = f"person_id, {K}"
    return f"""WITH RECURSIVE {visits(kind, scope)},
      v1 AS (SELECT *, {stretch()} AS st FROM vis),
      v2 AS (SELECT *, CASE WHEN place >= 0 AND last_value(CASE WHEN place >= 0 THEN place END IGNORE NULLS) OVER (PARTITION BY {g} ORDER BY us ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) <> place THEN 1 ELSE 0 END AS change,
             CASE WHEN lag(place) OVER w = place AND lag(st) OVER w = st THEN 0 ELSE 1 END AS f FROM v1 WINDOW w AS (PARTITION BY {g} ORDER BY us)),
      v3 AS (SELECT *, sum(f) OVER (PARTITION BY {g} ORDER BY us) AS visit FROM v2),
      stays AS (SELECT {g}, visit, place, sum(minutes) AS m FROM v3 GROUP BY ALL),
      sa AS (SELECT {g}, max(m) AS stay_max, min(m) AS stay_min, avg(m) AS stay_mean, stddev_pop(m) AS stay_std FROM stays WHERE place >= 0 GROUP BY ALL),
      bp AS (SELECT {g}, place, sum(minutes) AS m, sum(minutes * lat) / nullif(sum(minutes), 0) AS lat, sum(minutes * lon) / nullif(sum(minutes), 0) AS lon FROM v3 WHERE place >= 0 GROUP BY ALL),
      bq AS (SELECT *, m / nullif(sum(m) OVER q, 0) AS p, sum(m * lat) OVER q / nullif(sum(m) OVER q, 0) AS lat0, sum(m * lon) OVER q / nullif(sum(m) OVER q, 0) AS lon0,
             row_number() OVER (PARTITION BY {g} ORDER BY round(m, 6) DESC, place) AS rk FROM bp WINDOW q AS (PARTITION BY {g})),
      br AS (SELECT *, 2 * 6371.0088::DOUBLE * asin(least(1.0::DOUBLE, sqrt(power(sin(radians(lat0 - lat) / 2), 2) + cos(radians(lat)) * cos(radians(lat0)) * power(sin(radians(lon0 - lon) / 2), 2)))) AS d FROM bq),
      pa AS (SELECT {g}, count(*) AS places, sqrt(sum(p * d * d)) AS gyration_km, sum(m) FILTER (rk = 1) AS t1, sum(m) FILTER (rk = 2) AS t2, sum(m) FILTER (rk = 3) AS t3, sum(-p * ln(nullif(p, 0))) AS entropy, count(*) FILTER (p > 0) AS k FROM br GROUP BY ALL),
      al AS (SELECT {g}, sum(change) AS transitions, sum(CASE WHEN place = -2 THEN minutes ELSE 0 END) / nullif(sum(minutes), 0) AS moving_share, sum(CASE WHEN place = -1 THEN minutes ELSE 0 END) / nullif(sum(minutes), 0) AS rare_share FROM v3 GROUP BY ALL)
      SELECT {g}, coalesce(places, 0) AS places, transitions, gyration_km, coalesce(t1, 0) AS top1_minutes, coalesce(t2, 0) AS top2_minutes, coalesce(t3, 0) AS top3_minutes, moving_share, rare_share, stay_max, stay_min, stay_mean, stay_std, entropy,
             CASE WHEN k > 1 THEN entropy / ln(k) WHEN k = 1 THEN 0 END AS normalised_entropy
      FROM al LEFT JOIN pa USING ({g}) LEFT JOIN sa USING ({g})"""


def local_places(kind: str = DAY) -> str:
    g = "concat_ws('|', person_id, span, span_id, daytype, epoch)"
    return f"WITH RECURSIVE {HELD}, own AS MATERIALIZED (SELECT *, {g} AS g FROM {cells('held', kind)}), {dbscan('(SELECT * FROM own WHERE NOT moving)')} SELECT person_id, {K}, us, CASE WHEN moving THEN -2 ELSE place END AS place FROM own LEFT JOIN placed USING (g, sid)"


NIGHT = f"""night AS MATERIALIZED (SELECT row_number() OVER (ORDER BY person_id, us) AS sid, *, lag(us) OVER w AS us0, lag(lat) OVER w AS lat0, lag(lon) OVER w AS lon0
    FROM (SELECT person_id, us, lat, lon, least(coalesce(lead(us) OVER (PARTITION BY person_id ORDER BY us) - us, 0), {SIX_HOURS} - us % {SIX_HOURS}) / 60e6::DOUBLE AS minutes FROM pt) WHERE us // {SIX_HOURS} % 4 = 0 WINDOW w AS (PARTITION BY person_id ORDER BY us)),
  still AS MATERIALIZED (SELECT * FROM night WHERE us0 IS NULL OR us = us0 OR 2 * 6371.0088::DOUBLE * asin(least(1.0::DOUBLE, sqrt(power(sin(radians(lat - lat0) / 2), 2) + cos(radians(lat0)) * cos(radians(lat)) * power(sin(radians(lon - lon0) / 2), 2)))) / ((us - us0) / 3.6e9::DOUBLE) <= 1),
  {dbscan('(SELECT person_id AS g, sid, lat, lon FROM still)', 'n')},
  homes AS (SELECT person_id, arg_min(lat, (-round(m, 6), place)) AS home_lat, arg_min(lon, (-round(m, 6), place)) AS home_lon FROM (
    SELECT person_id, place, sum(minutes) AS m, avg(lat) AS lat, avg(lon) AS lon FROM still JOIN placedn USING (sid) WHERE place >= 0 GROUP BY ALL) GROUP BY ALL)"""


def home() -> str:
    return f"WITH RECURSIVE {NIGHT} SELECT * FROM homes"


def home_time(kind: str = DAY) -> str:
    held = "(SELECT person_id, us AS start_us, coalesce(lead(us) OVER (PARTITION BY person_id ORDER BY us), us) AS end_us, lat, lon FROM pt)"
    m = "2000 * 6371.0088::DOUBLE * asin(least(1.0::DOUBLE, sqrt(power(sin(radians(home_lat - lat) / 2), 2) + cos(radians(lat)) * cos(radians(home_lat)) * power(sin(radians(home_lon - lon) / 2), 2))))"
    return f"WITH RECURSIVE {NIGHT} SELECT person_id, {K}, sum(CASE WHEN {m} <= 10 THEN minutes ELSE 0 END) AS home_10m, sum(CASE WHEN {m} <= 100 THEN minutes ELSE 0 END) AS home_100m FROM {cells(pieces(held), kind)} JOIN homes USING (person_id) GROUP BY ALL"


# annotated places
SPACE_TIMES = "(SELECT person_id, type, us AS start_us, nxt AS end_us FROM spc)"
SPACE_BOUTS = "(SELECT person_id, type, start_us, end_us FROM spb)"


def space_minutes(kind: str) -> str:
    return f"SELECT *, minutes / nullif(sum(minutes) OVER (PARTITION BY person_id, {K}), 0) AS share FROM (SELECT person_id, {K}, type, sum(minutes) AS minutes FROM {cells(pieces(SPACE_TIMES), kind)} GROUP BY ALL)"


def space_transitions(kind: str) -> str:
    moved = "(SELECT *, lag(type) OVER (PARTITION BY person_id ORDER BY us) AS prev FROM spc)"
    return f"SELECT person_id, {K}, coalesce(sum(CAST(type <> prev AS INT)), 0) AS transitions FROM {cells(moved, kind)} GROUP BY ALL"


def space_bouts(kind: str) -> str:
    m = "minutes"
    return f"SELECT person_id, {K}, type, count(*) AS bouts, count(*) FILTER ({m} >= 10) AS bouts_10, count(*) FILTER ({m} >= 20) AS bouts_20, count(*) FILTER ({m} >= 30) AS bouts_30, min({m}) AS shortest, max({m}) AS longest, avg({m}) AS mean, stddev_pop({m}) AS std FROM {in_slices(SPACE_BOUTS, kind, 'type')} GROUP BY ALL"


#: Stretches between any two borders of the three kinds of interval, tested one by one, then joined.
STUDY = """(SELECT person_id, min(a) AS start_us, max(z) AS end_us FROM (SELECT *, sum(f) OVER (PARTITION BY person_id ORDER BY a) AS r FROM (SELECT *, CASE WHEN lag(z) OVER (PARTITION BY person_id ORDER BY a) = a THEN 0 ELSE 1 END AS f FROM (
    SELECT c.person_id, c.a, c.z FROM (SELECT person_id, t AS a, lead(t) OVER (PARTITION BY person_id ORDER BY t) AS z FROM (
        SELECT person_id, unnest([start_us, end_us]) AS t FROM spb WHERE type = 'academic' UNION SELECT person_id, unnest([start_us, end_us]) FROM ibout UNION SELECT person_id, unnest([us, us + 300000000]) FROM bin WHERE steps >= 10)) c
    JOIN (SELECT * FROM spb WHERE type = 'academic') b ON b.person_id = c.person_id AND b.start_us <= c.a AND c.z <= b.end_us AND c.z > c.a
    WHERE NOT EXISTS (SELECT 1 FROM ibout i WHERE i.person_id = c.person_id AND i.start_us < c.z AND c.a < i.end_us) AND NOT EXISTS (SELECT 1 FROM bin s WHERE s.person_id = c.person_id AND s.steps >= 10 AND s.us < c.z AND c.a < s.us + 300000000)
  ))) GROUP BY person_id, r HAVING max(z) - min(a) >= 1800000000)"""


def study(kind: str) -> str:
    return f"SELECT person_id, {K}, sum(minutes) AS study, count(*) AS bouts FROM {in_slices(STUDY, kind)} GROUP BY ALL"


def social_bouts(voice: str = "voice") -> str:
    return f"(SELECT person_id, start_us, end_us FROM (SELECT b.person_id, b.start_us, b.end_us, avg(CAST(v.inference IN ('voice', 'noise') AS DOUBLE)) AS share FROM spb b JOIN {voice} v ON v.person_id = b.person_id AND v.us >= b.start_us AND v.us < b.end_us WHERE b.type IN ('apartment', 'residence', 'green') AND b.minutes >= 20 GROUP BY ALL) WHERE share >= 0.8)"


def social(kind: str, voice: str = "voice") -> str:
    return f"SELECT person_id, {K}, sum(minutes) AS social, count(*) AS bouts FROM {in_slices(social_bouts(voice), kind)} GROUP BY ALL"


# the long table
def _long(sensor: str, body: str, group: str | None = None, but: str = "", prefix: str = "") -> str:
    out = f"person_id, {K}" + (f", {group}" if group else "")
    dropped = f"{out}, {but}" if but else out
    name = f"{group} || '.' || feature" if group else f"'{prefix}' || feature"
    return f"SELECT person_id, {K}, '{sensor}' AS sensor, {name} AS feature, value FROM (UNPIVOT (SELECT {out}, CAST(COLUMNS(* EXCLUDE ({dropped})) AS DOUBLE) FROM ({body})) ON COLUMNS(* EXCLUDE ({out})) INTO NAME feature VALUE value)"


def long(kind: str) -> str:
    parts = [
        _long("steps", step_features(kind)), _long("phone", phone_features(kind)), _long("phone", phone_hours(kind)), _long("calls", call_features(kind)),
        _long("sleep", sleep_counts(kind, SLEEP_EVENTS)), _long("sleep", sleep_bout_stats(kind, SLEEP_EVENTS), "state"), _long("sleep", sleep_extreme_minutes(kind), "state"),
        _long("proximity", scan_features(kind), "owners"), _long("location", basic(kind)), _long("location", circadian(kind)), _long("location", place_features(kind)), _long("location", place_features(kind, "local"), prefix="local_"),
        _long("location", home_time(kind)), _long("places", space_minutes(kind), "type"), _long("places", space_bouts(kind), "type"), _long("places", space_transitions(kind)),
        _long("places", study(kind), but="bouts"), _long("places", social(kind), but="bouts"),
    ]
    return " UNION ALL ".join(f"({p})" for p in parts)


# change
def joined_breaks(series: str) -> str:
    """One hinge by least squares on centred products, for every week of every series of `series` (person_id, feature, week, value): breakpoint, slope_before, slope_after."""
    return f"""(SELECT person_id, feature, arg_min(cut, (bic, cut)) AS breakpoint, arg_min(before, (bic, cut)) AS slope_before, arg_min(after, (bic, cut)) AS slope_after, min(bic) AS bic FROM (
      SELECT person_id, feature, cut, CASE WHEN two THEN beta ELSE line END AS before, CASE WHEN two THEN beta + gamma ELSE line END AS after,
             round(n * ln(greatest(CASE WHEN two THEN greatest(yy - beta * xy - gamma * hy, 0) ELSE greatest(yy - coalesce(line * xy, 0), 0) END, 1e-12 * (1 + yy)) / n) + CASE WHEN two THEN 3 ELSE 2 END * ln(n), 6) AS bic FROM (
        SELECT *, CASE WHEN two THEN (xy * hh - hy * xh) / det END AS beta, CASE WHEN two THEN (hy * xx - xy * xh) / det END AS gamma, CASE WHEN xx > 0 THEN xy / xx END AS line FROM (
          SELECT *, xx * hh - xh * xh AS det, xx * hh - xh * xh > 1e-9 * (1 + xx * xx) AS two FROM (
            SELECT person_id, feature, cut, count(*) AS n, var_pop(week) * count(*) AS xx, var_pop(value) * count(*) AS yy, covar_pop(value, week) * count(*) AS xy, var_pop(greatest(week - cut, 0)) * count(*) AS hh,
                   covar_pop(week, greatest(week - cut, 0)) * count(*) AS xh, covar_pop(value, greatest(week - cut, 0)) * count(*) AS hy
            FROM (SELECT s.*, c.week AS cut FROM {series} s JOIN (SELECT DISTINCT person_id, feature, week FROM {series}) c USING (person_id, feature)) GROUP BY ALL) WHERE n >= 3))) GROUP BY ALL)"""


def change_of(series: str, middle: int) -> str:
    part = lambda c: f"regr_slope(CASE WHEN {c} THEN value END, CASE WHEN {c} THEN week END)"
    slopes = f"(SELECT person_id, feature, count(*) AS n, regr_slope(value, week) AS slope, {part(f'week <= {middle}')} AS slope_first, {part(f'week >= {middle}')} AS slope_second FROM {series} GROUP BY ALL HAVING count(*) >= 3)"
    return f"SELECT * EXCLUDE (bic) FROM {slopes} LEFT JOIN {joined_breaks(series)} USING (person_id, feature)"
