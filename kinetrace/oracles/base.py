"""The sensor views and shared pieces of the SQL that checks the engine, for DuckDB."""

from __future__ import annotations

KINDS = {"b": "BIGINT", "s": "VARCHAR", "d": "DOUBLE"}
#: Digits kept of numbers: of most, and of slopes beside a bend close to a series' end, which few points fix.
DIGITS = {"d": 6, "e": 3}


def ep(us: str) -> str:
    return f"(['night','morning','afternoon','evening'])[(({us} // 21600000000) % 4) + 1]"


VIEWS = """
ev AS (SELECT event_id, user_id AS person_id, epoch_us(ts) AS us, event_type, value, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events),
scan AS (SELECT person_id, us, k % 10 AS address FROM ev),
calls AS (SELECT person_id, us, CASE event_type WHEN 'click' THEN 'incoming' WHEN 'view' THEN 'outgoing' WHEN 'error' THEN 'missed' END AS direction,
          k AS correspondent, value AS duration_s FROM ev WHERE event_type IN ('click', 'view', 'error')),
contacts AS (SELECT DISTINCT person_id, correspondent, CASE correspondent % 4 WHEN 0 THEN 'family' WHEN 1 THEN 'friend_off' ELSE 'friend_on' END AS category
             FROM calls WHERE correspondent % 4 < 3),
pt0 AS (SELECT person_id, us, CASE WHEN k < 90 THEN (person_id + k % 4) % 25 ELSE k % 25 END AS pl, CAST(round(value * 100) AS BIGINT) AS cents FROM ev),
pt AS (SELECT person_id, us, pl, 40 + 0.02::DOUBLE * (pl // 5) + (cents % 97 / 97.0::DOUBLE - 0.5::DOUBLE) * 0.0008::DOUBLE AS lat,
       -80 + 0.02::DOUBLE * (pl % 5) + (cents % 89 / 89.0::DOUBLE - 0.5::DOUBLE) * 0.0008::DOUBLE AS lon FROM pt0),
hop AS (SELECT *, lag(us) OVER w AS us0, lag(lat) OVER w AS lat0, lag(lon) OVER w AS lon0 FROM pt WINDOW w AS (PARTITION BY person_id ORDER BY us)),
mv0 AS (SELECT *, 2 * 6371.0088::DOUBLE * asin(least(1.0::DOUBLE, sqrt(power(sin(radians(lat - lat0) / 2), 2) + cos(radians(lat0)) * cos(radians(lat)) * power(sin(radians(lon - lon0) / 2), 2)))) AS km,
        (us - us0) / 3.6e9::DOUBLE AS hours FROM hop),
mv AS (SELECT *, CASE WHEN hours <> 0 THEN km / hours END AS speed, coalesce(CASE WHEN hours <> 0 THEN km / hours END > 1, false) AS moving FROM mv0),
screen AS (SELECT person_id, us, CASE event_type WHEN 'click' THEN 'unlock' WHEN 'view' THEN 'on' WHEN 'error' THEN 'off' WHEN 'purchase' THEN 'lock' END AS status
           FROM ev WHERE event_type IN ('click', 'view', 'error', 'purchase')),
voice AS (SELECT person_id, us, CASE WHEN value < 15 THEN 'silence' WHEN value < 50 THEN 'voice' WHEN value < 80 THEN 'noise' ELSE 'unknown' END AS inference FROM ev),
nap AS (SELECT l_suppkey AS person_id, 1704067200000000 + 60000000 * (row_number() OVER (PARTITION BY l_suppkey ORDER BY l_shipdate, l_orderkey, l_linenumber, l_partkey, l_quantity, l_extendedprice) - 1) AS us,
        CASE WHEN l_quantity <= 30 THEN 'asleep' WHEN l_quantity <= 40 THEN 'restless' WHEN l_quantity <= 47 THEN 'awake' ELSE 'unknown' END AS state FROM lineitem),
step AS (SELECT person_id, us, CAST(floor(value) AS BIGINT) AS steps FROM ev),
bin AS (SELECT person_id, us // 300000000 * 300000000 AS us, CAST(sum(steps) AS BIGINT) AS steps FROM step GROUP BY ALL),
binl AS (SELECT *, CASE WHEN steps < 10 THEN 'sedentary' ELSE 'active' END AS label FROM bin),
bin1 AS (SELECT *, CASE WHEN lag(label) OVER w = label AND us - lag(us) OVER w <= 300000000 THEN 0 ELSE 1 END AS s FROM binl WINDOW w AS (PARTITION BY person_id ORDER BY us)),
bin2 AS (SELECT *, sum(s) OVER (PARTITION BY person_id ORDER BY us) AS r FROM bin1),
stepbout AS (SELECT person_id, label, min(us) AS start_us, max(us) + 300000000 AS end_us, count(*) * 5.0 AS minutes, sum(steps) AS steps FROM bin2 GROUP BY person_id, r, label),
wk0 AS (SELECT l_suppkey AS person_id, (epoch_us(l_shipdate) // 86400000000 + 3) // 7 AS week, l_quantity, l_discount FROM lineitem),
wk1 AS (SELECT person_id, week, CAST(count(*) AS DOUBLE) AS lines, sum(l_quantity) AS quantity, avg(l_discount) AS discount FROM wk0 GROUP BY ALL),
weekly AS (SELECT person_id, week, 'lines' AS feature, lines AS value FROM wk1 UNION ALL SELECT person_id, week, 'quantity', quantity FROM wk1 UNION ALL SELECT person_id, week, 'discount', discount FROM wk1),
space AS (SELECT p.person_id, p.us, p.lat, p.lon, coalesce(min(CASE WHEN n.n_nationkey % 8 < 7 THEN n.n_nationkey % 8 END), 7) AS code
          FROM pt p LEFT JOIN nation n ON abs(p.lat - (40 + 0.02::DOUBLE * (n.n_nationkey // 5))) < 0.001 AND abs(p.lon - (-80 + 0.02::DOUBLE * (n.n_nationkey % 5))) < 0.001 GROUP BY ALL),
spc AS (SELECT person_id, us, lat, lon, (['social_greek','greek','apartment','residence','athletic','green','academic','off_campus'])[code + 1] AS type,
        coalesce(lead(us) OVER (PARTITION BY person_id ORDER BY us), us) AS nxt FROM space),
spb1 AS (SELECT *, CASE WHEN lag(type) OVER w = type THEN 0 ELSE 1 END AS s FROM spc WINDOW w AS (PARTITION BY person_id ORDER BY us)),
spb2 AS (SELECT *, sum(s) OVER (PARTITION BY person_id ORDER BY us) AS r FROM spb1),
spb AS (SELECT person_id, type, min(us) AS start_us, max(nxt) AS end_us, (max(nxt) - min(us)) / 60e6::DOUBLE AS minutes FROM spb2 GROUP BY person_id, r, type),
opens AS (SELECT *, (SELECT status FROM screen b WHERE b.person_id = a.person_id AND b.us < a.us AND b.status IN ('unlock','off','lock') ORDER BY b.us DESC LIMIT 1) AS before,
          (SELECT min(us) FROM screen b WHERE b.person_id = a.person_id AND b.us > a.us AND b.status IN ('off','lock')) AS closes,
          (SELECT max(us) FROM screen b WHERE b.person_id = a.person_id) AS last FROM screen a WHERE status = 'unlock'),
ibout AS (SELECT person_id, us AS start_us, coalesce(closes, last) AS end_us FROM opens WHERE before IS DISTINCT FROM 'unlock'),
opens2 AS (SELECT *, (SELECT status FROM screen b WHERE b.person_id = a.person_id AND b.us < a.us AND b.status IN ('unlock','lock') ORDER BY b.us DESC LIMIT 1) AS before,
          (SELECT min(us) FROM screen b WHERE b.person_id = a.person_id AND b.us > a.us AND b.status = 'lock') AS closes,
          (SELECT max(us) FROM screen b WHERE b.person_id = a.person_id) AS last FROM screen a WHERE status = 'unlock'),
ubout AS (SELECT person_id, us AS start_us, coalesce(closes, last) AS end_us FROM opens2 WHERE before IS DISTINCT FROM 'unlock'),
dev0 AS (SELECT person_id, address, count(DISTINCT us // 86400000000) AS days, count(*) AS scans FROM scan GROUP BY ALL),
dev1 AS (SELECT *, scans / days::DOUBLE AS frequency FROM dev0),
dev AS (SELECT *, round(coalesce((days - avg(days) OVER p) / nullif(stddev_pop(days) OVER p, 0), 0) + coalesce((frequency - avg(frequency) OVER p) / nullif(stddev_pop(frequency) OVER p, 0), 0), 9) AS score
        FROM dev1 WINDOW p AS (PARTITION BY person_id)),
cutv AS (SELECT DISTINCT person_id, score AS cut FROM dev),
two0 AS (SELECT d.person_id, c.cut, CASE WHEN d.score <= c.cut THEN 0 ELSE 1 END AS side, count(*) AS n, var_pop(d.score) * count(*) AS sse FROM dev d JOIN cutv c USING (person_id) GROUP BY ALL),
two1 AS (SELECT person_id, cut, round(sum(sse), 7) AS sse, count(*) AS sides FROM two0 GROUP BY ALL),
two AS (SELECT person_id, min(sse) AS sse2, arg_min(cut, (sse, cut)) AS cut FROM two1 t WHERE sides = 2 OR (SELECT count(*) FROM cutv c WHERE c.person_id = t.person_id) = 1 GROUP BY ALL),
tri0 AS (SELECT d.person_id, a.cut AS c1, b.cut AS c2, CASE WHEN d.score <= a.cut THEN 0 WHEN d.score <= b.cut THEN 1 ELSE 2 END AS side, var_pop(d.score) * count(*) AS sse
         FROM dev d JOIN cutv a USING (person_id) JOIN cutv b ON b.person_id = d.person_id AND a.cut < b.cut GROUP BY ALL),
tri1 AS (SELECT person_id, c1, c2, round(sum(sse), 7) AS sse FROM tri0 GROUP BY ALL HAVING count(*) = 3),
tri AS (SELECT person_id, min(sse) AS sse3, arg_min(c1, (sse, c1, c2)) AS c1, arg_min(c2, (sse, c1, c2)) AS c2 FROM tri1 GROUP BY ALL),
model AS (SELECT t.person_id, t.sse2, coalesce(r.sse3, 0) AS sse3, t.cut, r.c1, coalesce(r.c2, CASE WHEN (SELECT count(*) FROM cutv c WHERE c.person_id = t.person_id) > 1 THEN t.cut END) AS c2 FROM two t LEFT JOIN tri r USING (person_id)),
owner AS (SELECT d.*, CASE WHEN m.c2 IS NULL OR d.score > m.c2 THEN 'self' WHEN m.c1 IS NOT NULL AND d.score > m.c1 THEN 'related' ELSE 'others' END AS owner FROM dev d JOIN model m USING (person_id)),
line0 AS (SELECT w.*, c.week AS cut FROM weekly w JOIN (SELECT DISTINCT person_id, feature, week FROM weekly) c USING (person_id, feature))
"""


#: Added before rounding down to six digits: a half, and a little that no value's fraction falls on, so that halves (times are in microseconds) round alike in every engine.
HALF = 0.500123457


def columns(spec: str) -> list[tuple[str, str]]:
    return [tuple(c.split(":")) for c in spec.split()]


def sql(spec: str, body: str) -> str:
    number = lambda c, n: f"floor(CAST({c} AS DOUBLE) * 1e{n} + {HALF}::DOUBLE) / 1e{n}::DOUBLE AS {c}"
    picked = ", ".join(number(c, DIGITS[k]) if k in DIGITS else f"CAST({c} AS {KINDS[k]}) AS {c}" for c, k in columns(spec))
    return f"WITH RECURSIVE {VIEWS.strip()} SELECT {picked} FROM ({body}) AS result"
