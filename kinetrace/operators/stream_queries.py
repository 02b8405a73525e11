"""Streaming queries, each run over what the stream holds now."""

from __future__ import annotations

from kinetrace.sources import views as V
from kinetrace.streaming import streams as S

QUERIES = [
    ("stream_steps_tumbling", "person_id:b us:b steps:b", lambda s, d: S.finished(S.steps_tumbling(S.stream_of(s, d, ends=True))), "SELECT * FROM bin"),
    ("stream_scans_sliding", "person_id:b us:b scans:b", lambda s, d: S.finished(S.scans_sliding(S.stream_of(s, d, ends=True))), "SELECT person_id, w AS us, count(*) AS scans FROM (SELECT person_id, unnest([us // 900000000 * 900000000 - 900000000 * i for i in range(4)]) AS w FROM ev) GROUP BY ALL"),
    ("stream_session_bouts", "person_id:b start_us:b n:b", lambda s, d: S.finished(S.session_bouts(S.stream_of(s, d, ends=True))), "SELECT person_id, min(us) AS start_us, count(*) AS n FROM (SELECT *, sum(f) OVER (PARTITION BY person_id ORDER BY us) AS r FROM (SELECT *, CASE WHEN us - lag(us) OVER (PARTITION BY person_id ORDER BY us) < 1800000000 THEN 0 ELSE 1 END AS f FROM ev)) GROUP BY person_id, r"),
    ("stream_dedup", "event_id:b person_id:b", lambda s, d: S.finished(S.deduplicated(S.stream_of(s, d))), "SELECT event_id, person_id FROM ev"),
    ("stream_static_join", "event_id:b person_id:b category:s", lambda s, d: S.finished(S.with_contacts(S.stream_of(s, d), V.contacts_of(V.call_events(s, d)))), "SELECT event_id, e.person_id, category FROM ev e LEFT JOIN contacts c ON c.person_id = e.person_id AND c.correspondent = e.k WHERE event_type IN ('click', 'view', 'error')"),
    ("stream_stream_join", "person_id:b opened_us:b closed_us:b", lambda s, d: S.finished(S.unlock_to_close(S.stream_of(s, d))), "SELECT a.person_id, a.us AS opened_us, b.us AS closed_us FROM ev a JOIN ev b ON a.person_id = b.person_id AND a.event_type = 'click' AND b.event_type IN ('error', 'purchase') AND b.us > a.us AND b.us <= a.us + 21600000000"),
    ("stream_late", "arrived:b late:b repeated:b accepted:b", lambda s, d: S.late_accounts(s, d), "SELECT n + again + old AS arrived, old AS late, again AS repeated, n AS accepted FROM (SELECT count(*) AS n, count(*) FILTER (k < 10) AS old, count(*) FILTER (k >= 50 AND us > (SELECT max(us) FROM ev) - 172800000000) AS again FROM ev)"),
    ("stream_upsert", "person_id:b day:b quarter:b n:b total:d", lambda s, d: S.upserted(s, d), "SELECT person_id, us // 86400000000 AS day, us // 21600000000 % 4 AS quarter, count(*) AS n, sum(value) AS total FROM ev GROUP BY ALL"),
    ("stream_screen_state_uncapped", "person_id:b start_us:b end_us:b", lambda s, d: S.finished(S.screen_states(S.stream_of(s, d, ends=True), cap_hours=87_600)), "SELECT * FROM ibout"),
    ("stream_screen_state", "person_id:b start_us:b end_us:b", lambda s, d: S.finished(S.screen_states(S.stream_of(s, d, ends=True))), None),
]
