"""The streaming state machine against the batch bouts."""

from conftest import SF

from kinetrace.operators import phone
from kinetrace.operators.stream_queries import QUERIES
from kinetrace.sources import views as V
from kinetrace.streaming import streams as S

DAY = 24 * S.HOUR_US


def test_equals_batch_bouts(spark):
    batch = {(r.person_id, r.start_us, r.end_us) for r in phone.interaction_bouts(V.screen_events(spark, SF)).collect()}
    free = S.finished(S.screen_states(S.stream_of(spark, SF, ends=True), cap_hours=24 * 3650))
    assert {tuple(r) for r in free.collect()} == batch


def test_cap_ends_bouts(spark):
    query = next(q[2] for q in QUERIES if q[0] == "stream_screen_state")
    rows = query(spark, SF).collect()
    assert rows and all(0 <= r.end_us - r.start_us <= DAY for r in rows)
