"""All queries of the behavioural engine by name, with the SQL that must give the same rows."""

from __future__ import annotations

from kinetrace.oracles.base import DIGITS, HALF, columns, sql


def _shaped(frame, spec: str):
    from pyspark.sql import functions as F

    kinds = {"b": lambda c: F.col(c).cast("bigint"), "s": lambda c: F.col(c).cast("string")}
    kinds |= {k: (lambda c, n=10**n: F.floor(F.col(c).cast("double") * float(n) + HALF).cast("double") / float(n)) for k, n in DIGITS.items()}
    return frame.select(*(kinds[k](c).alias(c) for c, k in columns(spec)))


def _all() -> list:
    from kinetrace.operators import feature_queries, relational, stream_queries, variants

    return [*feature_queries.QUERIES, *variants.QUERIES, *relational.QUERIES, *stream_queries.QUERIES]


def queries() -> dict:
    """Name to a callable of (spark, sf_dir)."""
    return {name: (lambda s, d, f=run, c=spec: _shaped(f(s, d), c)) for name, spec, run, _ in _all()}


def oracle_sql() -> dict[str, str]:
    return {name: sql(spec, body) for name, spec, _, body in _all() if body}
