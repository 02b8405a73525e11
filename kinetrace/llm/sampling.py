"""Bounded samples of labelled rows for fitting, drawn by a hash of the key so that they don't depend on the layout. Texts stay whole."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Labels that a sample tells apart, the commonest first; characters of the longest documents that are drawn.
MOST_LABELS, LONGEST = 1000, 200_000


def remainder(key: str, modulus: int) -> Column:
    """crc32 of the key's text, modulo `modulus`."""
    return F.crc32(F.col(key).cast("string").cast("binary")) % modulus


def unit(key: str) -> Column:
    """A number from 0 to 1 that the key's 63-bit hash gives, so that small shares of very many rows are met."""
    return F.shiftrightunsigned(F.xxhash64(F.col(key).cast("string"), F.lit("sample")), 1) / float(2**63)


def stratified(rows: DataFrame, key: str, label: str, size: int) -> DataFrame:
    """About `size` rows of each label: one pass counts the labels, then a row stays if its hash is below the label's share."""
    found = rows.where(F.col(label).isNotNull()).groupBy(label).count().orderBy(F.desc("count"), label).limit(MOST_LABELS).collect()
    if not found:
        return rows.limit(0)
    share = F.create_map(*(x for r in found for x in (F.lit(r[label]), F.lit(min(1.0, size / r["count"])))))
    return rows.where(F.col(label).isNotNull() & (unit(key) < share[F.col(label)]))


def drawable(text: str) -> Column:
    """Whether a document may be drawn: very long ones aren't, so that a sample of whole texts fits the driver."""
    return F.length(text) <= LONGEST
