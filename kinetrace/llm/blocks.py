"""Dealing fingerprints into groups such that every pair within an error budget meets in some group.

Two fingerprints within `budget` bits agree on one of `budget` + 1 blocks of bits, whichever blocks they are
cut into. So each fingerprint goes, for each block, to the group of those with the same bits there. A group of
more than `hot` rows is dealt again: what is left of its bits is cut into `budget` + 1 blocks, and so on, until no
group is large or `budget` bits are left, which only a few different fingerprints can share. Each row is copied `budget` + 1 times at each level that its group needs.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kinetrace.llm.memory import releasing
from kinetrace.llm.storage import written

#: Hot groups that may be broadcast (16 bytes each); more are joined by a shuffle.
BROADCAST_GROUPS = 1 << 20


def _signed(mask: int) -> int:
    return mask - (1 << 64) if mask >> 63 else mask


def _cut(bits: tuple[int, ...], parts: int) -> list[tuple[int, ...]]:
    edges = [round(len(bits) * i / parts) for i in range(parts + 1)]
    return [bits[a:b] for a, b in zip(edges[:-1], edges[1:], strict=True) if b > a]


def _spread(rows: DataFrame, columns: list[str], of: list[tuple[int, tuple[int, ...], tuple[int, ...]]], budget: int, base: int) -> tuple[DataFrame, list]:
    """Rows (columns, path) copied for each block of the bits that their path leaves, with the group's key; and the new paths (number, used bits, left bits)."""
    new, parts = [], None
    for number, used, left in of:
        structs = []
        for block in _cut(left, budget + 1):
            taken = tuple(sorted(used + block))
            path = base + len(new)
            new.append((path, taken, tuple(b for b in left if b not in block)))
            masks = [sum(1 << (b - 64 * i) for b in taken if 64 * i <= b < 64 * (i + 1)) for i in range(len(columns))]
            key = F.xxhash64(F.lit(path), *(F.col(c).bitwiseAND(F.lit(_signed(m))) for c, m in zip(columns, masks, strict=True)))
            structs.append(F.struct(F.lit(path).alias("path"), key.alias("g")))
        mine = F.array(*structs)
        parts = mine if len(of) == 1 else (F.when(F.col("path") == number, mine) if parts is None else parts.when(F.col("path") == number, mine))
    return rows.select(*columns, F.explode(parts).alias("_b")).select(*columns, "_b.path", "_b.g"), new


def dealt(nodes: DataFrame, columns: list[str], budget: int, hot: int) -> DataFrame:
    """columns and g, the group: groups have `hot` rows (or 2 to the power of `budget`) at most. `nodes` (distinct fingerprints, 64 bits a column) should be written."""
    levels = [(0, (), tuple(range(64 * len(columns))))]
    rows, out, base = nodes.select(*columns, F.lit(0).alias("path")), None, 1
    while True:
        rows, levels = _spread(rows, columns, levels, budget, base)
        base += len(levels)
        last = [number for number, _, left in levels if len(left) <= budget]  # can't be cut into enough blocks; nor need be
        sizes = rows.groupBy("g", "path").agg(F.count("*").alias("n")).where((F.col("n") > hot) & ~F.col("path").isin(last))
        large = written(sizes.select("g"), "groups")
        n = large.count()
        if n == 0:
            cold = rows.select(*columns, "g")
            return cold if out is None else out.union(cold)
        small = F.broadcast(large) if n <= BROADCAST_GROUPS else large
        cold = rows.join(small, "g", "left_anti").select(*columns, "g")
        out = cold if out is None else out.union(cold)
        rows = written(rows.join(small, "g", "left_semi").select(*columns, "path"), "hot")
        live = {r["path"] for r in rows.select("path").distinct().collect()}  # one of the few paths, not of the groups
        levels = [x for x in levels if x[0] in live]


def by_group(rows: DataFrame, run: Callable[[pa.Table], pa.RecordBatch], schema: str, limit: int = 1 << 16) -> DataFrame:
    """`run` on tables of whole groups (column g, rows of a group together). A worker holds about `limit` rows and one group, whatever its partition holds."""

    def walk(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: pa.Table | None = None
        for batch in batches:
            for at in range(0, batch.num_rows, limit):
                part = pa.Table.from_batches([batch.slice(at, limit)])
                held = part if held is None else pa.concat_tables([held, part])
                if len(held) < limit:
                    continue
                g = held.column("g").to_numpy()
                cut = int((g == g[-1]).argmax())  # the last group may go on
                if cut:
                    yield run(held.slice(0, cut))
                    held = held.slice(cut)
        if held is not None and len(held):
            yield run(held)

    return rows.repartition("g").sortWithinPartitions("g").mapInArrow(releasing(walk), schema)
