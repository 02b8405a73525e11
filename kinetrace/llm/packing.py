"""Packing token sequences into windows: a configuration linear program on the histogram of lengths.

A configuration is a multiset of lengths that fits one window. The program "cover every length's
count with as few configurations as possible" is solved by multiplicative weights. Each round prices a
length by its share of the window times its weight, finds the dearest configurations by a knapsack
dynamic program, takes whole windows of them, and multiplies the weights of the lengths that these hold
by a factor below one. Any prices give a lower bound, too: all rows' prices over the dearest
configuration's. Windows are whole from the start, so rounding is only needed for the last RESIDUE of
the rows: these go, longest first, into the least room that holds them, of the program's windows or of
new ones. `solved` returns the windows with the bound; their ratio less one is the gap.

Only the histogram (at most `capacity` rows) reaches the driver; rows learn their place from their rank
among the rows of the same length.

Contract: null text counts as empty (one end token); documents over the capacity are cut into full
pieces of which the first may be shorter; repeated rows are packed each; an empty table gives an
empty result; columns other than doc_id and text are ignored.
"""

from __future__ import annotations

import zlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from kinetrace.llm import bpe
from kinetrace.llm.memory import releasing
from kinetrace.llm.storage import written

END = 0
#: Price of a full window of one row above that of many (long rows are hard to place late), tried in turn until the gap
#: is at most GAP; how far below the dearest
#: configuration's price others of the same round may lie; decay of a weight when all of a length is covered; share of
#: what a length has left that one round takes; share of the rows that is placed after the program.
LONG, GAP, NEAR, RATE, STEP, RESIDUE = (0.3, 1.0, 4.0), 0.002, 0.005, 0.5, 0.5, 0.05
#: Rows that one ranking group holds at most on average, and the least number of groups of a length.
RANKED, GROUPS = 1 << 21, 64
_ENCODERS: dict[str, bpe.Encoder] = {}


def _encoder(path: str) -> bpe.Encoder:
    """The encoder of this worker; new pre-tokens are merged by the compiled merge loop of tiktoken."""
    if path not in _ENCODERS:
        import tiktoken

        vocabulary = bpe.Vocabulary(path)
        special = set(vocabulary.special.values())
        ranks = {t: i for i, t in enumerate(vocabulary.tokens) if i not in special}
        one = tiktoken.Encoding("pieces", pat_str=r"[\s\S]+", mergeable_ranks=ranks, special_tokens={})._encode_single_piece
        _ENCODERS[path] = bpe.Encoder(vocabulary, lambda words: [one(w) for w in words])
    return _ENCODERS[path]


def token_pieces(docs: DataFrame, path: str, capacity: int = 2048, by: str | None = None) -> DataFrame:
    """A row for each piece of each document: doc_id, piece, start, length, ids_crc32, and the document's `by`, a column of strings, if given."""
    more = [by] if by else []

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = _encoder(path)
        for batch in batches:
            row, piece, start, length, crc = [], [], [], [], []
            for d, arrays in bpe.ids_by_document(encoder, batch.column("text").to_pylist()):
                ids = np.concatenate([*arrays, np.array([END], np.uint32)]).astype("<u4")
                at, k = 0, 0
                while at < len(ids):
                    to = at + (len(ids) % capacity or capacity) if k == 0 else at + capacity
                    row.append(d)
                    piece.append(k)
                    start.append(at)
                    length.append(to - at)
                    crc.append(zlib.crc32(ids[at:to].tobytes()))
                    at, k = to, k + 1
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id").take(pa.array(row, pa.int64())), pa.array(piece, pa.int32()), *(pa.array(x, pa.int64()) for x in (start, length, crc)), *(batch.column(c).take(pa.array(row, pa.int64())) for c in more)],
                ["doc_id", "piece", "start", "length", "ids_crc32", *more],
            )
        encoder.forget()

    kept = docs.select("doc_id", F.col("text").cast("string").alias("text"), *(F.col(c).cast("string").alias(c) for c in more))
    key = kept.schema["doc_id"].dataType.simpleString()
    return kept.mapInArrow(releasing(run), f"doc_id {key}, piece int, start bigint, length bigint, ids_crc32 bigint" + "".join(f", `{c}` string" for c in more))


def _worth(sizes: np.ndarray, prices: np.ndarray, capacity: int) -> tuple[np.ndarray, list[int]]:
    """For each room up to the capacity the price of its dearest multiset and one size of it, -1 where a smaller room is as dear."""
    least = int(sizes[0])
    dense = np.full(capacity + 1, -np.inf)
    dense[sizes] = prices
    dense = dense[least:]
    best, pick = np.zeros(capacity + 1), np.full(capacity + 1, -1)
    for c in range(least, capacity + 1):
        worth = dense[: c - least + 1] + best[: c - least + 1][::-1]
        j = int(worth.argmax())
        best[c] = best[c - 1]
        if worth[j] > best[c]:
            best[c], pick[c] = worth[j], j + least
    return best, pick.tolist()


def _traced(pick: list[int], room: int) -> list[int]:
    """The sizes, with repeats, of the dearest multiset of a room."""
    chosen = []
    while room > 0:
        if pick[room] < 0:
            room -= 1
        else:
            chosen.append(pick[room])
            room -= pick[room]
    return chosen


def _knapsack(sizes: np.ndarray, prices: np.ndarray, capacity: int) -> list[int]:
    """Indices, with repeats, of the dearest multiset of sizes within the capacity."""
    return np.searchsorted(sizes, _traced(_worth(sizes, prices, capacity)[1], capacity)).tolist()


def _within(chosen: list[int], sizes: np.ndarray, left: np.ndarray, touched: set[int], capacity: int) -> dict[int, int]:
    """The configuration as far as rows are left of its lengths (indices to numbers); the longest others that fit make up for the rest."""
    held = {i: min(k, int(left[i])) for i, k in Counter(np.searchsorted(sizes, chosen).tolist()).items()}
    room = capacity - sum(int(sizes[i]) * k for i, k in held.items())
    i = int(np.searchsorted(sizes, room, "right")) - 1
    while i >= 0:
        size, more = int(sizes[i]), 0
        if i not in touched:
            more = min(int(left[i]) - held.get(i, 0), room // size)
        if more > 0:
            held[i] = held.get(i, 0) + more
            room -= more * size
        i = min(i, int(np.searchsorted(sizes, room, "right"))) - 1
    return held


def configurations(histogram: dict[int, int], capacity: int, residue: float = RESIDUE, long: float = LONG[0]) -> tuple[list[tuple[dict[int, int], int]], dict[int, int], float]:
    """The program's windows with their multiplicity, the rows that it leaves (at most the share `residue`), and its lower bound.

    A round takes the dearest configuration and those near its price that have no length in common with one taken before."""
    sizes = np.array(sorted(histogram), np.int64)
    counts = np.array([histogram[s] for s in sizes.tolist()], np.int64)
    left, weight, found = counts.copy(), np.ones(len(sizes)), {}
    bound = float((sizes * counts).sum() / capacity)
    while left.sum() > residue * counts.sum():
        live = np.flatnonzero(left > 0)
        share = sizes[live] / capacity
        prices = share * weight[live] * (1 + long * share)
        best, pick = _worth(sizes[live], prices, capacity)
        bound = max(bound, float((counts[live] * prices).sum() / best[capacity]))
        worth = prices + best[capacity - sizes[live]]
        order = np.argsort(-worth, kind="stable")
        touched: set[int] = set()
        for i in live[order[worth[order] >= (1 - NEAR) * worth.max()]].tolist():
            if i in touched:
                continue
            chosen = [int(sizes[i]), *_traced(pick, capacity - int(sizes[i]))]
            if not touched.isdisjoint(np.searchsorted(sizes, chosen).tolist()):
                continue
            held = _within(chosen, sizes, left, touched, capacity)
            touched.update(held)
            amount = min(int(left[j]) // k for j, k in held.items())
            amount = amount if amount <= 2 else max(1, int(amount * STEP))
            for j, k in held.items():
                left[j] -= amount * k
                weight[j] *= np.exp(-RATE * amount * k / counts[j])
            key = tuple(sorted((int(sizes[j]), k) for j, k in held.items()))
            found[key] = found.get(key, 0) + amount
    return [(dict(k), n) for k, n in found.items()], {int(sizes[i]): int(left[i]) for i in np.flatnonzero(left).tolist()}, bound


def best_fit_decreasing(histogram: dict[int, int], capacity: int, begun: list[tuple[dict[int, int], int]] = ()) -> list[tuple[dict[int, int], int]]:
    """Windows with their multiplicity, `begun` ones filled first; packed on counts: equal windows move together."""
    rooms: dict[int, list[tuple[tuple[tuple[int, int], ...], int]]] = {}
    for config, k in begun:
        rooms.setdefault(capacity - sum(s * n for s, n in config.items()), []).append((tuple(config.items()), k))
    for size in sorted(histogram, reverse=True):
        n = histogram[size]
        room = size
        while n > 0 and room <= capacity:
            if not rooms.get(room):
                room += 1
                continue
            items, k = rooms[room].pop()
            fit = room // size
            if n < fit:  # a last window takes what is left
                taken, each = 1, n
            else:
                taken, each = min(k, n // fit), fit
            if k > taken:
                rooms[room].append((items, k - taken))
            rooms.setdefault(room - each * size, []).append((_with(items, size, each), taken))
            n -= taken * each
        fit = capacity // size
        for taken, each in ((n // fit, fit), (1, n % fit)):
            if taken and each:
                rooms.setdefault(capacity - each * size, []).append((((size, each),), taken))
    return [(dict(items), k) for group in rooms.values() for items, k in group]


def _with(items: tuple[tuple[int, int], ...], size: int, each: int) -> tuple[tuple[int, int], ...]:
    """`items` and some more of a size, which they may hold already."""
    had = dict(items)
    had[size] = had.get(size, 0) + each
    return tuple(had.items())


def solved(histogram: dict[int, int], capacity: int) -> tuple[list[tuple[dict[int, int], int]], float]:
    """Windows that hold every row, and the lower bound of the program on their number."""
    best, least, bound = [], None, 0.0
    for long in LONG:
        found, rest, dual = configurations(histogram, capacity, long=long)
        found, bound = best_fit_decreasing(rest, capacity, found), max(bound, dual)
        used = sum(k for _, k in found)
        if least is None or used < least:
            best, least = found, used
        if least <= max((1 + GAP) * bound, np.ceil(bound - 1e-9)):
            break
    return best, bound


def windows(histogram: dict[int, int], capacity: int) -> list[tuple[dict[int, int], int]]:
    return solved(histogram, capacity)[0]


def places(found: list[tuple[dict[int, int], int]]) -> dict[int, tuple[np.ndarray, ...]]:
    """For each length the blocks of ranks: first rank, first window, items in a window, their first offset."""
    table: dict[int, list[tuple[int, int, int, int]]] = {}
    used: dict[int, int] = {}
    base = 0
    for config, k in found:
        offset = 0
        for size, n in config.items():
            rank = used.get(size, 0)
            table.setdefault(size, []).append((rank, base, n, offset))
            used[size] = rank + k * n
            offset += size * n
        base += k
    return {s: tuple(np.array(x, np.int64).T) for s, x in table.items()}


def ranked(pieces: DataFrame, kind: str = "length") -> DataFrame:
    """`pieces` with a rank from 0 within each length (or kind); its rows are dealt to many groups by a hash."""
    groups = max(GROUPS, -(-pieces.count() // RANKED))
    dealt = pieces.withColumn("_group", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(groups)))
    before = Window.partitionBy(kind).orderBy("_group").rowsBetween(Window.unboundedPreceding, -1)
    bases = (
        dealt.groupBy(kind, "_group")
        .count()
        .select(kind, "_group", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("_base"))
    )
    within = Window.partitionBy(kind, "_group").orderBy("doc_id", "piece", "start")
    numbered = dealt.withColumn("_row", F.row_number().over(within) - 1)
    return numbered.join(bases, [kind, "_group"]).withColumn("_rank", F.col("_row") + F.col("_base"))


def pack_pieces(pieces: DataFrame, capacity: int = 2048, by: str | None = None) -> DataFrame:
    """`pieces` (written once: it is read three times) with sequence_id and offset; a sequence holds pieces of one value of `by` (null counts as
    empty), if given. These are few: the driver solves each value's program."""
    names, wide = ["doc_id", "piece", "start", "length", "ids_crc32", *([by] if by else [])], capacity + 1
    group = F.coalesce(F.col(by), F.lit("")) if by else F.lit("")
    histograms: dict[str, dict[int, int]] = {}
    for r in pieces.groupBy(group.alias("g"), "length").count().collect():
        histograms.setdefault(r["g"], {})[r["length"]] = r["count"]
    # A kind is a length of a group: the group's number times `wide`, and the length.
    table, base, order = {}, 0, sorted(histograms)
    for number, g in enumerate(order):
        found = windows(histograms[g], capacity)
        table |= {number * wide + size: (x[0], x[1] + base, *x[2:]) for size, x in places(found).items()}
        base += sum(k for _, k in found)
    numbers = F.create_map(*(F.lit(x) for n, g in enumerate(order) for x in (g, n)))[group] if len(order) > 1 else F.lit(0)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            kind, rank = batch.column("_kind").to_numpy(), batch.column("_rank").to_numpy()
            sequence, offset = np.zeros(len(rank), np.int64), np.zeros(len(rank), np.int64)
            for one in np.unique(kind).tolist():
                rows = np.flatnonzero(kind == one)
                first, start, n, at = table[one]
                block = np.searchsorted(first, rank[rows], "right") - 1
                nth = rank[rows] - first[block]
                sequence[rows] = start[block] + nth // n[block]
                offset[rows] = at[block] + nth % n[block] * (one % wide)
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in names), pa.array(sequence), pa.array(offset)], [*names, "sequence_id", "offset"])

    schema = pieces.select(*names).schema.add("sequence_id", LongType()).add("offset", LongType())
    kinds = pieces.withColumn("_kind", (numbers * wide + F.col("length")).cast("bigint"))
    return ranked(kinds, "_kind").select(*names, "_kind", "_rank").mapInArrow(run, schema)


def pack(docs: DataFrame, path: str, capacity: int = 2048, by: str | None = None) -> DataFrame:
    """Every document's pieces with their place in as few windows of `capacity` tokens as the method finds, those of each value of `by` by themselves."""
    return pack_pieces(written(token_pieces(docs, path, capacity, by), "pieces"), capacity, by)
