"""Document fingerprints by SimHash over weighted terms, and permuted block tables to find near ones.

Terms are pairs of neighbouring words (one word where there is only one), words being runs of anything but
white space, lower-cased letter by letter. A term's 128-bit hash votes with the weight 1 + ln(times) on every
bit; a bit is 1 where the signed vote is positive. Likeness is the cosine that the differing bits estimate.

Search: the bits are cut into `radius` + 1 blocks; two fingerprints within the radius agree on one of them, so a
table for each block, keyed by it (the block moved to the front, as it were), brings every near pair together. Keys
with very many rows are keyed again by blocks of their other bits (`blocks`). A task compares the rows of a key and
returns a spanning forest of the near ones.

Contract: null counts as empty; a text without words has the fingerprint zero; equal texts have equal
fingerprints; terms of very long texts are counted in bounded steps, over the whole text; rows of the same id are
ordered by a hash of their text; an only document is its own next one; the class of rows without an id is null.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kinetrace.llm import blocks
from kinetrace.llm import codes as C
from kinetrace.llm.components import components
from kinetrace.llm.storage import written
from kinetrace.llm.trie_join import CHUNK, Forest

BITS, RADIUS, STEP = 128, 3, 1 << 13
#: Most fingerprints of a key, which are compared pair by pair; larger keys are dealt again.
HOT = 4096


def fingerprint_many(texts: list[str | None]) -> np.ndarray:
    """Texts x 2 unsigned 64-bit numbers."""
    out = np.zeros((len(texts), 2), np.uint64)

    def vote(d: int, terms: np.ndarray, counts: np.ndarray) -> None:
        weight = (1 + np.log(counts)).astype(np.float32)
        both = np.stack([C.mixed(terms), C.mixed(terms ^ np.uint64(0xA5A5A5A5A5A5A5A5))], 1)
        total = np.zeros(BITS)
        for a in range(0, len(terms), STEP):
            part = both[a : a + STEP]
            bits = np.unpackbits(part.view(np.uint8).reshape(len(part), 16), axis=1, bitorder="little").astype(np.float32)
            total += 2 * (weight[a : a + STEP] @ bits).astype(float) - float(weight[a : a + STEP].sum(dtype=float))
        out[d] = np.packbits(total > 0, bitorder="little").view(np.uint64)

    open_: tuple | None = None  # the last document seen: its number, terms, counts, last word, and its word if it has only one
    for docs, pieces in C.grouped(texts):
        text = "\n" + "\n".join(pieces) + "\n"
        codes = C.code_points(text)
        lower = C.lowered_letters()[codes]
        codes = np.where(lower > 0, lower, codes)
        inside = C.classes()[codes] != C.SPACE
        edge = np.diff(inside.view(np.int8))
        starts, ends = np.flatnonzero(edge == 1) + 1, np.flatnonzero(edge == -1) + 1
        if not len(starts):
            continue
        border = np.cumsum([len(p) + 1 for p in pieces]) + 1
        owner = np.asarray(docs, np.int64)[np.searchsorted(border, starts, "right")]
        h = C.span_hashes(codes, starts, ends)
        if open_ and open_[0] == owner[0]:  # a text that goes on: its last word pairs with the next
            h, owner = np.append(open_[3], h), np.append(owner[0], owner)
        pair = owner[1:] == owner[:-1]
        with np.errstate(over="ignore"):
            two = C.mixed(h[:-1] * np.uint64(0x9E3779B97F4A7C15) + h[1:])[pair]
        of = owner[:-1][pair]
        order = np.lexsort((two, of))
        two, of = two[order], of[order]
        first = np.flatnonzero(np.append(True, (two[1:] != two[:-1]) | (of[1:] != of[:-1]))[: len(two)])
        count, two, of = np.diff(np.append(first, len(two))), two[first], of[first]
        last = np.append(np.flatnonzero(owner[1:] != owner[:-1]), len(owner) - 1)
        for d, at, words in zip(owner[last].tolist(), last.tolist(), np.diff(np.append(-1, last)).tolist(), strict=True):
            a, b = np.searchsorted(of, (d, d + 1))
            terms, counts, only = two[a:b], count[a:b], h[at : at + 1] if words == 1 else None
            if open_ and open_[0] == d:
                terms, back = np.unique(np.concatenate((open_[1], terms)), return_inverse=True)
                counts = np.bincount(back, np.concatenate((open_[2], counts))).astype(np.int64)
            elif open_:
                vote(open_[0], *((open_[4], np.ones(1)) if open_[4] is not None else open_[1:3]))
            open_ = (d, terms, counts, h[at], only)
    if open_:
        vote(open_[0], *((open_[4], np.ones(1)) if open_[4] is not None else open_[1:3]))
    return out


def likeness(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Estimated cosine, 0 to 1, of the texts behind two arrays of fingerprints; 1 exactly where they are equal."""
    differ = np.bitwise_count(a ^ b).sum(1)
    return np.clip(np.cos(math.pi * differ / BITS), 0, 1)


def as_text(found: np.ndarray) -> list[str]:
    return [f"{a:016x}{b:016x}" for a, b in found.tolist()]


def edited(text: str, following: str) -> str:
    """`text` with its last third replaced by the beginning of the following document."""
    k = len(text) // 3
    return text[: len(text) - k] + following[:k]


def _digests(ids: pa.Array, texts: list[str], following: list[str]) -> pa.RecordBatch:
    changed = [edited(a, b) for a, b in zip(texts, following, strict=True)]
    n = len(texts)
    found = fingerprint_many([*texts, *following[-1:]])
    own = found[:n]
    after = np.concatenate((found[1:n], found[n:])) if all(x is y for x, y in zip(texts[1:], following, strict=False)) else fingerprint_many(following)
    other = fingerprint_many(changed)
    return pa.RecordBatch.from_arrays(
        [
            ids, pa.array([len(x) for x in texts], pa.int64()), pa.array([hashlib.sha256(x.encode()).hexdigest() for x in changed], pa.string()),
            pa.array(as_text(own), pa.string()), pa.array(as_text(other), pa.string()), pa.array(likeness(own, other)), pa.array(likeness(own, after)),
            pa.array(own[:, 0].view(np.int64)), pa.array(own[:, 1].view(np.int64)),
        ],
        ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next", "high", "low"],
    )


COLUMNS = "n_chars bigint, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double, high bigint, low bigint"


def with_edits(docs: DataFrame) -> DataFrame:
    """Every document's digest row, the next document being the one before it in id, after the smallest the largest.

    One shuffle deals the documents by ranges of ids. A task walks its range from the largest id down; only the
    first and the last document of each range go through shared storage to meet the neighbouring range.
    """
    spark = docs.sparkSession
    kept = docs.select("doc_id", F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    key = kept.schema["doc_id"].dataType.simpleString()
    walk = kept.repartitionByRange(F.desc("doc_id")).sortWithinPartitions(F.desc("doc_id"), F.xxhash64("text"), "text")
    names = ["part", "edge", "text"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, held, number = TaskContext.get().partitionId(), None, 0
        kinds = [pa.int32(), pa.int32(), pa.string()]

        def rows(batch: pa.RecordBatch, edge: int | None, texts: list[str | None]) -> pa.RecordBatch:
            more = [pa.array([part] * batch.num_rows, kinds[0]), pa.array([edge] * batch.num_rows, kinds[1]), pa.array(texts, kinds[2])]
            return pa.RecordBatch.from_arrays([*batch.columns, *more], [*batch.schema.names, *names])

        def bare(ids: pa.Array) -> pa.RecordBatch:
            kinds = [pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64(), pa.int64(), pa.int64()]
            return pa.RecordBatch.from_arrays([ids, *(pa.nulls(len(ids), k) for k in kinds)], ["doc_id", *(c.split()[0] for c in COLUMNS.split(", "))])

        for batch in batches:
            for at in range(0, batch.num_rows, 1000):
                ids, texts = batch.column("doc_id").slice(at, 1000), batch.column("text").slice(at, 1000).to_pylist()
                if held is None:
                    yield rows(bare(ids.slice(0, 1)), 0, texts[:1])
                else:
                    ids, texts = pa.concat_arrays([held[0], ids]), [held[1], *texts]
                held = (ids.slice(len(ids) - 1), texts[-1])
                if len(texts) > 1:
                    done = _digests(ids.slice(0, len(ids) - 1), texts[:-1], texts[1:])
                    yield rows(done, None, [None] * done.num_rows)
                    number += done.num_rows
        if held is not None:
            yield rows(bare(held[0]), 1, [held[1]])

    found = written(walk.mapInArrow(run, f"doc_id {key}, {COLUMNS}, part int, edge int, text string"), "edits")
    parts = sorted(r["part"] for r in found.where("edge = 0").select("part").collect())
    if not parts:
        return found.select("doc_id", *(c.split()[0] for c in COLUMNS.split(", ")))
    after = spark.createDataFrame([*zip(parts, [*parts[1:], parts[0]], strict=True)], "part int, following_part int")
    heads = found.where("edge = 0").select(F.col("part").alias("following_part"), F.col("text").alias("following"))
    lasts = found.where("edge = 1").select("doc_id", "part", "text").join(F.broadcast(after), "part").join(heads, "following_part").select("doc_id", "text", "following")

    def close(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield _digests(batch.column("doc_id"), batch.column("text").to_pylist(), batch.column("following").to_pylist())

    schema = f"doc_id {key}, {COLUMNS}"
    return found.where("edge is null").drop(*names).union(lasts.mapInArrow(close, schema))


def fingerprints(docs: DataFrame) -> DataFrame:
    """doc_id and its fingerprint as two numbers, high and low."""
    kept = docs.select("doc_id", F.col("text").cast("string").alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = fingerprint_many(batch.column("text").to_pylist()).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(found[:, 0].copy()), pa.array(found[:, 1].copy())], ["doc_id", "high", "low"])

    return kept.mapInArrow(run, f"doc_id {kept.schema['doc_id'].dataType.simpleString()}, high bigint, low bigint")


def near_classes(found: DataFrame, radius: int = RADIUS) -> DataFrame:
    """doc_id and class_id: fingerprints within `radius` bits, and what they reach, share the class of the least id.

    `found` (doc_id, high, low) should be written: it is read twice."""
    return found.select("doc_id", "high", "low").join(_classes(found, radius), ["high", "low"]).select("doc_id", "class_id")


def _classes(found: DataFrame, radius: int) -> DataFrame:
    """high, low and class_id of every different fingerprint."""
    nodes = written(found.groupBy("high", "low").agg(F.min("doc_id").alias("least")), "nodes")

    def run(table: pa.Table) -> pa.RecordBatch:
        high, low, g = (table.column(c).to_numpy() for c in ("high", "low", "g"))
        order = np.lexsort((low, high, g))
        high, low, g = high[order], low[order], g[order]
        x, y = high.view(np.uint64), low.view(np.uint64)
        first = np.flatnonzero(np.append(True, g[1:] != g[:-1]))
        end = np.repeat(np.append(first[1:], len(g)), np.diff(np.append(first, len(g))))
        forest = Forest(len(g))
        gap = 1
        live = np.flatnonzero(np.arange(len(g)) + gap < end)
        while len(live):  # rows at distance 1, 2, ... of the same key, those of one tree left out
            for at in range(0, len(live), CHUNK):
                a = live[at : at + CHUNK]
                b = a + gap
                a, b = a[forest.parent[a] != forest.parent[b]], b[forest.parent[a] != forest.parent[b]]
                close = np.bitwise_count(x[a] ^ x[b]) + np.bitwise_count(y[a] ^ y[b]) <= radius
                forest.link(a[close], b[close])
            gap += 1
            live = live[live + gap < end[live]]
        child = np.flatnonzero(forest.parent != np.arange(len(g)))
        sides = [pa.StructArray.from_arrays([pa.array(high[i]), pa.array(low[i])], ["high", "low"]) for i in (child, forest.parent[child])]
        return pa.RecordBatch.from_arrays(sides, ["a", "b"])

    print_ = "struct<high:bigint,low:bigint>"
    roots = components(blocks.by_group(blocks.dealt(nodes, ["high", "low"], radius, HOT), run, f"a {print_}, b {print_}"))
    linked = roots.select("node.high", "node.low", "root").join(nodes, ["high", "low"])
    named = linked.join(linked.groupBy("root").agg(F.min("least").alias("class_id")), "root").select("high", "low", "class_id")
    alone = F.col("class_id").isNull()  # of a class without any id, too
    return written(nodes.join(named, ["high", "low"], "left").select("high", "low", F.when(alone, F.col("least")).otherwise(F.col("class_id")).alias("class_id")), "classes")


def edit_rows(docs: DataFrame, radius: int = RADIUS) -> DataFrame:
    """`with_edits` and class_id, the least id that is reachable over fingerprints within `radius` bits."""
    rows = written(with_edits(docs), "rows")
    return rows.join(_classes(rows, radius), ["high", "low"]).drop("high", "low")
