"""SimHash near-duplicates: a binary trie self-join of the distinct fingerprints.

Words are the runs of anything but ASCII white space of the text with A-Z lower-cased; shingles of
four words, repeats included, are hashed by XXH64 (seed 42) and vote on 64 bits.

The join deals the distinct fingerprints into groups that agree on a block of bits (`blocks`), and dense groups
again by further blocks, so no group is large and no near pair is lost. In each group stands a binary trie, which
is a sorted array: a node is a range of rows with a common prefix. The join walks pairs of nodes together, skips to
the first bit at which either branches, counts the differing bits of the two prefixes and drops the pair as soon as
they exceed the budget; it also drops pairs whose rows are all known to belong together. A task returns a spanning
forest of the links that it finds, so groups of thousands of copies never become all their pairs, and no link
between groups is lost.

Contract: null or blank text has the fingerprint zero and is linked like any other; equal rows share
their component; an empty table gives an empty result; long texts are hashed in bounded steps.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kinetrace.llm import blocks
from kinetrace.llm.components import components
from kinetrace.llm.storage import written

SHINGLE, SEED, BUDGET = 4, 42, 4
#: Most fingerprints of a trie; larger groups are dealt again.
HOT = 50_000
LEAF, CHUNK, STEP = 24, 100_000, 1 << 16


def simhash(text: str | None) -> int:
    """The fingerprint of one text."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    joined = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))
    n = max(1, len(words) - SHINGLE + 1)
    votes, digest = np.zeros(64, np.int64), xxhash.xxh64_intdigest
    for at in range(0, n, STEP):
        to = min(n, at + STEP)
        last = ends[at + SHINGLE - 1 : to + SHINGLE - 1] if len(words) >= SHINGLE else ends[-1:]
        hashes = np.array([digest(joined[a:b], SEED) for a, b in zip(starts[at:to].tolist(), last.tolist(), strict=True)], "<u8")
        votes += np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(votes * 2 > n, bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame) -> DataFrame:
    """doc_id and fp, the fingerprint as a signed 64-bit number."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = np.fromiter((simhash(x.as_py()) for x in batch.column("text")), np.uint64, batch.num_rows)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(found.view(np.int64))], ["doc_id", "fp"])

    kept = docs.select("doc_id", F.col("text").cast("string").alias("text"))
    return kept.mapInArrow(run, f"doc_id {kept.schema['doc_id'].dataType.simpleString()}, fp bigint")


def _leading_zeros(x: np.ndarray) -> np.ndarray:
    for s in (1, 2, 4, 8, 16, 32):
        x = x | x >> np.uint64(s)
    return 64 - np.bitwise_count(x).astype(np.int64)


class Forest:
    """Union-find over rows with array operations."""

    def __init__(self, n: int):
        self.parent = np.arange(n)
        self.changed = True

    def link(self, a: np.ndarray, b: np.ndarray) -> None:
        while len(a):
            a, b = self.parent[a], self.parent[b]
            apart = a != b
            a, b = a[apart], b[apart]
            if not len(a):
                return
            np.minimum.at(self.parent, np.maximum(a, b), np.minimum(a, b))
            while True:
                up = self.parent[self.parent]
                if (up == self.parent).all():
                    break
                self.parent = up
            self.changed = True

    def breaks(self) -> np.ndarray:
        """Running number of places where neighbouring rows are of different trees."""
        if self.changed:
            self._breaks = np.concatenate(([0], np.cumsum(self.parent[1:] != self.parent[:-1])))
            self.changed = False
        return self._breaks


def trie_links(keys: np.ndarray, group: np.ndarray, budget: int) -> tuple[np.ndarray, np.ndarray]:
    """A spanning forest, as two arrays of rows, of the pairs of `keys` within `budget` bits and one group.

    keys: uint64, sorted within each group; groups are runs.
    """
    n = len(keys)
    if n < 2:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    forest = Forest(n)
    first = np.flatnonzero(np.concatenate(([True], group[1:] != group[:-1])))
    lo, hi = first, np.append(first[1:], n)
    stack = [np.stack([lo, hi, lo, hi], 1)]
    ones = np.uint64(0xFFFFFFFFFFFFFFFF)
    while stack:
        pairs = stack.pop()
        if len(pairs) > CHUNK:
            stack.append(pairs[CHUNK:])
            pairs = pairs[:CHUNK]
        pairs = pairs[(pairs[:, 1] > pairs[:, 0]) & (pairs[:, 3] > pairs[:, 2])]
        a0, a1, b0, b1 = pairs.T
        own = a0 == b0
        breaks = forest.breaks()
        known = (breaks[a1 - 1] == breaks[a0]) & (breaks[b1 - 1] == breaks[b0]) & (forest.parent[a0] == forest.parent[b0])
        keep = ~known & ~(own & (a1 - a0 < 2))
        a0, a1, b0, b1, own = a0[keep], a1[keep], b0[keep], b1[keep], own[keep]
        if not len(a0):
            continue
        da, db = _leading_zeros(keys[a0] ^ keys[a1 - 1]), _leading_zeros(keys[b0] ^ keys[b1 - 1])
        depth = np.minimum(da, db)
        shift = np.minimum(64 - depth, 63).astype(np.uint64)
        differ = np.where(depth == 0, np.uint64(0), (keys[a0] ^ keys[b0]) >> shift)
        differ = np.where(depth == 64, keys[a0] ^ keys[b0], differ)
        errors = np.bitwise_count(differ).astype(np.int64)
        near = errors <= budget
        all_near = near & (errors + 64 - depth <= budget)
        for x0, x1 in ((a0[all_near], a1[all_near]), (b0[all_near], b1[all_near])):
            size = x1 - x0
            rows = np.repeat(x0 - (np.cumsum(size) - size), size) + np.arange(size.sum())
            forest.link(rows, np.repeat(a0[all_near], size))
        go = near & ~all_near
        a0, a1, b0, b1, own, da, db, depth = (x[go] for x in (a0, a1, b0, b1, own, da, db, depth))
        small = (a1 - a0 <= LEAF) & (b1 - b0 <= LEAF)
        if small.any():
            wide, tall = a1[small] - a0[small], b1[small] - b0[small]
            count = wide * tall
            nth = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
            tall_of = np.repeat(tall, count)
            x, y = np.repeat(a0[small], count) + nth // tall_of, np.repeat(b0[small], count) + nth % tall_of
            close = np.bitwise_count(keys[x] ^ keys[y]) <= budget
            forest.link(x[close], y[close])
        big = ~small
        a0, a1, b0, b1, own, da, db, depth = (x[big] for x in (a0, a1, b0, b1, own, da, db, depth))
        if not len(a0):
            continue

        def halves(x0, x1, splits):
            """The border between the rows with bit `depth` clear and set; the whole range where it doesn't branch."""
            at = np.minimum(depth, 63).astype(np.uint64)
            low = ones >> at
            border = keys[x0] & ~low | (np.uint64(1) << (np.uint64(63) - at))
            left, right = x0.copy(), x1.copy()
            while (left < right).any():  # binary search within each node's own range
                middle = (left + right) // 2
                less = keys[np.minimum(middle, n - 1)] < border
                open_ = left < right
                left = np.where(open_ & less, middle + 1, left)
                right = np.where(open_ & ~less, middle, right)
            return np.where(splits, left, x1)

        am, bm = halves(a0, a1, da == depth), halves(b0, b1, db == depth)
        s = own
        stack.append(np.concatenate([np.stack([a0[s], am[s], am[s], a1[s]], 1)]))
        o = ~own
        stack.append(np.concatenate([np.stack([x0[o], x1[o], y0[o], y1[o]], 1) for x0, x1 in ((a0, am), (am, a1)) for y0, y1 in ((b0, bm), (bm, b1))]))
        stack.append(np.concatenate([np.stack([a0[s], am[s], a0[s], am[s]], 1), np.stack([am[s], a1[s], am[s], a1[s]], 1)]))
    child = np.flatnonzero(forest.parent != np.arange(n))
    return child, forest.parent[child]


def links(nodes: DataFrame, budget: int = BUDGET) -> DataFrame:
    """Edges (a, b) between the distinct fingerprints `fp` of `nodes` (written): together they connect what is
    connected by pairs within `budget` bits."""

    def run(table: pa.Table) -> pa.RecordBatch:
        key, g = table.column("fp").to_numpy().view(np.uint64), table.column("g").to_numpy()
        order = np.lexsort((key, g))
        child, parent = trie_links(key[order], g[order], budget)
        back = lambda x: pa.array(key[order[x]].view(np.int64))
        return pa.RecordBatch.from_arrays([back(child), back(parent)], ["a", "b"])

    return blocks.by_group(blocks.dealt(nodes, ["fp"], budget, HOT), run, "a bigint, b bigint")


def near_duplicates(docs: DataFrame, budget: int = BUDGET) -> DataFrame:
    """doc_id, fp and component_id, the smallest doc_id that is reachable over links."""
    found = written(fingerprints(docs), "fingerprints")
    nodes = written(found.groupBy("fp").agg(F.min("doc_id").alias("least")), "nodes")
    roots = components(links(nodes, budget)).withColumnRenamed("node", "fp")
    linked = roots.join(nodes, "fp")
    least = linked.groupBy("root").agg(F.min("least").alias("component_id"))
    named = linked.select("fp", "root").join(least, "root").select("fp", "component_id")
    classes = written(nodes.join(named, "fp", "left").select("fp", F.coalesce("component_id", "least").alias("component_id")), "classes")
    return found.join(classes, "fp")


def fingerprint_rows(docs: DataFrame) -> DataFrame:
    """doc_id, fingerprint as 16 hexadecimal digits, component_id."""
    return near_duplicates(docs).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
