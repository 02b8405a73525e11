"""Exact top-k inner products by MaxScore over shards of vectors.

A vector's components are a query's terms and a shard keeps the postings of each component. The most that
a term can add to any score in the shard bounds it. Terms are taken in order of falling bounds: the leading,
essential ones are summed for every candidate; as soon as a query's later terms together can't lift a
candidate that has nothing more to gain over the k-th best score, the rest is non-essential and is probed,
term block by term block, only for candidates that can still compete. Equal bounds are kept, so ties are
exact. Shards' results are merged by query.

Queries meet shards in a grid of bounded blocks: one task holds one block of queries and one shard, neither
of which grows with the data. Before that, each query meets a pilot, a bounded sample of the candidates: its k-th
best score there is a floor that the k-th best of all can't be below, so every shard prunes from its first slice on,
and returns nothing for a query that it can't serve.

Contract: vectors that are null or hold null or non-finite components take no part; scores are between vectors of
equal length, each length being searched by itself; repeated ids are separate candidates and a query skips all rows
of its own id; ties go to the smaller id; an empty table gives an empty result; empty vectors score 0.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Vectors of a shard, queries of a block, candidates that are scored together, terms probed together; candidates of the pilot.
SHARD, BLOCK, SLICE, PROBE, PILOT = 2048, 8192, 512, 8, 2048


def quantised(vectors: DataFrame, scale: float = 256.0) -> DataFrame:
    """vec_id and v, the components as floor(scale * x); only whole, finite vectors."""
    finite = F.forall("embedding", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    whole = vectors.select("vec_id", F.col("embedding").cast("array<double>").alias("embedding")).where("vec_id is not null and embedding is not null").where(finite)
    return whole.select("vec_id", F.transform("embedding", lambda x: F.floor(x * scale).cast("bigint")).alias("v"))


def search_shard(queries: np.ndarray, query_ids: np.ndarray, shard: np.ndarray, ids: np.ndarray, k: int, floors: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row of the query, id, score) of each query's k best rows of the shard, by score and then by id; those below the query's floor may be left out."""
    order = np.argsort(ids, kind="stable")
    ids, shard = ids[order], shard[order]
    m, n = len(queries), len(ids)
    if not n or not m:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    exact = np.abs(queries).max(initial=0) * np.abs(shard).max(initial=0) * max(1, shard.shape[1]) < 2**53
    kind = np.float64 if exact else object
    q, s = queries.astype(kind), shard.astype(kind)
    low, high = s.min(0), s.max(0)
    bound = np.maximum(q * low, q * high)  # what a term adds at most
    terms = np.argsort(-np.abs(bound).sum(0).astype(float), kind="stable")  # one order for the block
    q, s, bound = q[:, terms], s[:, terms], bound[:, terms]
    rest = np.concatenate((np.cumsum(bound[:, ::-1], 1)[:, ::-1], np.zeros((m, 1), kind)), 1)  # most that terms from t on add
    top_score, top_id = np.full((m, k), -np.inf, kind), np.zeros((m, k), np.int64)
    d = s.shape[1]
    begin = np.full(m, -np.inf) if floors is None else floors
    for at in range(0, n, SLICE):
        part, own = s[at : at + SLICE], ids[at : at + SLICE]
        floor_ = np.maximum(top_score[:, -1], begin)
        essential = min(d, PROBE)
        total = q[:, :essential] @ part[:, :essential].T
        live = total + rest[:, essential, None] >= floor_[:, None]
        live &= query_ids[:, None] != own[None, :]
        while essential < d and live.mean() > 0.25:  # still essential: nearly all candidates compete
            total += q[:, essential : essential + PROBE] @ part[:, essential : essential + PROBE].T
            essential = min(d, essential + PROBE)
            live &= total + rest[:, essential, None] >= floor_[:, None]
        a, b = np.nonzero(live)
        score = total[a, b]
        for t in range(essential, d, PROBE):
            score = score + (q[a, t : t + PROBE] * part[b, t : t + PROBE]).sum(1)
            keep = score + rest[a, min(d, t + PROBE)] >= floor_[a]
            a, b, score = a[keep], b[keep], score[keep]
        if not len(a):
            continue
        row = np.concatenate((np.repeat(np.arange(m), k), a))
        new_score = np.concatenate((top_score.ravel(), score))
        new_id = np.concatenate((top_id.ravel(), own[b]))
        rank = np.lexsort((new_id, -new_score, row)) if exact else np.array(sorted(range(len(row)), key=lambda i: (row[i], -new_score[i], new_id[i])))
        first = np.searchsorted(row[rank], np.arange(m))
        best = rank[first[:, None] + np.arange(k)]
        top_score, top_id = new_score[best], new_id[best]
    r, c = np.nonzero(top_score > -np.inf)
    return r, top_id[r, c], top_score[r, c].astype(np.int64)


def _matrix(table: pa.Table | pa.RecordBatch) -> np.ndarray:
    column = table.column("v")
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return column.flatten().to_numpy(zero_copy_only=False).reshape(table.num_rows, len(column[0]))


def _floored(queries: DataFrame, candidates: DataFrame, number: int, k: int) -> DataFrame:
    """`queries` with floor: the k-th best score among a bounded sample of the candidates, null where it holds fewer than k of the length."""
    share = min(1.0, PILOT / max(1, number))
    unit = F.shiftrightunsigned(F.xxhash64("vec_id", "v", F.lit(3)), 1) / float(2**63)
    pilot: dict[int, tuple[list, list]] = {}
    for r in candidates.where(unit < share).select("vec_id", "v").limit(4 * PILOT).collect():  # the limit only guards the driver: any sample gives a valid floor
        ids, vectors = pilot.setdefault(len(r.v), ([], []))
        ids.append(r.vec_id)
        vectors.append(r.v)
    arrays = {n: (np.array(i, np.int64), np.array(v, np.int64).reshape(len(i), n)) for n, (i, v) in pilot.items()}
    shared = queries.sparkSession.sparkContext.broadcast(arrays)

    def run(batches):
        for whole in batches:
            for at in range(0, whole.num_rows, 1024):
                batch = whole.slice(at, 1024)
                size = np.diff(batch.column("v").offsets.to_numpy())
                floors = np.full(batch.num_rows, np.nan)
                for n in np.unique(size).tolist():
                    rows = np.flatnonzero(size == n)
                    if n not in shared.value:
                        continue
                    ids, vectors = shared.value[n]
                    mine = batch.take(pa.array(rows))
                    row, _, score = search_shard(_matrix(mine), mine.column("vec_id").to_numpy(), vectors, ids, k)
                    full = np.bincount(row, minlength=len(rows)) == k
                    least = np.full(len(rows), np.inf)
                    np.minimum.at(least, row, score)
                    floors[rows[full]] = least[full]
                yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(floors, from_pandas=True)], [*batch.schema.names, "floor"])

    return queries.select("vec_id", "v").mapInArrow(run, "vec_id bigint, v array<bigint>, floor double")


def top_k(candidates: DataFrame, queries: DataFrame, k: int = 5) -> DataFrame:
    """query_id, rank, vec_id, score: for each row of `queries` (vec_id, v) its k best rows of `candidates` (vec_id, v)."""
    asked = {r["n"]: r["count"] for r in queries.groupBy(F.size("v").alias("n")).count().collect()}
    held = {r["n"]: r["count"] for r in candidates.groupBy(F.size("v").alias("n")).count().collect() if r["n"] in asked}
    both = {n: (max(1, -(-c // SHARD)), max(1, -(-asked[n] // BLOCK))) for n, c in held.items()}
    if not both:
        return candidates.select(F.col("vec_id").alias("query_id"), F.lit(1).alias("rank"), "vec_id", F.col("vec_id").alias("score")).limit(0)
    shards = F.create_map(*(F.lit(x) for n, (a, _) in both.items() for x in (n, a)))[F.size("v")]
    blocks = F.create_map(*(F.lit(x) for n, (_, b) in both.items() for x in (n, b)))[F.size("v")]
    spread = lambda n, salt: F.pmod(F.xxhash64("vec_id", "v", F.lit(salt)), n).cast("int")
    known = F.size("v").isin(*both)
    length = F.size("v").alias("length")
    rows = candidates.where(known).select("vec_id", "v", length, spread(shards, 1).alias("shard"), F.explode(F.sequence(F.lit(0), blocks - 1)).alias("block"))
    floored = _floored(queries.where(known), candidates.where(known), sum(held.values()), k)
    asks = floored.select("vec_id", "v", "floor", length, spread(blocks, 2).alias("block"), F.explode(F.sequence(F.lit(0), shards - 1)).alias("shard"))

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        if not len(left) or not len(right):
            return pa.table({c: pa.array([], pa.int64()) for c in ("query_id", "vec_id", "score")})
        ids = right.column("vec_id").to_numpy()
        floors = np.nan_to_num(right.column("floor").to_numpy(), nan=-np.inf)
        row, found, score = search_shard(_matrix(right), ids, _matrix(left), left.column("vec_id").to_numpy(), k, floors)
        return pa.table({"query_id": pa.array(ids[row]), "vec_id": pa.array(found), "score": pa.array(score)})

    key = ("length", "block", "shard")
    parts = rows.groupBy(*key).cogroup(asks.groupBy(*key)).applyInArrow(run, "query_id bigint, vec_id bigint, score bigint")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return parts.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def sampled_queries(vectors: DataFrame, k: int = 5, every: int = 50) -> DataFrame:
    """The k best partners of every vector whose id is divisible by `every`, among all others."""
    rows = quantised(vectors)
    return top_k(rows, rows.where(F.col("vec_id") % every == 0).dropDuplicates(["vec_id", "v"]), k)


#: The same by SQL, for tables small enough for all products.
ORACLE_SQL = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT)) AS v FROM embeddings
           WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
p AS (SELECT q.vec_id AS query_id, c.vec_id AS vec_id,
             CAST(list_sum(list_transform(range(1, len(q.v) + 1), lambda i: q.v[i] * c.v[i])) AS BIGINT) AS score
      FROM v q JOIN v c ON q.vec_id <> c.vec_id AND len(q.v) = len(c.v) WHERE q.vec_id % 50 = 0)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score
FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM p) WHERE rank <= 5
"""
