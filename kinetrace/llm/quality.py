"""Quality by nearest neighbours in a latent-semantic space.

A text's terms are its character trigrams, upper case and marks kept, hashed into slots, and the event that a
word follows itself, which has slots of its own; they are weighted by damped frequency and by rarity in the
fit sample. A truncated singular value decomposition of the sample
gives the latent space. The sample's labelled vectors (a bounded number) are broadcast; every document's
vector meets all of them in exact blocked products, and its nearest ones by cosine vote with weights that
grow with similarity.

Contract: null and empty texts have the zero vector and get the share of label 1 in the sample, as does
every text if there are no labels; equal cosines are taken in the sample's order; equal texts score equally.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kinetrace.llm import codes as C
from kinetrace.llm.sampling import drawable, remainder, stratified

SLOTS, REPEATS, RANK, NEIGHBOURS, SHARPNESS = 1 << 12, 32, 48, 15, 8.0
#: Bounds of the fit: labelled documents of each label, characters of each.
SAMPLE_DOCS = 1200


@dataclass
class Space:
    rarity: np.ndarray
    axes: np.ndarray  # SLOTS x RANK
    vectors: np.ndarray  # labelled x RANK, of length 1
    labels: np.ndarray
    weights: np.ndarray  # of each labelled vector's vote, so that the sample's shares stand for the population's
    share: float


def histograms(texts: list[str | None]) -> np.ndarray:
    """Texts x SLOTS counts of character trigrams; the last REPEATS slots count repeated words."""
    out = np.zeros((len(texts), SLOTS), np.float32)
    for docs, pieces in C.grouped(texts):
        codes = C.code_points("".join(pieces)).astype(np.uint64)
        if len(codes) < 3:
            continue
        with np.errstate(over="ignore"):
            h = ((codes[:-2] * np.uint64(0x1F123BB5) + codes[1:-1]) * np.uint64(0x1F123BB5) + codes[2:]) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(52)
        doc = np.repeat(docs, [len(p) for p in pieces])
        first, last = docs[0], docs[-1]
        same = doc[2:] == doc[:-2]
        key = (doc[2:] - first)[same] * SLOTS + h[same].astype(np.int64) % (SLOTS - REPEATS)
        out[first : last + 1] += np.bincount(key, minlength=(last - first + 1) * SLOTS).reshape(-1, SLOTS)
        w = C.Words(docs, pieces)
        h = w.hashes()
        again = (h[1:] == h[:-1]) & (w.doc[1:] == w.doc[:-1])
        out[first : last + 1, -REPEATS:] += np.bincount(w.doc[1:][again] - first, minlength=last - first + 1)[:, None]
    return out


def damped(counts: np.ndarray) -> np.ndarray:
    x = np.log1p(counts, out=counts)
    return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-9)


def project(space: Space, texts: list[str | None]) -> np.ndarray:
    x = (damped(histograms(texts)) * space.rarity) @ space.axes
    return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-9) * (np.abs(x).sum(1, keepdims=True) > 1e-9)


def fit(texts: list[str], labels: list[int], share: float, rank: int = RANK, seed: int = 5) -> Space:
    """The latent space of `texts` and their labelled vectors; `share` is label 1's share among all labels."""
    y = np.asarray(labels, float)
    if not len(y):
        return Space(np.zeros(SLOTS, np.float32), np.zeros((SLOTS, 1), np.float32), np.zeros((0, 1), np.float32), y, y, share)
    counts = histograms(texts)
    rarity = np.log((1 + len(y)) / (1 + (counts > 0).sum(0))).astype(np.float32) + 1
    x = damped(counts) * rarity
    rank = min(rank, len(y))
    rng = np.random.default_rng(seed)
    basis = np.linalg.qr(x @ rng.normal(size=(SLOTS, rank + 8)).astype(np.float32))[0]
    for _ in range(3):
        basis = np.linalg.qr(x @ (x.T @ basis))[0]
    axes = np.linalg.svd(basis.T @ x, full_matrices=False)[2][:rank].T.astype(np.float32)
    v = x @ axes
    v /= np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-9)
    own = y.mean()
    weights = np.where(y == 1, share / max(own, 1e-9), (1 - share) / max(1 - own, 1e-9))
    return Space(rarity, axes, v.astype(np.float32), y, weights, share)


def scores(space: Space, texts: list[str | None], block: int = 1024) -> np.ndarray:
    out = np.full(len(texts), space.share)
    if not len(space.labels):
        return out
    k = min(NEIGHBOURS, len(space.labels))
    for at in range(0, len(texts), block):
        v = project(space, texts[at : at + block])
        cosine = v @ space.vectors.T
        near = np.argpartition(-cosine, k - 1, axis=1)[:, :k]
        votes = np.exp(SHARPNESS * (np.take_along_axis(cosine, near, 1).astype(float) - 1)) * space.weights[near]
        voted = (votes * space.labels[near]).sum(1) / votes.sum(1)
        some = np.abs(v).sum(1) > 0
        out[at : at + block][some] = voted[some]
    return out


def train(docs: DataFrame, labels: DataFrame, modulus: int | None = 4, held_out: int = 2, size: int = SAMPLE_DOCS) -> Space:
    """Fit on at most about `size` whole labelled documents of each label, none of them held out."""
    marks = labels.select("doc_id", F.col("quality").cast("int").alias("_quality")).where("_quality is not null").groupBy("doc_id").agg(F.max("_quality").alias("_quality"))
    if modulus:
        marks = marks.where(remainder("doc_id", modulus) != held_out)
    share = marks.agg(F.avg("_quality")).first()[0]
    chosen = stratified(marks, "doc_id", "_quality", size)
    rows = docs.select("doc_id", F.col("text").cast("string").alias("_text")).where(F.col("_text").isNotNull() & drawable("_text")).join(F.broadcast(chosen), "doc_id")
    found = rows.select("doc_id", "_quality", F.col("_text").alias("text")).toArrow().sort_by([("doc_id", "ascending"), ("text", "ascending")])
    return fit(found["text"].to_pylist(), found["_quality"].to_pylist(), float(share if share is not None else 0.5))


def score_rows(docs: DataFrame, space: Space) -> DataFrame:
    """doc_id and score of every row."""
    shared = docs.sparkSession.sparkContext.broadcast(space)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(scores(shared.value, batch.column("text").to_pylist()))], ["doc_id", "score"])

    kept = docs.select("doc_id", F.col("text").cast("string").alias("text"))
    return kept.mapInArrow(run, f"doc_id {kept.schema['doc_id'].dataType.simpleString()}, score double")


def predictions(docs: DataFrame, labels: DataFrame, threshold: float = 0.7) -> DataFrame:
    """doc_id, held_out, score, predicted of every document, learned from the labels that aren't held out."""
    scored = score_rows(docs, train(docs, labels))
    return scored.select("doc_id", (remainder("doc_id", 4) == 2).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
