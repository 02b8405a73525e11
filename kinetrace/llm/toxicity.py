"""Toxicity by non-negative positive-unlabelled learning, in numpy.

The classifier sees confirmed toxic texts and unlabelled texts. Its risk is estimated as
prior * loss(positive, +1) + max(0, loss(unlabelled, -1) - prior * loss(positive, -1)): the second part
estimates the risk on clean texts and can't be negative; where a step would drive it below zero, the step
is taken back along its gradient. The class prior comes from the labels of the fit rows.

Features of a text are its distinct words and their beginnings of 3, 5 and 7 letters, hashed into slots, each
weighted by a damped rate. A slot counts by how surely it is more or less frequent among the confirmed texts than
among the unlabelled (the log odds over their deviation, less KEEP deviations; slots nearer than that don't count), so a
few confirmed texts are enough. A linear scorer with a bias gives the probability. Confirmed texts that hold nothing
toxic pull all scores down; so the scores are moved, by at most the odds of FLOOR, until the share of unlabelled texts
that score a half or more is the prior.

Contract: null and empty texts have no features and get the score of the bias; with no positive label every
score is the prior; equal texts get equal scores; nothing but the text enters a score.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kinetrace.llm import codes as C
from kinetrace.llm.memory import releasing
from kinetrace.llm.sampling import drawable, remainder, stratified

SLOTS = 1 << 18
PREFIXES = (3, 5, 7)
#: Bounds of the fit: confirmed toxic texts, unlabelled texts.
POSITIVES, UNLABELLED = 1500, 4500
#: Deviations that a slot's odds must differ by; the least score that may become a half.
KEEP, FLOOR = 2.0, 0.25
RUN_CHARS = 500_000


@dataclass
class Scorer:
    weights: np.ndarray
    bias: float


def term_counts(texts: list[str | None]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(document, slot, count) by group of texts; a document that spans groups comes in several."""
    for docs, pieces in C.grouped(texts):
        w = C.Words(docs, pieces)
        if not len(w):
            continue
        size = w.ends - w.starts
        parts = [w.hashes()] + [C.span_hashes(w.codes, w.starts, w.starts + np.minimum(size, n)) ^ np.uint64(n) for n in PREFIXES]
        keep = [np.ones(len(w), bool)] + [size >= n for n in PREFIXES]
        slot = np.concatenate([p[k] for p, k in zip(parts, keep, strict=True)]) >> np.uint64(46)
        doc = np.concatenate([w.doc[k] for k in keep])
        key, count = np.unique(doc.astype(np.uint64) << np.uint64(18) | slot, return_counts=True)
        yield (key >> np.uint64(18)).astype(np.int64), (key & np.uint64(SLOTS - 1)).astype(np.int64), count


def _merged(texts: list[str | None]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """`term_counts` by whole documents: what the last document of a group has waits for the next group."""
    wait: tuple | None = None
    for part in term_counts(texts):
        if wait is not None:
            if part[0][0] == wait[0][0]:
                mine = np.searchsorted(part[0], wait[0][0], "right")
                slot, back = np.unique(np.concatenate((wait[1], part[1][:mine])), return_inverse=True)
                count = np.bincount(back, np.concatenate((wait[2], part[2][:mine]))).astype(np.int64)
                wait, part = (np.full(len(slot), wait[0][0]), slot, count), tuple(x[mine:] for x in part)
                if not len(part[0]):
                    continue
            yield wait
        cut = np.searchsorted(part[0], part[0][-1])
        if cut:
            yield tuple(x[:cut] for x in part)
        wait = tuple(x[cut:] for x in part)
    if wait is not None:
        yield wait


def vectors(texts: list[str | None], kept: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(document, slot, value) of all texts, in the order of documents and slots; only slots that `kept` marks, if given."""
    parts, total = [], np.zeros(len(texts))
    for doc, slot, count in _merged(texts):
        total += np.bincount(doc, count, len(texts))
        keep = slice(None) if kept is None else kept[slot]
        parts.append(tuple(x[keep].astype(np.int32) for x in (doc, slot, count)))
    if not parts:
        none = np.zeros(0, np.int32)
        return none, none, np.zeros(0)
    doc, slot, count = (np.concatenate(x) for x in zip(*parts, strict=True))
    del parts
    return doc, slot, (1 + np.log(count)) / np.sqrt(1 + np.log1p(total))[doc]


def document_counts(texts: list[str]) -> np.ndarray:
    """Number of texts that each slot is in."""
    found = np.zeros(SLOTS)
    for _, slot, _ in _merged(texts):
        found += np.bincount(slot, minlength=SLOTS)
    return found


def associations(positive: list[str], unlabelled: list[str], least: int) -> np.ndarray:
    """How surely each slot tells confirmed texts from unlabelled ones, 0 to 1."""
    p, u, n, m = document_counts(positive), document_counts(unlabelled), len(positive), len(unlabelled)
    odds = np.log((p + 0.5) / (n - p + 0.5)) - np.log((u + 0.5) / (m - u + 0.5))
    z = np.abs(odds) / np.sqrt(1 / (p + 0.5) + 1 / (u + 0.5))
    sure = np.where((z > KEEP) & (p + u >= least), z - KEEP + 0.5, 0)
    return sure / max(sure.max(), 1e-9)


def risk(score: np.ndarray, is_p: np.ndarray, prior: float) -> tuple[float, np.ndarray]:
    """The non-negative risk (its clean part, clipped at 0, and the positive part) and the direction of descent: its gradient by score,
    or, where the clean part is negative, that of the clean part reversed."""
    prob, (p, u) = 1 / (1 + np.exp(-np.clip(score, -30, 30))), (is_p.sum(), (~is_p).sum())
    negative, positive = np.logaddexp(0, score), np.logaddexp(0, -score)  # losses of the labels -1 and +1
    clean = negative[~is_p].mean() - prior * negative[is_p].mean()
    g = np.where(is_p, -prior * prob / p, prob / u)
    value = prior * positive[is_p].mean() + max(0.0, clean)
    return value, g + np.where(is_p, prior * (prob - 1) / p, 0) if clean >= 0 else -g


def scores(model: Scorer, texts: list[str | None]) -> np.ndarray:
    """Score of each text; whole texts are scored in runs of about `RUN_CHARS` characters, so memory doesn't follow the batch."""
    out, run, size = [np.zeros(0)], [], 0
    for i, text in enumerate(texts):
        run.append(text)
        size += len(text or "")
        if size >= RUN_CHARS or i == len(texts) - 1:
            doc, slot, value = vectors(run)
            out.append(1 / (1 + np.exp(-np.clip(np.bincount(doc, model.weights[slot] * value, len(run)) + model.bias, -30, 30))))
            run, size = [], 0
    return np.concatenate(out)


def fit(positive: list[str], unlabelled: list[str], prior: float, epochs: int = 120, rate: float = 0.2, decay: float = 2e-5, least: int = 3, parts: int = 3, seed: int = 3) -> Scorer:
    """Adam on the non-negative risk with the logistic loss, in batches of both kinds of text."""
    model = Scorer(np.zeros(SLOTS), float(np.log(max(prior, 1e-6) / max(1 - prior, 1e-6))))
    if not positive or not unlabelled:
        return model
    sure, n = associations(positive, unlabelled, least), len(positive)
    used = np.flatnonzero(sure)
    doc, slot, value = vectors([*positive, *unlabelled], sure > 0)
    value = value * sure[slot]
    number = np.zeros(SLOTS, np.int32)
    number[used] = np.arange(len(used))
    column = number[slot]
    del slot
    border = np.searchsorted(doc, np.arange(n + len(unlabelled) + 1))
    rng = np.random.default_rng(seed)
    w, b = np.zeros(len(used)), model.bias
    m, v, mb, vb, turn = np.zeros(len(used)), np.zeros(len(used)), 0.0, 0.0, 0
    batches = max(1, min(parts, n // 64, len(unlabelled) // 64))
    for _ in range(epochs):
        order_p, order_u = rng.permutation(n), n + rng.permutation(len(unlabelled))
        for p, u in zip(np.array_split(order_p, batches), np.array_split(order_u, batches), strict=True):
            rows = np.concatenate((p, u))
            size = border[rows + 1] - border[rows]
            at = np.repeat(border[rows] - (np.cumsum(size) - size), size) + np.arange(size.sum())
            row = np.repeat(np.arange(len(rows)), size)
            score = np.bincount(row, w[column[at]] * value[at], len(rows)) + b
            _, g = risk(score, np.arange(len(rows)) < len(p), prior)
            gw, gb = np.bincount(column[at], g[row] * value[at], len(used)) + decay * w, g.sum()
            turn += 1
            m += 0.1 * (gw - m)
            v += 0.001 * (gw * gw - v)
            mb, vb = mb + 0.1 * (gb - mb), vb + 0.001 * (gb * gb - vb)
            fix1, fix2 = 1 - 0.9**turn, 1 - 0.999**turn
            pace = rate * (1 - (turn - 1) / (epochs * batches))
            w -= pace * (m / fix1) / (np.sqrt(v / fix2) + 1e-8)
            b -= pace * (mb / fix1) / (np.sqrt(vb / fix2) + 1e-8)
    model.weights[used] = w * sure[used]
    free = doc >= n
    score = np.bincount(doc[free] - n, w[column[free]] * value[free], len(unlabelled)) + b
    cut = float(np.quantile(score, 1 - min(max(prior, 0.0), 1.0)))
    lowest = float(np.log(FLOOR / (1 - FLOOR)))
    model.bias = float(b - min(max(cut, lowest), 0.0))
    return model


def train(docs: DataFrame, labels: DataFrame, modulus: int | None = 5, held_out: int = 0, positives: int = POSITIVES, unlabelled: int = UNLABELLED) -> Scorer:
    """Fit on bounded samples of confirmed toxic documents and of documents taken as unlabelled, whole texts; neither has held-out rows."""
    marks = labels.select("doc_id", F.col("toxic").cast("int").alias("_toxic")).where("_toxic is not null").groupBy("doc_id").agg(F.max("_toxic").alias("_toxic"))
    rows = docs.select("doc_id", F.col("text").cast("string").alias("_text")).where(F.col("_text").isNotNull() & drawable("_text"))
    if modulus:
        marks, rows = marks.where(remainder("doc_id", modulus) != held_out), rows.where(remainder("doc_id", modulus) != held_out)
    share = marks.agg(F.avg("_toxic")).first()[0] or 0.0
    chosen = stratified(marks.where("_toxic = 1"), "doc_id", "_toxic", positives).select("doc_id")
    ordered = lambda frame: frame.select("doc_id", F.col("_text").alias("text")).toArrow().sort_by([("doc_id", "ascending"), ("text", "ascending")])["text"].to_pylist()
    confirmed = ordered(rows.join(F.broadcast(chosen), "doc_id", "left_semi"))
    free = ordered(stratified(rows.withColumn("_all", F.lit(1)), "doc_id", "_all", unlabelled))
    return fit(confirmed, free, float(share))


def score_rows(docs: DataFrame, model: Scorer) -> DataFrame:
    """doc_id and score of every row."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 2000):
                part = batch.slice(at, 2000)
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(scores(shared.value, part.column("text").to_pylist()))], ["doc_id", "score"])

    kept = docs.select("doc_id", F.col("text").cast("string").alias("text"))
    return kept.mapInArrow(run, f"doc_id {kept.schema['doc_id'].dataType.simpleString()}, score double")


def accepted(docs: DataFrame, model: Scorer, most: float = 0.5, text: str = "text") -> DataFrame:
    """The rows of `docs` that score below `most`; their columns don't change."""
    shared, schema, at = docs.sparkSession.sparkContext.broadcast(model), docs.schema, docs.columns.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch.filter(pa.array(scores(shared.value, batch.column(at).to_pylist()) < most, pa.bool_()))

    return docs.mapInArrow(releasing(run), schema)


def predictions(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted of every document, learned from the labels that aren't held out."""
    scored = score_rows(docs, train(docs, labels))
    return scored.select("doc_id", (remainder("doc_id", 5) == 0).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
