"""Language identification by a linear-chain conditional random field over words.

A word is a run of letters. Its features are its letters, its letter trigrams with the word's edges,
its affixes of three letters, itself (all hashed into one table of weights), and its membership in each
language's lexicon. Transition weights between neighbouring words are learned with them from sequences
that are spliced out of spans of labelled documents, so changes of language occur. The forward-backward
algorithm gives each word's posterior; a document's score of a language is the mean over its words.

The recursions are exact for sequences of any length: rows of `ROW` words are reduced to transfer
matrices, the matrices are chained by document, and all rows are then run at once.

Contract: null texts and texts without a letter get `und` and score 0; with no labelled rows at all every
text gets `und`; ties go to the first language in order; equal texts get equal results.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kinetrace.llm import codes as C
from kinetrace.llm.memory import released, releasing
from kinetrace.llm.sampling import drawable, remainder, stratified, unit

SLOTS, ROW, UNKNOWN = 1 << 16, 48, "und"
#: Bounds of the fit: labelled documents of a language and characters of each.
SAMPLE_DOCS, SAMPLE_TOTAL = 250, 1_200_000


@dataclass
class Model:
    labels: list[str]
    weights: np.ndarray  # SLOTS x labels
    lexicon: np.ndarray  # sorted word hashes
    members: np.ndarray  # lexicon x labels
    lexical: np.ndarray  # labels x labels
    transition: np.ndarray  # labels x labels


def _slots(h: np.ndarray, salt: int) -> np.ndarray:
    h = (h.astype(np.uint64) + np.uint64(salt)) * np.uint64(0x9E3779B97F4A7C15)
    return (h >> np.uint64(48)).astype(np.int64)


def features(w: C.Words) -> tuple[np.ndarray, np.ndarray]:
    """(by letter: its slots, 2 a letter; by word: prefix, suffix and whole word)."""
    s = w.codes.astype(np.uint64)
    at, step = w.at, np.uint64(1_000_003)
    one = s[at]
    three = (s[at - 1] * step + one) * step + s[at + 1]
    letters = np.stack([_slots(one, 1), _slots(three, 2)], 1)
    a, b, size = w.starts, w.ends, w.ends - w.starts
    second, third = np.where(size > 1, s[np.minimum(a + 1, len(s) - 1)], 0), np.where(size > 2, s[np.minimum(a + 2, len(s) - 1)], 0)
    z2, z3 = np.where(size > 1, s[b - 2], 0), np.where(size > 2, s[np.maximum(b - 3, 0)], 0)
    prefix, suffix = (s[a] * step + second) * step + third, (z3 * step + z2) * step + s[b - 1]
    return letters, np.stack([_slots(prefix, 3), _slots(suffix, 4), _slots(w.hashes(), 5)], 1)


def emissions(model: Model, w: C.Words, found: tuple[np.ndarray, np.ndarray] | None = None) -> np.ndarray:
    """Words x labels, unnormalised log scores. found: the features, where they are known."""
    letters, words = found or features(w)
    by_letter = model.weights[letters[:, 0]] + model.weights[letters[:, 1]]
    out = np.add.reduceat(by_letter, w.first, axis=0) if len(w) else np.zeros((0, len(model.labels)), np.float32)
    for k in range(words.shape[1]):
        out = out + model.weights[words[:, k]]
    if len(model.lexicon):
        h = w.hashes()
        at = np.minimum(np.searchsorted(model.lexicon, h), len(model.lexicon) - 1)
        hit = model.lexicon[at] == h
        out[hit] += model.members[at[hit]] @ model.lexical
    return out


def posteriors(scores: np.ndarray, sizes: np.ndarray, transition: np.ndarray) -> np.ndarray:
    """Words x labels, exact marginals of chains of `sizes` words that lie one after another."""
    sizes = np.asarray(sizes, np.int64)
    n, k = scores.shape
    if not n:
        return np.zeros((0, k))
    step = np.exp(transition - transition.max())
    emit = np.exp(scores - scores.max(1, keepdims=True)).astype(float) + 1e-12
    rows = -(-sizes // ROW)
    first_row, first_word = np.cumsum(rows) - rows, np.cumsum(sizes) - sizes
    total = int(rows.sum())
    place = np.repeat(first_row * ROW - first_word, sizes) + np.arange(n)
    grid, used = np.ones((total * ROW, k)), np.zeros(total * ROW, bool)
    grid[place], used[place] = emit, True
    grid, used = grid.reshape(total, ROW, k), used.reshape(total, ROW)
    head = np.zeros(total, bool)
    head[first_row[rows > 0]] = True

    normal = lambda x: x / x.sum(-1, keepdims=True)
    enter, leave = np.ones((total, k)), np.ones((total, k))
    deepest = int(rows.max())
    if deepest > 1:
        order = np.argsort(-rows, kind="stable")
        active = np.searchsorted(-rows[order], -np.arange(deepest), "left")  # documents with more than r rows
        inner = np.repeat(rows > 1, rows)
        index = np.full(total, -1)
        index[inner] = np.arange(inner.sum())
        product = np.tile(np.eye(k), (int(inner.sum()), 1, 1))
        g, u, h = grid[inner], used[inner], head[inner]
        for t in range(ROW):
            moved = (product.reshape(-1, k) @ step).reshape(product.shape)
            if t == 0:
                moved = np.where(h[:, None, None], product, moved)
            moved = moved * g[:, t, None, :]
            moved /= moved.sum((1, 2), keepdims=True)
            product = np.where(u[:, t, None, None], moved, product)
        for r in range(deepest - 1):
            docs = order[: active[r + 1]]
            here = first_row[docs] + r
            enter[here + 1] = normal(np.einsum("ij,ijk->ik", enter[here], product[index[here]]))
        for r in range(deepest - 1, 0, -1):
            docs = order[: active[r]]
            here = first_row[docs] + r
            leave[here - 1] = normal(np.einsum("ijk,ik->ij", product[index[here]], leave[here]))
    forward = np.empty((ROW, total, k))
    a = enter
    for t in range(ROW):
        moved = a @ step
        if t == 0:
            moved = np.where(head[:, None], a, moved)
        a = np.where(used[:, t, None], normal(moved * grid[:, t]), a)
        forward[t] = a
    out = np.empty((total, ROW, k))
    b = leave
    for t in range(ROW - 1, -1, -1):
        out[:, t] = normal(forward[t] * b)
        if t:
            b = np.where(used[:, t, None], normal((b * grid[:, t]) @ step.T), b)
    return out.reshape(-1, k)[place]


def fit(texts: list[str], langs: list[str], rounds: int = 25, seed: int = 7, length: int = 64) -> Model:
    """Maximum likelihood with weight decay by Adam over sequences of about `length` words spliced from spans."""
    labels = sorted(set(langs))
    k, rng = len(labels), np.random.default_rng(seed)
    w = C.Words(list(range(len(texts))), texts)
    gold_of_doc = np.array([labels.index(x) for x in langs], np.int64)
    model = Model(labels, np.zeros((SLOTS, k), np.float32), np.zeros(0, np.uint64), np.zeros((0, k), np.float32), np.zeros((k, k), np.float32), np.zeros((k, k)))
    if not len(w):
        return model
    gold, h = gold_of_doc[w.doc], w.hashes()
    words, back, count = np.unique(h, return_inverse=True, return_counts=True)
    by_label = np.stack([np.bincount(back, gold == j, len(words)) for j in range(k)], 1)
    strong = (count >= 5) & (by_label.max(1) >= 0.9 * count)
    model.lexicon, model.members = words[strong], (by_label[strong] >= 0.9 * count[strong][:, None]).astype(np.float32)
    # spans of 4 to 40 words in random order make the sequences
    cuts = [0]
    while cuts[-1] < len(w):
        cuts.append(cuts[-1] + int(rng.integers(4, 41)))
    cuts[-1] = len(w)
    edges = np.unique(np.concatenate((cuts, np.flatnonzero(np.diff(w.doc)) + 1)))
    spans = np.stack([edges[:-1], edges[1:]], 1)[rng.permutation(len(edges) - 1)]
    size = spans[:, 1] - spans[:, 0]
    order = np.repeat(spans[:, 0] - (np.cumsum(size) - size), size) + np.arange(size.sum())
    chain = np.diff(np.append(np.arange(0, len(order), length), len(order)))
    target = gold[order]
    ends = np.cumsum(chain)
    inside = np.ones(len(order), bool)
    inside[ends - 1] = False
    pair = np.flatnonzero(inside)
    letters, whole = features(w)
    owner = np.repeat(np.arange(len(w)), w.ends - w.starts)
    at = np.minimum(np.searchsorted(model.lexicon, h), max(len(model.lexicon) - 1, 0))
    hit = np.flatnonzero(model.lexicon[at] == h) if len(model.lexicon) else np.zeros(0, np.int64)
    params = [model.weights, model.lexical, model.transition]
    moments = [(np.zeros_like(p, float), np.zeros_like(p, float)) for p in params]
    for turn in range(1, rounds + 1):
        score = emissions(model, w, (letters, whole))[order]
        # marginals of words and of adjacent words from the two neighbours' messages
        step = np.exp(model.transition - model.transition.max())
        emit = np.exp(score - score.max(1, keepdims=True))
        left = _messages(emit, chain, step, False)
        right = _messages(emit, chain, step, True)
        post = left * right
        post /= post.sum(1, keepdims=True)
        joint = left[pair][:, :, None] * step[None] * (emit[pair + 1] * right[pair + 1])[:, None, :]
        joint /= joint.sum((1, 2), keepdims=True)
        seen = np.zeros((k, k))
        np.add.at(seen, (target[pair], target[pair + 1]), 1)
        gap = -post
        gap[np.arange(len(order)), target] += 1
        error = np.empty_like(gap)
        error[order] = gap
        grads = []
        g = np.stack([sum(np.bincount(letters[:, c], error[owner, j], SLOTS) for c in (0, 1)) + sum(np.bincount(whole[:, c], error[:, j], SLOTS) for c in range(3)) for j in range(k)], 1)
        grads.append(g / len(w) - 1e-7 * model.weights)
        grads.append(model.members[at[hit]].T @ error[hit] / len(w) if len(hit) else np.zeros((k, k)))
        grads.append((seen - joint.sum(0)) / len(w))
        for p, g, (m, v) in zip(params, grads, moments, strict=True):
            m += 0.1 * (g - m)
            v += 0.02 * (g * g - v)
            p += (0.1 * (m / (1 - 0.9**turn)) / (np.sqrt(v / (1 - 0.98**turn)) + 1e-8)).astype(p.dtype)
        del score, emit, left, right, post, joint, gap, error, grads, g  # the driver holds those of one round at a time
    released()
    return model


def _messages(emit: np.ndarray, chain: np.ndarray, step: np.ndarray, backward: bool) -> np.ndarray:
    """Normalised forward (with the word's own emission) or backward messages of short chains."""
    first = np.cumsum(chain) - chain
    out = np.ones_like(emit, float)
    longest = int(chain.max())
    for t in range(longest):
        live = chain > t
        if backward:
            here = (first + chain - 1 - t)[live]
            m = np.ones((len(here), emit.shape[1])) if t == 0 else (out[here + 1] * emit[here + 1]) @ step.T
        else:
            here = (first + t)[live]
            m = emit[here] if t == 0 else (out[here - 1] @ step) * emit[here]
        out[here] = m / m.sum(1, keepdims=True)
    return out


def label_documents(model: Model, texts: list[str | None]) -> tuple[list[str], np.ndarray]:
    """Language and score of each text."""
    k = len(model.labels)
    if not k:
        return [UNKNOWN] * len(texts), np.zeros(len(texts))
    sums, counts = np.zeros((len(texts), k)), np.zeros(len(texts))
    pending: list[np.ndarray] = []
    owner = -1

    def settle(scores: np.ndarray, docs: np.ndarray) -> None:
        at = np.flatnonzero(np.concatenate(([True], docs[1:] != docs[:-1])))
        post = posteriors(scores, np.diff(np.append(at, len(docs))), model.transition)
        sums[docs[at]] += np.add.reduceat(post, at, axis=0)
        counts[docs[at]] += np.diff(np.append(at, len(docs)))

    groups = C.grouped(texts)
    for docs, pieces in groups:
        w = C.Words(docs, pieces)
        scores, of = emissions(model, w), w.doc
        if pending and docs[0] != owner:
            whole = np.concatenate(pending)
            settle(whole, np.full(len(whole), owner))
            pending = []
        if len(pieces) == 1 and len(pieces[0]) > C.GROUP_CHARS // 2:  # perhaps a piece of a longer document: only scores are kept
            owner = docs[0]
            pending.append(scores)
        elif pending and docs[0] == owner:
            mine = of == owner
            whole = np.concatenate([*pending, scores[mine]])
            if len(whole):
                settle(whole, np.full(len(whole), owner))
            pending = []
            if (~mine).any():
                settle(scores[~mine], of[~mine])
        elif len(w):
            settle(scores, of)
    if pending:
        whole = np.concatenate(pending)
        if len(whole):
            settle(whole, np.full(len(whole), owner))
    mean = sums / np.maximum(counts, 1)[:, None]
    best = mean.argmax(1)
    return [model.labels[j] if n else UNKNOWN for j, n in zip(best.tolist(), counts.tolist(), strict=True)], np.where(counts > 0, np.minimum(mean.max(1), 1.0), 0.0)


def train(docs: DataFrame, modulus: int | None = 3, held_out: int = 1, size: int = SAMPLE_DOCS, total: int = SAMPLE_TOTAL) -> Model:
    """Fit on at most about `size` whole labelled documents of each language, as many as `total` characters hold, never on held-out rows."""
    rows = docs.select("doc_id", F.col("text").cast("string").alias("text"), "lang").where("text is not null and lang is not null")
    if modulus:
        rows = rows.where(remainder("doc_id", modulus) != held_out)
    found = stratified(rows.where(drawable("text")), "doc_id", "lang", size).select("text", "lang", "doc_id", unit("doc_id").alias("u"))
    found = found.toArrow().sort_by([("u", "ascending"), ("doc_id", "ascending"), ("text", "ascending")])
    room: dict[str, int] = dict.fromkeys(found["lang"].unique().to_pylist(), total // max(1, len(found["lang"].unique())))
    texts, langs = [], []
    for text, lang in zip(found["text"].to_pylist(), found["lang"].to_pylist(), strict=True):
        if len(text) <= room[lang]:
            room[lang] -= len(text)
            texts.append(text)
            langs.append(lang)
    return fit(texts, langs)


def identify(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, lang_pred, score for every row of `docs`."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            langs, scores = label_documents(shared.value, batch.column("text").to_pylist())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(langs, pa.string()), pa.array(scores)], ["doc_id", "lang_pred", "score"])

    kept = docs.select("doc_id", F.col("text").cast("string").alias("text"))
    return kept.mapInArrow(run, f"doc_id {kept.schema['doc_id'].dataType.simpleString()}, lang_pred string, score double")


def accepted(docs: DataFrame, model: Model, least: float = 0.4, text: str = "text", into: str | None = None) -> DataFrame:
    """The rows of `docs` whose language is known with a score of at least `least`; of their columns only `into` changes, if given: it gets the language."""
    shared, schema = docs.sparkSession.sparkContext.broadcast(model), docs.schema
    at, to = docs.columns.index(text), docs.columns.index(into) if into else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            langs, scores = label_documents(shared.value, batch.column(at).to_pylist())
            stays = pa.array([x != UNKNOWN and s >= least for x, s in zip(langs, scores.tolist(), strict=True)], pa.bool_())
            if to is not None:
                batch = batch.set_column(to, batch.schema.field(to), pa.array(langs, batch.schema.field(to).type))
            yield batch.filter(stays)

    return docs.mapInArrow(releasing(run), schema)


def predictions(docs: DataFrame) -> DataFrame:
    """doc_id, held_out, lang_pred, score of every document, learned from the rows that aren't held out."""
    return identify(docs, train(docs)).select("doc_id", (remainder("doc_id", 3) == 1).alias("held_out"), "lang_pred", "score")
