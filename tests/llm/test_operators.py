"""Each operator against brute force, an exact round trip or held-out labels, on small and awkward tables."""

import hashlib
import math
import pathlib
import random
import re
import unicodedata
import zlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers
import pytest
import xxhash
from tokenizers import Tokenizer

from kinetrace.llm import codes as C
from kinetrace.llm import bpe, langid, maxscore, packing, pii, quality, simhash, toxicity, trie_join, warc
from kinetrace.llm.components import components

SF = "/root/testdata/sf0.001"
VOCABULARY = public_tokenizers.path("byte_bpe_50k.json")
DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint, fp string, score string, k1 int"
SPECIAL = "a <|endoftext|>b"
ODD = [None, "", "   ", "\n\n", "one", "a b c", SPECIAL, "x" * 5000, "word " * 30000, "It's 5 o'clock, they'll say...\t\t 漢字 🙂 ½", "été là 12²"]


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empties, a very long text, repeated rows, and columns with clashing names."""
    texts = [*ODD, "one", SPECIAL]
    rows = [(i, t, None if i % 3 else "en", None, None, "x", "y", 1) for i, t in enumerate(texts)]
    return spark.createDataFrame([*rows, rows[4], (None, "lost id", "de", "s", 1, "x", "y", 1)], DOCS).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DOCS)


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


@pytest.fixture(scope="module")
def tokenizer():
    return Tokenizer.from_file(VOCABULARY)


def ids_of(tokenizer, text):
    return tokenizer.encode(text or "", add_special_tokens=False).ids


# 1: language


def test_forward_backward_is_exact():
    rng = np.random.default_rng(0)
    sizes, k = [1, 5, 200, 48, 49, 97], 3
    scores, step = rng.normal(size=(sum(sizes), k)) * 2, rng.normal(size=(k, k))
    found, at = langid.posteriors(scores, np.array(sizes), step), 0
    for n in sizes:
        e, a, b = np.exp(scores[at : at + n]), np.zeros((n, k)), np.ones((n, k))
        a[0] = e[0] / e[0].sum()
        for t in range(1, n):
            a[t] = a[t - 1] @ np.exp(step) * e[t]
            a[t] /= a[t].sum()
        for t in range(n - 2, -1, -1):
            b[t] = np.exp(step) @ (b[t + 1] * e[t + 1])
            b[t] /= b[t].sum()
        want = a * b / (a * b).sum(1, keepdims=True)
        assert np.allclose(found[at : at + n], want, atol=1e-6)
        at += n


def test_language_held_out(spark, docs):
    rows = langid.predictions(docs).join(docs.select("doc_id", "lang"), "doc_id").collect()
    held = [r for r in rows if r.held_out]
    assert len(rows) == docs.count() and all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1) for r in rows)
    assert sum(r.lang == r.lang_pred for r in held) >= 0.95 * len(held)
    assert all(0 <= r.score <= 1 for r in rows)


def test_language_of_odd_rows(odd, empty, docs):
    model = langid.train(docs)
    rows = langid.identify(odd, model).collect()
    assert len(rows) == odd.count()
    by_id = {r.doc_id: r for r in rows}
    assert all(by_id[i].lang_pred == "und" and by_id[i].score == 0 for i in (0, 1, 2, 3))
    assert by_id[7].lang_pred in model.labels and by_id[8].lang_pred in model.labels
    assert langid.identify(empty, model).count() == 0 and langid.predictions(empty).count() == 0
    kept = langid.accepted(odd, model)
    assert kept.columns == odd.columns and not {0, 1, 2, 3} & {r.doc_id for r in kept.collect()}


def test_language_label_in_mixed_text(docs):
    model = langid.train(docs)
    rows = {r.lang: r.text for r in docs.where("length(text) > 2000").collect()}
    mixed = " ".join(rows["en"].split()[:60]) + " " + " ".join(rows["fr"].split()[:60])
    words = langid.C.Words([0], [mixed])
    post = langid.posteriors(langid.emissions(model, words), [len(words)], model.transition)
    said = [model.labels[j] for j in post.argmax(1)]
    assert said[:50].count("en") > 40 and said[-50:].count("fr") > 40


def test_long_text_in_pieces_equals_whole(docs, monkeypatch):
    model = langid.train(docs)
    texts = [r.text for r in docs.orderBy("doc_id").limit(20).collect()]
    whole = langid.label_documents(model, texts)
    monkeypatch.setattr(langid.C, "GROUP_CHARS", 500)
    monkeypatch.setattr(langid.C.grouped, "__defaults__", (500,))
    parts = langid.label_documents(model, texts)
    assert whole[0] == parts[0] and np.allclose(whole[1], parts[1], atol=1e-3)


# 2: packing


def check_packing(rows, texts, tokenizer, capacity=2048):
    by_sequence, by_doc = defaultdict(list), defaultdict(list)
    for r in rows:
        assert 1 <= r.length <= capacity and r.offset >= 0
        by_sequence[r.sequence_id].append((r.offset, r.length))
        by_doc[r.doc_id].append(r)
    for places in by_sequence.values():
        at = 0
        for offset, length in sorted(places):
            assert offset == at
            at += length
        assert at <= capacity
    for d, text in texts.items():
        ids, found = [*ids_of(tokenizer, text), 0], sorted(by_doc[d], key=lambda r: r.piece)
        assert [r.piece for r in found] == [*range(len(found))] and sum(r.length for r in found) == len(ids)
        assert all(r.length == capacity for r in found[1:])
        for r in found:
            assert r.ids_crc32 == zlib.crc32(np.array(ids[r.start : r.start + r.length], "<u4").tobytes())
    return len(by_sequence)


def test_packing(spark, docs, tokenizer):
    rows = packing.pack(docs, VOCABULARY).collect()
    texts = {r.doc_id: r.text for r in docs.collect()}
    assert {r.doc_id for r in rows} == set(texts)
    used = check_packing(rows, texts, tokenizer)
    assert used <= 1.02 * -(-sum(r.length for r in rows) // 2048) + 1


def test_packing_of_odd_rows(odd, empty, tokenizer):
    distinct = odd.where("doc_id is not null").dropDuplicates()
    check_packing(packing.pack(distinct, VOCABULARY).collect(), {r.doc_id: r.text for r in distinct.collect()}, tokenizer)
    assert packing.pack(empty, VOCABULARY).count() == 0
    assert packing.pack(odd, VOCABULARY).where("doc_id = 4").count() == 2


def test_windows_use_every_item_once():
    rng = np.random.default_rng(3)
    for capacity in (10, 64):
        sizes = rng.integers(1, capacity + 1, 400)
        histogram = dict(Counter(sizes.tolist()))
        found = packing.windows(histogram, capacity)
        used = Counter()
        for config, k in found:
            assert sum(s * n for s, n in config.items()) <= capacity and k > 0
            for s, n in config.items():
                used[s] += n * k
        assert used == histogram
        lower = max(-(-int(sizes.sum()) // capacity), int((sizes * 2 > capacity).sum()))
        assert sum(k for _, k in found) <= 1.12 * lower
        program, rest, bound = packing.configurations(histogram, capacity)
        placed = Counter(rest)
        for config, k in program:
            for s, n in config.items():
                placed[s] += n * k
        assert placed == histogram and bound <= sum(k for _, k in found) + 1e-9


def test_knapsack_is_optimal():
    sizes, prices = np.array([3, 4, 5]), np.array([2.0, 3.0, 3.9])
    chosen = packing._knapsack(sizes, prices, 11)
    best = max(a * 2 + b * 3 + c * 3.9 for a in range(4) for b in range(3) for c in range(3) if 3 * a + 4 * b + 5 * c <= 11)
    assert sizes[chosen].sum() <= 11 and abs(prices[chosen].sum() - best) < 1e-9


# 3: near duplicates


def slow_fingerprint(text):
    words = re.findall(rb"[^\x20\x09-\x0D]+", (text or "").encode().lower())
    if not words:
        return 0
    shingles = [b" ".join(words[i : i + 4]) for i in range(max(1, len(words) - 3))]
    hashes = [xxhash.xxh64_intdigest(s, seed=42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def slow_components(prints):
    """prints: (id, fingerprint) pairs; smallest reachable id of each fingerprint."""
    distinct = sorted({f for _, f in prints})
    up = {f: f for f in distinct}

    def top(f):
        while up[f] != f:
            f = up[f]
        return f

    for i, a in enumerate(distinct):
        for b in distinct[:i]:
            if (a ^ b).bit_count() <= 4:
                up[top(a)] = top(b)
    least = {}
    for d, f in prints:
        least[top(f)] = min(d, least.get(top(f), d))
    return {f: least[top(f)] for f in distinct}


def test_near_duplicates(docs):
    rows = trie_join.fingerprint_rows(docs).collect()
    texts = {r.doc_id: r.text for r in docs.collect()}
    prints = {d: slow_fingerprint(t) for d, t in texts.items()}
    least = slow_components([*prints.items()])
    assert {r.doc_id: (r.fingerprint, r.component_id) for r in rows} == {d: (f"{f:016x}", least[f]) for d, f in prints.items()}


def test_near_duplicates_of_odd_rows(odd, empty):
    rows = trie_join.fingerprint_rows(odd).collect()
    assert len(rows) == odd.count() and {r.fingerprint for r in rows if r.doc_id in (0, 1, 2, 3)} == {"0" * 16}
    assert {r.component_id for r in rows if r.doc_id in (4, 11)} == {4}
    assert trie_join.fingerprint_rows(empty).count() == 0


@pytest.mark.parametrize("hot", [50_000, 8])
def test_trie_links_over_spark(spark, monkeypatch, hot):
    monkeypatch.setattr(trie_join, "HOT", hot)
    rng = random.Random(hot)
    base = [rng.getrandbits(64) for _ in range(25)]
    prints = {b ^ sum(1 << rng.randrange(64) for _ in range(rng.randrange(6))) & (2**64 - 1) for b in base for _ in range(12)}
    nodes = [(i, f - 2**64 if f >= 2**63 else f) for i, f in enumerate(sorted(prints))]
    frame = spark.createDataFrame(nodes, "least bigint, fp bigint")
    groups = defaultdict(set)
    for r in components(trie_join.links(frame)).collect():
        groups[r.root].add(r.node % 2**64)
    least = slow_components([(i, f % 2**64) for i, f in nodes])
    want = defaultdict(set)
    for f, d in least.items():
        want[d].add(f)
    assert sorted(map(sorted, groups.values())) == sorted(sorted(g) for g in want.values() if len(g) > 1)


def test_components_of_chain_and_star(spark):
    chain, star = [(i, i + 1) for i in range(60)], [(1000, 1001 + i) for i in range(40)]
    rows = components(spark.createDataFrame([*chain, *star, (7, 7)], "a bigint, b bigint")).collect()
    roots = defaultdict(set)
    for r in rows:
        roots[r.root].add(r.node)
    assert sorted(map(sorted, roots.values())) == [[*range(61)], [*range(1000, 1041)]]
    assert components(spark.createDataFrame([], "a bigint, b bigint")).count() == 0


# 4 and 10: classifiers


def test_quality(spark, docs, odd, empty):
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    big, marks = spark.read.parquet("/root/testdata/sf0.01/documents.parquet"), spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    rows = quality.predictions(big, marks).join(marks, "doc_id").where("held_out").collect()
    assert sum(r.predicted == r.quality for r in rows) >= 0.93 * len(rows)
    space = quality.train(docs, labels)
    scored = {r.doc_id: r.score for r in quality.score_rows(odd, space).collect()}
    assert all(0 <= s <= 1 for s in scored.values()) and scored[0] == scored[1] == space.share
    assert quality.predictions(empty, labels).count() == 0
    assert {r.score for r in quality.predictions(docs, labels.limit(0)).collect()} == {0.5}


def test_neighbours_are_exact(docs):
    texts = [r.text for r in docs.orderBy("doc_id").limit(60).collect()]
    space = quality.fit(texts[:40], [i % 2 for i in range(40)], 0.5)
    vectors = quality.project(space, texts[40:])
    for v, s in zip(vectors, quality.scores(space, texts[40:]), strict=True):
        cosine = space.vectors @ v
        near = np.argsort(-cosine, kind="stable")[: quality.NEIGHBOURS]
        votes = np.exp(quality.SHARPNESS * (cosine[near] - 1)) * space.weights[near]
        assert abs((votes * space.labels[near]).sum() / votes.sum() - s) < 1e-4


def test_toxicity(spark, docs, odd, empty):
    big, marks = spark.read.parquet("/root/testdata/sf0.1/documents.parquet"), spark.read.parquet("/root/testdata/sf0.1/labels.parquet")
    rows = toxicity.predictions(big, marks).join(marks, "doc_id").where("held_out").collect()
    toxic, clean = [r.score for r in rows if r.toxic], [r.score for r in rows if not r.toxic]
    auc = np.mean([(a > b) + 0.5 * (a == b) for a in toxic for b in clean])
    assert auc > 0.9 and np.mean(np.array(clean) >= 0.5) < 0.05
    model = toxicity.fit(["idiot scum"] * 30, ["good day"] * 60 + ["idiot scum"] * 6, 0.1, least=1)
    scored = {r.doc_id: r.score for r in toxicity.score_rows(odd, model).collect()}
    assert len(scored) == len({r.doc_id for r in odd.collect()}) and scored[0] == scored[1]
    assert toxicity.scores(model, ["you idiot scum"])[0] > 0.5 > toxicity.scores(model, ["good day to all"])[0]
    assert toxicity.predictions(empty, marks).count() == 0
    kept = toxicity.accepted(odd, model)
    assert kept.columns == odd.columns


@pytest.mark.parametrize("shift", [-2.0, 3.0])
def test_risk_and_its_gradient(shift):
    """Against plain sums and differences; with high scores the clean part is positive, with low ones of unlabelled rows negative."""
    rng = np.random.default_rng(8)
    score, is_p, prior = rng.normal(size=40) + 1, np.arange(40) < 15, 0.3
    score[15:] += shift - 3
    loss = lambda s, y: math.log1p(math.exp(-y * s))

    def parts(s):
        mean = lambda mask, y: np.mean([loss(x, y) for x in s[mask]])
        return prior * mean(is_p, 1), mean(~is_p, -1) - prior * mean(is_p, -1)

    value, g = toxicity.risk(score, is_p, prior)
    first, clean = parts(score)
    assert (clean < 0) == (shift < 0) and abs(value - (first + max(0, clean))) < 1e-12
    for i in range(40):
        step = np.eye(40)[i] * 1e-6
        a, b = parts(score + step), parts(score - step)
        want = (sum(a) - sum(b)) / 2e-6 if clean >= 0 else -(a[1] - b[1]) / 2e-6
        assert abs(g[i] - want) < 1e-8


def test_associations_by_plain_counting():
    positive, free = ["vile words here", "vile again", "fine words"] * 5, ["fine words here", "some vile thing", "again fine"] * 20
    found = toxicity.associations(positive, free, 3)
    slots = lambda text: {int(s) for _, slot, _ in toxicity.term_counts([text]) for s in slot}
    want = np.zeros(toxicity.SLOTS)
    for s in set().union(*map(slots, positive + free)):
        p, u = sum(s in slots(t) for t in positive), sum(s in slots(t) for t in free)
        odds = math.log((p + 0.5) / (15 - p + 0.5)) - math.log((u + 0.5) / (60 - u + 0.5))
        z = abs(odds) / math.sqrt(1 / (p + 0.5) + 1 / (u + 0.5))
        want[s] = z - toxicity.KEEP + 0.5 if z > toxicity.KEEP and p + u >= 3 else 0
    assert np.allclose(found, want / want.max()) and (found > 0).any()


@pytest.mark.parametrize(("sf", "least"), [("0.01", 0.8), ("0.1", 0.85)])
def test_toxicity_held_out(spark, sf, least):
    """Some of the documents marked toxic hold nothing that clean ones don't; the rest is found."""
    big, marks = (spark.read.parquet(f"/root/testdata/sf{sf}/{t}.parquet") for t in ("documents", "labels"))
    rows = toxicity.predictions(big, marks).join(marks, "doc_id").where("held_out").collect()
    toxic, clean = [r.predicted for r in rows if r.toxic], [r.predicted for r in rows if not r.toxic]
    assert np.mean(toxic) >= least and np.mean(clean) <= 0.04


# 5: top-k


def test_top_k(spark):
    rng = np.random.default_rng(1)
    vectors = rng.normal(size=(400, 16)).astype("float32").tolist()
    rows = [(i, v) for i, v in enumerate(vectors)] + [(500, vectors[3]), (501, vectors[3]), (600, None), (650, [float("nan")] * 16), (700, [None] * 16), (750, [1.0] * 3)]
    frame = spark.createDataFrame(rows, "vec_id bigint, embedding array<float>")
    got = {(r.query_id, r["rank"]): (r.vec_id, r.score) for r in maxscore.sampled_queries(frame).collect()}
    whole = {i: np.floor(256 * np.array(v, "float32").astype(float)).astype(int) for i, v in rows if v and None not in v and len(v) == 16 and not np.isnan(v).any()}
    want = {}
    for q in (i for i in whole if i % 50 == 0):
        best = sorted(((-int(whole[q] @ v), i) for i, v in whole.items() if i != q))[:5]
        want |= {(q, k + 1): (i, -s) for k, (s, i) in enumerate(best)}
    assert got == want
    assert maxscore.sampled_queries(frame.limit(0)).count() == 0


@pytest.mark.parametrize("shard", [2048, 40])
def test_top_k_of_short_and_mixed_vectors(spark, monkeypatch, shard):
    monkeypatch.setattr(maxscore, "SHARD", shard)
    monkeypatch.setattr(maxscore, "BLOCK", 3)
    monkeypatch.setattr(maxscore, "PILOT", 60)
    rng = np.random.default_rng(4)
    rows = [(i, rng.normal(size=(3, 20, 9, 0)[i // 10 % 4] if i % 7 else 3).round(2).tolist()) for i in range(400)]
    found = maxscore.sampled_queries(spark.createDataFrame(rows, "vec_id bigint, embedding array<double>")).collect()
    whole = {i: np.floor(256 * np.array(v)).astype(int) for i, v in rows}
    want = set()
    for q in range(0, 400, 50):
        best = sorted(((-int(whole[q] @ v), i) for i, v in whole.items() if i != q and len(v) == len(whole[q])))[:5]
        want |= {(q, k + 1, i, -s) for k, (s, i) in enumerate(best)}
    assert {tuple(r) for r in found} == want


def test_shard_search_prunes_exactly(monkeypatch):
    monkeypatch.setattr(maxscore, "SLICE", 16)
    rng = np.random.default_rng(2)
    shard, queries = rng.integers(-300, 300, (200, 24)), rng.integers(-300, 300, (9, 24))
    shard[50:60] = shard[3]
    ids, asked = rng.permutation(200), np.arange(9)
    row, found, score = maxscore.search_shard(queries, asked, shard, ids, 4)
    for q in range(9):
        want = sorted((-int(queries[q] @ shard[i]), int(ids[i])) for i in range(200) if ids[i] != asked[q])[:4]
        assert [(-int(s), int(i)) for i, s in zip(found[row == q], score[row == q], strict=True)] == want


# 6: archives


def test_archive_round_trip(spark, tmp_path):
    mark = warc.MARK.decode()
    html = [None, "", "short", "p" * 150, "p" * 150, "p" * 99, "p" * 99, "é" * 5000, mark * 30, "x" * 999 + mark + "y", "a\r\n\r\nb" * 40, mark[:-1] * 20, "p" * 150, "WARC/1.1\r\nx", "\r\nWARC/1.1", "x\r\n\r\nWARC/1.1"]
    rows = [(i, f"http://h/{i}" if i % 2 else None, h, 7) for i, h in enumerate(html)]
    pages = spark.createDataFrame(rows, "page_id bigint, url string, html string, digest int").repartition(3)
    got = {r.page_id: tuple(r)[1:] for r in warc.round_trip(pages, chunk=1000).collect()}
    for i, h in enumerate(html):
        data = (h or "").encode()
        same = [j for j, x in enumerate(html) if (x or "") == (h or "")]
        revisit = len(data) >= 100 and same[0] != i
        assert got[i] == (len(data), hashlib.sha256(data).hexdigest(), "revisit" if revisit else "response", same[0] if revisit else None)
    assert warc.round_trip(pages.limit(0)).count() == 0
    path = f"file://{tmp_path}/a"
    warc.write_archive(warc.classified(pages), path, chunk=1000)
    table = warc.read_chunks(spark, path).collect()
    assert max(len(r.payload) for r in table) <= 1000 and sum(r.record_type == "continuation" for r in table) > 10


def test_running_digests(spark):
    data = "".join(map(chr, range(32, 127))) * 400
    pages = spark.createDataFrame([(1, None, data), (2, "u", "small")], "page_id bigint, url string, html string")
    rows = warc.archive_records(warc.classified(pages), 1000).where("value not like '%warcinfo%'").collect()
    large = sorted((x for x in rows if sum(y.record == x.record for y in rows) > 1), key=lambda x: x.chunk_number)
    assert len(large) == 38
    for k, x in enumerate(large):
        assert x.running_digest == hashlib.sha256(data[: 1000 * (k + 1)].encode()).hexdigest()


def test_archive_reads_as_the_format_has_it(spark, tmp_path):
    """A plain reader by Content-Length finds every record; revisits refer to the response's record."""
    html = ["p" * 150, "q" * 5000, "p" * 150, "p" * 150, "tiny", "tiny"]
    pages = spark.createDataFrame([(9 - i, f"http://h/{i}", h) for i, h in enumerate(html)], "page_id bigint, url string, html string").repartition(2)
    path = f"{tmp_path}/b"
    warc.write_archive(warc.classified(pages), f"file://{path}", chunk=1000)
    found = {}
    for file in sorted(pathlib.Path(path).glob("part-*")):
        data, kinds = file.read_bytes(), []
        while data:
            head, _, rest = data.partition(b"\r\n\r\n")
            version, *lines = head.decode().split("\r\n")
            fields = dict(x.split(": ", 1) for x in lines)
            n = int(fields["Content-Length"])
            assert version == "WARC/1.1" and rest[n : n + 4] == b"\r\n\r\n"
            found[fields["WARC-Record-ID"]] = fields | {"block": rest[:n]}
            kinds.append(fields["WARC-Type"])
            data = rest[n + 4 :]
        assert not kinds or kinds[0] == "warcinfo"
    revisits = [f for f in found.values() if f["WARC-Type"] == "revisit"]
    assert len(revisits) == 2 and {found[f["WARC-Refers-To"]]["Page-Id"] for f in revisits} == {"6"}
    assert sum(f["WARC-Type"] == "continuation" for f in found.values()) == 4


# 7: BPE


def test_encoder_equals_library(tokenizer):
    rng = random.Random(1)
    letters = "abstmdrevl'' '   \n\t  éß漢字½²٣_!?.🙂\x1c\x85IL<|>"
    texts = ["".join(rng.choice(letters) for _ in range(rng.randint(0, 60))) for _ in range(3000)] + ODD
    encoder = bpe.Encoder(bpe.Vocabulary(VOCABULARY))
    for text, (_, parts) in zip(texts, bpe.ids_by_document(encoder, texts), strict=True):
        ids = np.concatenate(parts).tolist() if parts else []
        assert ids == ids_of(tokenizer, text)
        assert bpe.decode_text(encoder.vocabulary, ids) == tokenizer.decode(ids, skip_special_tokens=False)
    small = [np.concatenate(p).tolist() for _, p in bpe.ids_by_document(bpe.Encoder(encoder.vocabulary), [ODD[8]])]
    assert small == [ids_of(tokenizer, ODD[8])]


def test_clashing_hashes_do_not_matter(tokenizer, monkeypatch):
    plain = C.span_hashes
    monkeypatch.setattr(C, "span_hashes", lambda *x: plain(*x) % np.uint64(7))
    texts = ["The quick brown fox doesn't jump", "over 12 lazy dogs", ""]
    encoder = bpe.Encoder(bpe.Vocabulary(VOCABULARY))
    for text, (_, parts) in zip(texts, bpe.ids_by_document(encoder, texts), strict=True):
        assert (np.concatenate(parts).tolist() if parts else []) == ids_of(tokenizer, text)


def test_long_texts_are_cut_where_tokens_end(tokenizer):
    text = "One  two\n three's 44 don't\t x  " * 200
    encoder = bpe.Encoder(bpe.Vocabulary(VOCABULARY))
    parts = [ids for _, ids in encoder.documents([text], 300)]
    assert len(parts) > 5 and np.concatenate(parts).tolist() == ids_of(tokenizer, text)


def test_bpe_rows(docs, odd, empty, tokenizer):
    texts = {r.doc_id: r.text for r in docs.collect()}
    for r in bpe.round_trip_digests(docs, VOCABULARY).collect():
        ids = ids_of(tokenizer, texts[r.doc_id])
        assert r.n_tokens == len(ids) and r.ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()
        assert r.decoded_sha256 == hashlib.sha256(texts[r.doc_id].encode()).hexdigest()
    assert bpe.round_trip_digests(odd, VOCABULARY).count() == odd.count() and bpe.round_trip_digests(empty, VOCABULARY).count() == 0
    back = bpe.decode_ids(bpe.encode(odd, VOCABULARY), VOCABULARY)
    assert back.columns == [*odd.columns, "ids", "decoded"] and back.where("decoded <> coalesce(text, '')").count() == 0


# 8: fingerprints


def test_edits(docs, odd, empty):
    for frame in (docs, odd.where("doc_id is not null").dropDuplicates(["doc_id"])):
        texts = {r.doc_id: r.text or "" for r in frame.collect()}
        order = sorted(texts, reverse=True)
        got = {r.doc_id: r for r in simhash.with_edits(frame).collect()}
        assert set(got) == set(texts)
        for a, b in zip(order, [*order[1:], order[0]], strict=True):
            changed = simhash.edited(texts[a], texts[b])
            assert got[a].n_chars == len(texts[a]) and got[a].edited_sha256 == hashlib.sha256(changed.encode()).hexdigest()
            assert got[a].edited_fingerprint == simhash.as_text(simhash.fingerprint_many([changed]))[0]
            assert 0 <= got[a].near_edited <= 1 and 0 <= got[a].near_next <= 1
            if texts[a] == changed:
                assert got[a].near_edited == 1
    assert simhash.with_edits(empty).count() == 0
    assert simhash.with_edits(odd).count() == odd.count()


def test_likeness_separates(docs):
    rows = simhash.with_edits(docs).where("n_chars > 300").collect()
    assert np.mean([r.near_edited > r.near_next + 0.2 for r in rows]) > 0.9


@pytest.mark.parametrize("hot", [50_000, 6])
def test_block_tables(spark, monkeypatch, hot):
    monkeypatch.setattr(simhash, "HOT", hot)
    monkeypatch.setattr(simhash, "RADIUS", 6)
    rng = random.Random(5)
    base = [rng.getrandbits(128) for _ in range(20)]
    prints = sorted({b ^ sum(1 << rng.randrange(128) for _ in range(rng.randrange(9))) & (2**128 - 1) for b in base for _ in range(8)})
    signed = lambda x: x - 2**64 if x >= 2**63 else x
    found = spark.createDataFrame([(i, signed(f & (2**64 - 1)), signed(f >> 64)) for i, f in enumerate(prints)], "doc_id bigint, high bigint, low bigint")
    up = [*range(len(prints))]
    while True:
        new = [min(up[j] for j in range(len(prints)) if (prints[i] ^ prints[j]).bit_count() <= simhash.RADIUS) for i in range(len(prints))]
        if new == up:
            break
        up = new
    assert {r.doc_id: r.class_id for r in simhash.near_classes(found, 6).collect()} == dict(enumerate(up))


def slow_print(text):
    """Fingerprint of one text from plain counts; hashes of words and their mixing are the module's."""
    words, lower = [], "".join(c.lower() if len(c.lower()) == 1 and unicodedata.category(c)[0] == "L" else c for c in text or "")
    words = [w for w in re.split("[" + "".join(map(chr, C.WHITE_SPACE)) + "]+", lower) if w]
    hashes = []
    for w in words:
        codes = C.code_points(w)
        hashes.append(int(C.span_hashes(codes, np.array([0]), np.array([len(codes)]))[0]))
    mix = lambda x: int(C.mixed(np.array([x & (2**64 - 1)], np.uint64))[0])
    terms = Counter(mix(a * 0x9E3779B97F4A7C15 + b) for a, b in zip(hashes, hashes[1:], strict=False)) or Counter(hashes[:1])
    bits = [mix(t) | mix(t ^ 0xA5A5A5A5A5A5A5A5) << 64 for t in terms]
    weights = [1 + math.log(n) for n in terms.values()]
    whole = sum(1 << i for i in range(128) if sum(w if b >> i & 1 else -w for w, b in zip(weights, bits, strict=True)) > 0)
    return whole & (2**64 - 1), whole >> 64


def test_votes_by_plain_counting(docs, monkeypatch):
    texts = [r.text for r in docs.where("length(text) < 3000").limit(20).collect()] + ["", None, "one", "One two", "a b a b a", "x  y\u2003z", "é É ß"]
    want = [slow_print(t) for t in texts]
    assert [tuple(x) for x in simhash.fingerprint_many(texts).tolist()] == want
    monkeypatch.setattr(C.grouped, "__defaults__", (200,))  # texts of many pieces
    assert [tuple(x) for x in simhash.fingerprint_many(texts).tolist()] == want


def test_classes_of_repeated_and_missing_ids(spark):
    rows = [(1, 5, 0), (1, 2**40, 2**50), (2, 4, 0), (None, 2**40, 2**50), (None, 7, -1)]
    found = simhash.near_classes(spark.createDataFrame(rows, "doc_id bigint, high bigint, low bigint")).collect()
    assert sorted((str(r.doc_id), str(r.class_id)) for r in found) == [("1", "1"), ("1", "1"), ("2", "1"), ("None", "1"), ("None", "None")]
    names = spark.createDataFrame([("b", 1, 1), ("a", 3, 1), ("c", -1, 99)], "doc_id string, high bigint, low bigint")
    assert {r.doc_id: r.class_id for r in simhash.near_classes(names).collect()} == {"a": "a", "b": "a", "c": "c"}


def test_classes_of_documents(docs):
    rows = simhash.edit_rows(docs).collect()
    prints = {r.doc_id: int(r.fingerprint, 16) for r in rows}
    up = {d: d for d in prints}

    def top(d):
        while up[d] != d:
            d = up[d]
        return d

    for a in prints:
        for b in prints:
            if a < b and (prints[a] ^ prints[b]).bit_count() <= simhash.RADIUS:
                x, y = sorted((top(a), top(b)))
                up[y] = x
    assert {r.doc_id: r.class_id for r in rows} == {d: top(d) for d in prints}


# 9: personal data

BASE = {
    "email": re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"), "ip": re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"),
    "card": re.compile(r"[0-9]([\x20-]?[0-9])+"), "phone": re.compile(r"\+[0-9][\x20().0-9-]+[0-9]"),
}


def slow_spans(text):
    out = []
    for kind, pattern in BASE.items():
        for m in pattern.finditer(text or ""):
            digits = [int(c) for c in re.sub("[^0-9]", "", m[0])]
            luhn = sum(d if i % 2 == 0 else d * 2 - 9 * (d > 4) for i, d in enumerate(reversed(digits)))
            if {"email": True, "ip": kind == "ip" and all(int(p) <= 255 for p in m[0].split(".")), "card": 16 <= len(digits) <= 19 and luhn % 10 == 0, "phone": 8 <= len(digits) <= 15}[kind]:
                out.append((kind, m.start(), m.end()))
    return out


def test_base_spans(spark, docs, odd, empty):
    rng = random.Random(4)
    letters = "ab1905.@%+- ()é🙂"
    made = ["".join(rng.choice(letters) for _ in range(rng.randint(0, 80))) for _ in range(1500)]
    made += ["4111 1111 1111 1111", "4111-1111-1111-1112", "x 0000255.1.2.3 y 256.1.1.1", "a@b.c%d@e.f", "+1 (234) 555-0100 +12", "1" * 3000, "a" * 100_000, "4929348385146306" * 2, "🙂a@b.co"]
    frame = spark.createDataFrame([(i, t) for i, t in enumerate(made)], "doc_id bigint, text string")
    for table in (frame, docs, odd.dropDuplicates(["doc_id"]).where("doc_id is not null").select("doc_id", "text")):
        texts = {r.doc_id: r.text for r in table.collect()}
        rows = pii.span_rows(table).collect()
        assert len(rows) == len(texts)
        for r in rows:
            want = slow_spans(texts[r.doc_id])
            base = ",".join(f"{k}:{a}:{b}" for k, a, b in want)
            assert (r.n_email, r.n_ip, r.n_card, r.n_phone) == tuple(sum(k == x for x, _, _ in want) for k in BASE)
            assert r.base_sha256 == hashlib.sha256(base.encode()).hexdigest() and r.spans.startswith(base)
    assert pii.span_rows(empty).count() == 0


def test_disclosing_terms(spark):
    secret = "meet the falconer of Tarn at bob@x.org for tea in the garden"
    texts = [secret] * 4 + [f"tea in the garden number {i} with plain words" for i in range(40)] + [f"write to person{i}@y.org for tea" for i in range(10)]
    frame = spark.createDataFrame([(i, t, i) for i, t in enumerate(texts)], "doc_id bigint, text string, n_chars bigint")
    rows = {r.doc_id: r.spans for r in pii.span_rows(frame).collect()}
    at = secret.index("falconer")
    assert f"term:{at}:{at + 8}" in rows[0] and "term" not in rows[10] and "term" not in rows[50]
    clean = {r.doc_id: r.text for r in pii.sanitised(frame).collect()}
    # every word that only stands with the address goes, generalised to its class
    assert clean[0] == "[WORD] the [WORD] [WORD] [NAME] [WORD] [EMAIL] for tea in the garden" and clean[10] == texts[10] and clean[50] == "write to [EMAIL] for tea"
    assert "falconer" not in pii.sanitised(frame, remove=True).where("doc_id = 0").first().text


def test_terms_go_wherever_they_stand(spark):
    """A name 200 characters from the address, and in a document without it, goes too; ordinary words stay."""
    filler = "plain words of every day that all of the others hold as well "
    near = f"Falconer writes from bob@x.org {filler * 4} and signs as Falconer"
    texts = [near] * 4 + [f"{filler} about Falconer alone"] + [f"{filler} and from as about alone signs writes {i}" for i in range(60)]
    frame = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id bigint, text string")
    clean = {r.doc_id: r.text for r in pii.sanitised(frame).collect()}
    assert all("Falconer" not in t and "bob" not in t for t in clean.values())
    assert clean[0].count("[NAME]") == 2 and filler * 4 in clean[0] and clean[4] == f"{filler} about [NAME] alone" and clean[30] == texts[30]


def slow_terms(texts):
    """The disclosing terms by plain counts."""
    words = lambda t: set(re.findall(r"[^\W_]+", t.lower()))
    has, exact = defaultdict(set), set()
    for i, t in enumerate(texts):
        for kind, a, b in slow_spans(t):
            v, digits = t[a:b].lower(), re.sub("[^0-9]", "", t[a:b])
            own = (kind, v if kind in ("email", "ip") else digits)
            exact.add(own)
            shared = {"email": [v.split("@")[0], v.rsplit("@", 1)[-1]], "ip": [v.rsplit(".", 1)[0]], "card": [digits[:6]], "phone": [digits[:5]]}[kind]
            for e in [own, *((kind, n, x) for n, x in enumerate(shared))]:
                has[e].add(i)
    n = len(texts)
    of = defaultdict(set)
    for i, t in enumerate(texts):
        for w in words(t):
            of[w].add(i)
    known = {e: d for e, d in has.items() if pii.SUPPORT <= len(d) < n}
    pairs = {(e, w): len(d & of[w]) for e, d in known.items() for w in of if len(d & of[w]) >= pii.SUPPORT}
    found = set()
    for (e, w), both in pairs.items():
        own = math.log(n / len(known[e]))
        share = math.log(both * n / (len(known[e]) * len(of[w]))) / own
        if share >= pii.THRESHOLD and (e in exact or (len(known[e]) <= pii.COMMON * n and both * own >= math.log(len(pairs)))):
            found.add(w)
    return found


@pytest.mark.parametrize("limit", [10**9, 0])
def test_terms_by_plain_counting(spark, monkeypatch, limit):
    monkeypatch.setattr(pii, "BROADCAST_TERMS", limit)
    monkeypatch.setattr(pii, "BROADCAST_BYTES", limit)
    rng = random.Random(9)
    people = [(f"ann{i}@mail{i % 3}.org", f"Name{i}", f"+1 (20{i % 10}) 555-01{i:02d}") for i in range(40)]
    texts = []
    for i in range(700):
        words = [f"w{rng.randrange(60)}" for _ in range(rng.randrange(3, 30))]
        if rng.random() < 0.4:
            mail, name, phone = people[rng.randrange(40)]
            words += rng.sample([mail, name, name, phone, f"x{rng.randrange(500)}"], rng.randrange(1, 6))
            rng.shuffle(words)
        texts.append(" ".join(words))
    want = slow_terms(texts)
    assert len(want) > 5
    for r in pii.span_rows(spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id bigint, text string")).collect():
        t, base = texts[r.doc_id], slow_spans(texts[r.doc_id])
        terms = [(m.start(), m.end()) for m in re.finditer(r"[^\W_]+", t) if m[0].lower() in want and all(m.end() <= a or b <= m.start() for _, a, b in base)]
        assert r.spans == ",".join(f"{k}:{a}:{b}" for k, a, b in [*base, *(("term", a, b) for a, b in terms)])


def test_sanitised_keeps_columns(odd, empty):
    out = pii.sanitised(odd)
    assert out.columns == odd.columns and out.count() == odd.count() and pii.sanitised(empty).count() == 0
    assert out.where("text is null").count() == odd.where("text is null").count()
