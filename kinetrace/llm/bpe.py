"""Byte-level BPE: exact encoding by backtracking over longest matches, decoding by an offset table.

A text is cut into pre-tokens with array operations. Every pre-token that a worker hasn't met is
encoded in time linear in its length: an Aho-Corasick automaton lists the vocabulary's matches, the
longest match at a position is tried first, and it stands only if it is compatible with the token
before it, that is, if BPE run on the two tokens' bytes would give just these two. Where no match
stands, the last token is taken back and the next shorter one is tried. The merged result of BPE is
the only sequence whose neighbours are all compatible, so the encoding is exact.

Contract: null counts as empty; an empty text has no ids; special tokens in a text get their own ids,
as the tokenizers library has it by default; repeated rows stay; texts of any length are processed
whole in pieces of bounded size. Pre-tokens are recognised by a 64-bit hash within a worker's cache.
"""

from __future__ import annotations

import hashlib
import json
from collections.abc import Callable, Iterator
from functools import lru_cache

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, LongType, StringType

from kinetrace.llm import codes as C

#: Pre-tokens and token pairs that a worker remembers; beyond it starts anew.
CACHE = 800_000
SEPARATOR = "Ѐ"


def _byte_letters() -> dict[str, int]:
    """The printable stand-ins of byte-level vocabularies: shown bytes stand for themselves, the rest follow from 256."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    hidden = [b for b in range(256) if b not in shown]
    return {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(hidden)}


class Vocabulary:
    """Tokens, merges and their split and pair tables from a tokenizers file."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model, letters = spec["model"], _byte_letters()
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.size = 1 + max([*model["vocab"].values(), *self.special.values()])
        self.tokens = [b""] * self.size
        for text, i in model["vocab"].items():
            self.tokens[i] = bytes(letters[c] for c in text) if text not in self.special else text.encode()
        for text, i in self.special.items():
            self.tokens[i] = text.encode()
        vocab = model["vocab"]
        self.pairs: dict[int, int] = {}
        self.split: dict[int, tuple[int, int]] = {}
        for m in model["merges"]:
            a, b = m.split(" ") if isinstance(m, str) else m
            whole = vocab[a + b]
            self.pairs[vocab[a] << 20 | vocab[b]] = whole
            self.split.setdefault(whole, (vocab[a], vocab[b]))
        ranked = {vocab["".join(m.split(" ") if isinstance(m, str) else m)] for m in model["merges"]}
        base = {i for i in vocab.values() if len(self.tokens[i]) == 1}
        if max(base) > min(ranked) or sorted(ranked) != [*self.split]:
            raise ValueError("ids must follow the order of the merges")
        special = set(self.special.values())
        plain = {self.tokens[i]: i for i in vocab.values() if i not in special}
        self.automaton = ahocorasick.Automaton()
        self.single, self.lengths, self.shorter = [0] * 256, [len(t) for t in self.tokens], [-1] * self.size
        for token, i in plain.items():
            if len(token) == 1:
                self.single[token[0]] = i
                continue
            self.automaton.add_word(token.decode("latin-1"), (len(token) - 1, i))
            self.shorter[i] = next(plain[token[:n]] for n in range(len(token) - 1, 0, -1) if token[:n] in plain)
        self.automaton.make_automaton()
        self.blob = np.frombuffer(b"".join(self.tokens), np.uint8)
        self.offsets = np.concatenate(([0], np.cumsum([len(t) for t in self.tokens]))).astype(np.int64)
        self.compatible_pairs: dict[int, bool] = {}

    def compatible(self, left: int, right: int) -> bool:
        """Whether BPE on the bytes of `left` + `right` ends in these two tokens: undo merges from the
        latest on and see whether an earlier one would have joined the facing parts across the border."""
        key = left << 20 | right
        known = self.compatible_pairs.get(key)
        if known is not None:
            return known
        a, b, before, stands = left, right, self.size + 1, True
        while True:
            joined = self.pairs.get(a << 20 | b)
            if joined is not None and joined < before:
                stands = False
                break
            if a > b and a in self.split or b not in self.split and a in self.split:
                before, a = a, self.split[a][1]
            elif b in self.split:
                before, b = b + 1, self.split[b][0]
            else:
                break
        if len(self.compatible_pairs) >= CACHE:
            self.compatible_pairs.clear()
        self.compatible_pairs[key] = stands
        return stands

    def encode_pretokens(self, words: list[bytes]) -> list[list[int]]:
        """Ids of each pre-token, one pass of the automaton over all of them. Of a position's matches only
        the longest is kept (it ends last); its shorter ones follow from the table of prefixes."""
        text = SEPARATOR.join(w.decode("latin-1") for w in words)
        single, longest = self.single, [0] * len(text)
        for i, b in enumerate(text):
            if b != SEPARATOR:
                longest[i] = single[ord(b)]
        for end, (back, token) in self.automaton.iter(text):
            longest[end - back] = token
        out, at = [], 0
        for w in words:
            out.append(self._walk(longest, at, at + len(w)))
            at += len(w) + 1
        return out

    def _walk(self, longest: list[int], at: int, end: int) -> list[int]:
        lengths, shorter, pairs, compatible = self.lengths, self.shorter, self.compatible_pairs, self.compatible
        ids: list[int] = []
        dead: set[int] | tuple = ()
        last, token = -1, longest[at] if at < end else 0
        while at < end:
            while token >= 0:
                to = at + lengths[token]
                if to not in dead:
                    if last < 0:
                        break
                    fits = pairs.get(last << 20 | token)
                    if fits or fits is None and compatible(last, token):
                        break
                token = shorter[token]
            if token >= 0:
                ids.append(token)
                last, at = token, to
                token = longest[at] if at < end else 0
            else:  # nothing stands here: take the last token back and go on with the next shorter one
                dead = dead or set()
                dead.add(at)
                token = ids.pop()
                at -= lengths[token]
                last, token = ids[-1] if ids else -1, shorter[token]
        return ids


def pretoken_starts(codes: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Where the pre-tokens of GPT-2's pattern begin, in pieces that begin at `first` and aren't empty."""
    kind = C.classes()[codes]
    n = len(codes)
    begin = np.zeros(n, bool)
    begin[first] = True
    run = begin.copy()
    run[1:] |= kind[1:] != kind[:-1]
    blank = codes == 32
    after_blank = np.zeros(n, bool)
    after_blank[1:] = blank[:-1]
    after_blank &= ~begin
    space = kind == C.SPACE
    flag = run & (space | ~after_blank)
    last = space.copy()  # the last white space before something else in the same piece
    last[:-1] &= ~space[1:] & ~begin[1:]
    last[-1:] = False
    flag |= last
    quotes = np.flatnonzero((codes == 39) & run & ~after_blank)
    if len(quotes):
        pad = np.concatenate((codes, np.zeros(3, codes.dtype)))
        same = np.concatenate((~begin, np.zeros(3, bool)))
        one, two = pad[quotes + 1], pad[quotes + 2]
        short = np.isin(one, [115, 116, 109, 100]) & same[quotes + 1]  # s t m d
        pair = one.astype(np.uint64) << np.uint64(32) | two.astype(np.uint64)
        wanted = np.array([ord(x[0]) << 32 | ord(x[1]) for x in ("re", "ve", "ll")], np.uint64)
        long = np.isin(pair, wanted) & same[quotes + 1] & same[quotes + 2] & ~short
        flag[quotes[short | long] + 1] = False
        for hit, step in ((short, 2), (long, 3)):
            to = quotes[hit] + step
            to = to[to < n]
            flag[to[~run[to]]] = True
    return np.flatnonzero(flag)


class Encoder:
    """Encodes groups of texts; what pre-tokens were met is kept by their hash."""

    def __init__(self, vocabulary: Vocabulary, encode: Callable[[list[bytes]], list[list[int]]] | None = None):
        self.vocabulary = vocabulary
        self.encode = encode or vocabulary.encode_pretokens
        self.forget()

    def forget(self) -> None:
        self.slots: dict[int, int] = {}
        self.pool, self.at = np.zeros(1 << 16, np.uint32), np.zeros(1 << 16, np.int64)
        self.count, self.used = 0, 0

    def _learn(self, keys: list[int], words: list[bytes]) -> None:
        ids = self.encode(words)
        sizes = np.fromiter(map(len, ids), np.int64, len(ids))
        flat = np.fromiter((i for x in ids for i in x), np.uint32, int(sizes.sum()))
        for name, need in (("pool", self.used + len(flat)), ("at", self.count + len(ids) + 1)):
            old = getattr(self, name)
            if need > len(old):
                setattr(self, name, np.concatenate((old, np.zeros(max(need, len(old)), old.dtype))))
        self.pool[self.used : self.used + len(flat)] = flat
        self.at[self.count + 1 : self.count + 1 + len(ids)] = self.used + np.cumsum(sizes)
        self.slots.update(zip(keys, range(self.count, self.count + len(ids)), strict=True))
        self.count, self.used = self.count + len(ids), self.used + len(flat)

    def pieces(self, pieces: list[str]) -> list[np.ndarray]:
        """Ids of each piece, as arrays of uint32."""
        text = "".join(pieces)
        if not text:
            return [np.zeros(0, np.uint32) for _ in pieces]
        codes = C.code_points(text)
        sizes = np.fromiter(map(len, pieces), np.int64, len(pieces))
        borders = np.concatenate(([0], np.cumsum(sizes)))
        starts = pretoken_starts(codes, borders[:-1][sizes > 0])
        ends = np.append(starts[1:], len(codes))
        keys, where, back = np.unique(C.span_hashes(codes, starts, ends), return_index=True, return_inverse=True)
        listed = keys.tolist()
        new = [i for i, k in enumerate(listed) if k not in self.slots]
        if len(new) + self.count > CACHE:
            self.forget()
            new = [*range(len(listed))]
        if new:
            a, b = starts[where[new]].tolist(), ends[where[new]].tolist()
            self._learn([listed[i] for i in new], [text[x:y].encode("utf-8", "replace") for x, y in zip(a, b, strict=True)])
        slot = np.fromiter(map(self.slots.__getitem__, listed), np.int64, len(listed))[back]
        lengths = self.at[slot + 1] - self.at[slot]
        total = np.concatenate(([0], np.cumsum(lengths)))
        ids = self.pool[np.repeat(self.at[slot] - total[:-1], lengths) + np.arange(total[-1])]
        if decode(self.vocabulary, ids) != text.encode("utf-8", "replace"):  # two pre-tokens with one hash: none is looked up
            found = self.encode([text[x:y].encode("utf-8", "replace") for x, y in zip(starts.tolist(), ends.tolist(), strict=True)])
            total = np.concatenate(([0], np.cumsum([len(x) for x in found])))
            ids = np.fromiter((i for x in found for i in x), np.uint32, int(total[-1]))
        cuts = total[np.searchsorted(starts, borders)]
        return [ids[a:b] for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True)]

    def documents(self, texts: list[str | None], limit: int = C.GROUP_CHARS) -> Iterator[tuple[int, np.ndarray, bool]]:
        """(document, ids, whether it is the document's last piece) in order."""
        for docs, pieces in C.grouped(texts, limit):
            parts, owner, specials = [], [], []
            for d, piece in zip(docs, pieces, strict=True):
                for token, i in self.vocabulary.special.items():
                    if token in piece:
                        split = piece.split(token)
                        parts += split
                        owner += [d] * len(split)
                        specials += [i] * (len(split) - 1) + [None]
                        break
                else:
                    parts.append(piece)
                    owner.append(d)
                    specials.append(None)
            for d, ids, special in zip(owner, self.pieces(parts), specials, strict=True):
                yield d, ids if special is None else np.append(ids, np.uint32(special))


def ids_by_document(encoder: Encoder, texts: list[str | None]) -> Iterator[tuple[int, list[np.ndarray]]]:
    """For each document its index and the arrays whose concatenation are its ids."""
    current, arrays = 0, []
    for d, ids in encoder.documents(texts):
        if d != current:
            yield current, arrays
            current, arrays = d, []
        arrays.append(ids)
    if texts:
        yield current, arrays


def decode(vocabulary: Vocabulary, ids: np.ndarray) -> bytes:
    """The bytes of `ids`, gathered from the table of all tokens' bytes by their offsets."""
    begin = vocabulary.offsets[ids]
    lengths = vocabulary.offsets[ids.astype(np.int64) + 1] - begin
    before = np.cumsum(lengths) - lengths
    return vocabulary.blob[np.repeat(begin - before, lengths) + np.arange(int(lengths.sum()))].tobytes()


def decode_text(vocabulary: Vocabulary, ids: np.ndarray) -> str:
    return decode(vocabulary, np.asarray(ids, np.uint32)).decode("utf-8", "replace")


@lru_cache(2)
def shared_encoder(path: str) -> Encoder:
    """One encoder for each worker and vocabulary file."""
    return Encoder(Vocabulary(path))


def encode(docs: DataFrame, path: str, text: str = "text", to: str = "ids") -> DataFrame:
    """`docs` with a column of token ids."""
    out = pa.schema([("ids", pa.list_(pa.int64()))])
    names = [c for c in docs.columns if c != to]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = shared_encoder(path)
        for batch in batches:
            ids = [np.concatenate(x).astype(np.int64) if x else [] for _, x in ids_by_document(encoder, batch.column(text).to_pylist())]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in names), pa.array(ids, out.field(0).type)], [*names, to])

    schema = docs.select(*names).schema.add(to, ArrayType(LongType()))
    return docs.mapInArrow(run, schema)


def decode_ids(encoded: DataFrame, path: str, ids: str = "ids", to: str = "decoded") -> DataFrame:
    """`encoded` with the text that its ids stand for; null ids count as none."""
    names = [c for c in encoded.columns if c != to]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary = shared_encoder(path).vocabulary
        for batch in batches:
            texts = [decode_text(vocabulary, np.asarray(x or [], np.uint32)) for x in batch.column(ids).to_pylist()]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in names), pa.array(texts, pa.string())], [*names, to])

    return encoded.mapInArrow(run, encoded.select(*names).schema.add(to, StringType()))


def round_trip_digests(docs: DataFrame, path: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256 and decoded_sha256 of every text, ids and bytes hashed as they come."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = shared_encoder(path)
        for batch in batches:
            counts, hashes, decoded = [], [], []
            for _, arrays in ids_by_document(encoder, batch.column("text").to_pylist()):
                ids = np.concatenate(arrays) if arrays else np.zeros(0, np.uint32)
                counts.append(len(ids))
                hashes.append(hashlib.sha256(ids.astype("<u4").tobytes()).hexdigest())
                decoded.append(hashlib.sha256(decode(encoder.vocabulary, ids).decode("utf-8", "replace").encode()).hexdigest())
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), pa.array(counts, pa.int64()), pa.array(hashes, pa.string()), pa.array(decoded, pa.string())],
                ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"],
            )

    kept = docs.select("doc_id", F.col("text").cast("string").alias("text"))
    key = kept.schema["doc_id"].dataType.simpleString()
    return kept.mapInArrow(run, f"doc_id {key}, n_tokens bigint, ids_sha256 string, decoded_sha256 string")
