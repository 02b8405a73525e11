"""Texts as numpy arrays of code points: the vectorised ground floor of the text operators.

Every function works on bounded groups of pieces (`grouped`), so a worker's memory follows the
group size and not the length of a document. A document that is longer than a group is cut only at
a single blank between two other characters, where neither words nor BPE pre-tokens continue.
"""

from __future__ import annotations

import unicodedata
from collections.abc import Iterator
from functools import lru_cache

import numpy as np

OTHER, LETTER, NUMBER, SPACE = 0, 1, 2, 3
GROUP_CHARS = 400_000
LAST = 0x110000
# The code points with the Unicode property White_Space.
WHITE_SPACE = [*range(0x09, 0x0E), 0x20, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]


@lru_cache(None)
def classes() -> np.ndarray:
    """Class of each code point: letter, number, white space or other."""
    kinds = {"L": LETTER, "N": NUMBER}
    table = np.fromiter((kinds.get(unicodedata.category(chr(c))[0], OTHER) for c in range(LAST)), np.uint8, LAST)
    table[WHITE_SPACE] = SPACE
    return table


@lru_cache(None)
def lowered_letters() -> np.ndarray:
    """Lower-case code point of each letter, 0 for all that is no letter."""
    table = np.zeros(LAST, np.uint32)
    for c in np.flatnonzero(classes() == LETTER).tolist():
        low = chr(c).lower()
        table[c] = ord(low) if len(low) == 1 else c
    return table


@lru_cache(None)
def scrambled() -> np.ndarray:
    """A fixed random 64-bit value for each code point."""
    return np.random.default_rng(20240229).integers(1, 2**63, LAST, dtype=np.uint64) | np.uint64(1)


@lru_cache(None)
def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    base = 0x9E3779B97F4A7C17
    back = pow(base, -1, 2**64)
    up, down = np.empty(n, np.uint64), np.empty(n, np.uint64)
    up[0] = down[0] = 1
    with np.errstate(over="ignore"):
        up[1:], down[1:] = np.uint64(base), np.uint64(back)
        return np.multiply.accumulate(up), np.multiply.accumulate(down)


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    size = 1 << max(20, (n + 1).bit_length())
    return _powers(size)


def mixed(h: np.ndarray) -> np.ndarray:
    """Bits spread over the whole 64-bit word."""
    with np.errstate(over="ignore"):
        h = (h ^ (h >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)
        h = (h ^ (h >> np.uint64(29))) * np.uint64(0x94D049BB133111EB)
        return h ^ (h >> np.uint64(32))


def code_points(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)


def span_hashes(codes: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each span of code points; the same string has the same hash wherever it stands."""
    up, down = powers(len(codes))
    with np.errstate(over="ignore"):
        total = np.zeros(len(codes) + 1, np.uint64)
        np.cumsum(scrambled()[codes] * up[: len(codes)], out=total[1:])
        return mixed((total[ends] - total[starts]) * down[starts] + (ends - starts).astype(np.uint64))


def _cut(text: str, limit: int) -> Iterator[str]:
    at = 0
    while len(text) - at > limit:
        for j in (*range(at + limit, at, -1), *range(at + limit + 1, len(text) - 1)):
            if text[j] == " " and not text[j - 1].isspace() and not text[j + 1 : j + 2].isspace():
                break
        else:
            break
        yield text[at:j]
        at = j
    yield text[at:]


def grouped(texts: list[str | None], limit: int = GROUP_CHARS) -> Iterator[tuple[list[int], list[str]]]:
    """Groups of (document indices, pieces) of about `limit` characters; nulls count as empty."""
    docs, pieces, size = [], [], 0
    for i, text in enumerate(texts):
        for piece in _cut(text or "", limit):
            if pieces and size + len(piece) > limit:
                yield docs, pieces
                docs, pieces, size = [], [], 0
            docs.append(i)
            pieces.append(piece)
            size += len(piece)
    if pieces:
        yield docs, pieces


class Words:
    """The runs of letters of a group of pieces, lower-cased: arrays over letters and over words."""

    def __init__(self, docs: list[int], pieces: list[str]):
        codes = code_points("\n" + "\n".join(pieces) + "\n")
        self._hashes: np.ndarray | None = None
        self.codes = lowered_letters()[codes]
        letter = self.codes > 0
        edge = np.diff(letter.view(np.int8))
        self.starts = np.flatnonzero(edge == 1) + 1
        self.ends = np.flatnonzero(edge == -1) + 1
        ends = np.cumsum([len(p) + 1 for p in pieces]) + 1
        self.doc = np.asarray(docs, np.int64)[np.searchsorted(ends, self.starts, "right")]
        self.at = np.flatnonzero(letter)
        self.first = np.concatenate(([0], np.cumsum(self.ends - self.starts)[:-1])) if len(self.starts) else np.zeros(0, np.int64)

    def __len__(self) -> int:
        return len(self.starts)

    def hashes(self) -> np.ndarray:
        if self._hashes is None:
            self._hashes = span_hashes(self.codes, self.starts, self.ends)
        return self._hashes
