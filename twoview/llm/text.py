"""Columnar text kernel: whole Arrow string columns as code-point arrays, words and hashes in numpy.

Every operator that reads texts goes through here, so that each text is decoded once and no Python
loop runs over characters or words. A null text is an empty text. Texts are never cut; a chunk holds
whole texts and about CHUNK_CHARS characters, so memory follows the longest single text.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

CHUNK_CHARS = 1 << 18
_ODD = np.uint64(0x9E3779B97F4A7C15)
_BASE = np.uint64(0xD6E8FEB86659FD93)
_powers = np.ones(1, np.uint64)


def powers(n: int) -> np.ndarray:
    """The first n powers of the hash base, modulo 2**64; grown on demand."""
    global _powers
    if len(_powers) < n:
        steps = np.full(max(n, 4096, 2 * len(_powers)), _BASE, np.uint64)
        steps[0] = 1
        _powers = np.multiply.accumulate(steps)
    return _powers[:n]


def mix(h: np.ndarray) -> np.ndarray:
    """Finaliser that spreads all 64 bits; works in place on uint64."""
    h ^= h >> np.uint64(32)
    h *= np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(32)
    h *= np.uint64(0xC2B2AE3D27D4EB4F)
    h ^= h >> np.uint64(29)
    return h


@dataclass
class Chunk:
    """Texts row0..row1 of a batch: cp are their code points, off the start of each and the end."""

    row0: int
    row1: int
    cp: np.ndarray
    off: np.ndarray

    @property
    def n(self) -> int:
        return self.row1 - self.row0

    @cached_property
    def lower(self) -> np.ndarray:
        """Code points with A-Z lower-cased and nothing else changed."""
        return self.cp + ((self.cp - np.uint32(65)) < 26).astype(np.uint32) * np.uint32(32)

    @cached_property
    def solid(self) -> np.ndarray:
        """True where a code point is no white space (0x20, 0x09 to 0x0D)."""
        return (self.cp != 32) & ((self.cp - np.uint32(9)) >= 5)

    @cached_property
    def _bounds(self) -> tuple[np.ndarray, np.ndarray]:
        flags = np.zeros(len(self.cp) + 1, bool)
        flags[1:-1] = self.solid[1:] != self.solid[:-1]
        flags[self.off] = True  # a text's edge is a word's edge
        at = np.flatnonzero(flags)
        if len(at) < 2:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        inside = self.solid[at[:-1]]
        return at[:-1][inside], at[1:][inside]

    @property
    def starts(self) -> np.ndarray:
        return self._bounds[0]

    @property
    def ends(self) -> np.ndarray:
        return self._bounds[1]

    @cached_property
    def n_words(self) -> np.ndarray:
        """Words of each text."""
        return np.diff(np.searchsorted(self.starts, self.off))

    @cached_property
    def word_off(self) -> np.ndarray:
        """Index of the first word of each text, and the number of words."""
        return np.searchsorted(self.starts, self.off)

    @cached_property
    def doc(self) -> np.ndarray:
        """Text number, within the chunk, of each word."""
        return np.repeat(np.arange(self.n, dtype=np.int32), self.n_words)

    def hashes(self, lower: bool = True) -> np.ndarray:
        """A 64-bit hash of each word."""
        return span_hashes(self.lower if lower else self.cp, self.starts, self.ends, self.solid)

    def per_doc(self, flags: np.ndarray) -> np.ndarray:
        """How many True there are in each text, from one flag a code point."""
        total = np.zeros(len(flags) + 1, np.int64)
        np.cumsum(flags, out=total[1:])
        return total[self.off[1:]] - total[self.off[:-1]]

    def text(self, a: int, b: int) -> str:
        return self.cp[a:b].tobytes().decode("utf-32-le")


def span_hashes(cp: np.ndarray, starts: np.ndarray, ends: np.ndarray, inside: np.ndarray) -> np.ndarray:
    """Polynomial hashes of the ascending disjoint spans [starts, ends) of cp, mixed with their lengths.

    inside marks the code points that lie in a span.
    """
    if not len(starts):
        return np.zeros(0, np.uint64)
    lens = ends - starts
    first = int(starts[0])
    upto = np.append(starts[1:], len(cp))
    pos = np.arange(first, len(cp)) - np.repeat(starts, upto - starts)
    terms = (cp[first:].astype(np.uint64) + np.uint64(1)) * _ODD
    terms ^= terms >> np.uint64(29)
    longest = int(lens.max())
    terms *= powers(longest + 1)[np.minimum(pos, longest)]
    terms *= inside[first:]
    h = np.add.reduceat(terms, starts - first)
    h += lens.astype(np.uint64) * np.uint64(0xA24BAED4963EE407)
    return mix(h)


def column_chunks(column: pa.Array | pa.ChunkedArray, limit: int = CHUNK_CHARS) -> Iterator[Chunk]:
    """Chunks of a string column; together they hold all its rows in order."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = pc.fill_null(column.cast(pa.large_string()), "")
    if not len(column):
        return
    _, offsets, data = column.buffers()
    off = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    a = 0
    while a < len(column):
        b = int(np.searchsorted(off, off[a] + limit, "right")) - 1
        b = min(max(b, a + 1), len(column))
        part = raw[off[a] : off[b]]
        bounds = off[a : b + 1] - off[a]
        if len(part) and part.max() > 127:
            heads = np.zeros(len(part) + 1, np.int64)
            np.cumsum((part & 0xC0) != 0x80, out=heads[1:])
            bounds = heads[bounds]
            cp = np.frombuffer(part.tobytes().decode("utf-8").encode("utf-32-le"), np.uint32)
        else:
            cp = part.astype(np.uint32)
        yield Chunk(a, b, cp, bounds.astype(np.int64))
        a = b


def windows(chunk: Chunk, hashes: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all runs of size words within a text, and the index of each run's first word."""
    if len(hashes) < size:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    n = len(hashes) - size + 1
    p = powers(size)
    h = hashes[:n] * p[0]
    for k in range(1, size):
        h += hashes[k : k + n] * p[k]
    at = np.flatnonzero(chunk.doc[:n] == chunk.doc[size - 1 :])
    return mix(h[at]), at


def shingle_sets(chunk: Chunk, size: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingles of each text as (text, hash), sorted by both.

    A text with fewer words than size has its whole word sequence as its one shingle; without words, none.
    """
    words = chunk.hashes()
    h, at = windows(chunk, words, size)
    doc = chunk.doc[at]
    short = np.flatnonzero((chunk.n_words > 0) & (chunk.n_words < size))
    if len(short):
        extra = np.zeros(len(short), np.uint64)
        for k in range(size - 1):
            has = chunk.n_words[short] > k
            extra[has] += words[chunk.word_off[short[has]] + k] * powers(size)[k]
        extra = mix(extra + chunk.n_words[short].astype(np.uint64) * _ODD)
        doc, h = np.concatenate([doc, short.astype(np.int32)]), np.concatenate([h, extra])
    order = np.lexsort((h, doc))
    doc, h = doc[order], h[order]
    keep = np.ones(len(h), bool)
    keep[1:] = (h[1:] != h[:-1]) | (doc[1:] != doc[:-1])
    return doc[keep], h[keep]
