"""Vectorised work on batches of UTF-8 texts: word borders, 64-bit word hashes, byte n-grams.

A batch is one byte array holding the texts, each followed by a line feed; every step is a numpy pass over it, so the
interpreter runs once a batch and not once a word.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np

U64 = np.uint64
_GOLD, _M1, _M2 = U64(0x9E3779B97F4A7C15), U64(0xBF58476D1CE4E5B9), U64(0x94D049BB133111EB)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit integers that spreads every bit."""
    x = (x + _GOLD).astype(U64, copy=False)
    x = (x ^ (x >> U64(30))) * _M1
    x = (x ^ (x >> U64(27))) * _M2
    return x ^ (x >> U64(31))


BYTE_VALUE = mix(np.arange(256, dtype=U64) * U64(0x632BE59BD9B4E019))
LOWERED = np.arange(256, dtype=np.uint8)
LOWERED[65:91] += 32
SPACE = np.zeros(256, bool)
SPACE[[32, 9, 10, 11, 12, 13]] = True
#: For words without punctuation: every ASCII byte that is no letter or digit parts them.
NOT_ALNUM = np.ones(256, bool)
NOT_ALNUM[128:] = False
for _a, _b in ((48, 58), (65, 91), (97, 123)):
    NOT_ALNUM[_a:_b] = False

_places = np.zeros(0, U64)


def _place_values(n: int) -> np.ndarray:
    """A number for each place 0..n-1 of a span; those of places below 2**16 are kept."""
    global _places
    if n <= len(_places):
        return _places[:n]
    made = mix(np.arange(max(n, 1 << 10), dtype=U64) * _M1 + _GOLD)
    if n <= 1 << 16:
        _places = made
    return made[:n]


def span_hash(buf: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """64-bit hashes of the spans buf[start:end], which follow each other, hold a byte at least and do not overlap.

    A hash is the mixed sum of one number for each byte, made of its value and its place in the span by a function that is not
    linear. A sum of powers modulo 2**64 would give one hash to many pairs of regular texts whatever its base.
    """
    if not len(start):
        return np.zeros(0, U64)
    origin = np.zeros(len(buf), np.int64)
    origin[start] = start
    place = np.arange(len(buf))
    place -= np.maximum.accumulate(origin, out=origin)
    size = end - start
    np.minimum(place, int(size.max()) - 1, out=place)  # only bytes between spans lie further
    x = BYTE_VALUE[buf]
    x += _place_values(int(size.max()))[place]
    x ^= x >> U64(32)
    x *= _M1
    x ^= x >> U64(29)
    cuts = np.empty(2 * len(start), np.int64)
    cuts[0::2], cuts[1::2] = start, end
    if cuts[-1] == len(buf):
        x = np.append(x, U64(0))
    return mix(np.add.reduceat(x, cuts)[::2] + size.astype(U64) * _M2)


class Words:
    """Words of a batch: start, end (byte places), doc (index in the batch), and hash on demand."""

    def __init__(self, texts: list[bytes], lower: bool = True, parted_by: np.ndarray = SPACE):
        self.n = len(texts)
        raw = np.frombuffer(b"\n".join(texts) + b"\n", np.uint8)
        self.buf = LOWERED[raw] if lower else raw
        sizes = np.fromiter((len(t) + 1 for t in texts), np.int64, self.n)
        self.begin = np.concatenate(([0], np.cumsum(sizes)))
        gap = np.ones(len(raw) + 2, np.int8)
        gap[1:-1] = parted_by[raw]
        edges = np.flatnonzero(np.diff(gap))
        self.start, self.end = edges[0::2], edges[1::2]
        # first word of each document, then one past the last word
        self.first = np.searchsorted(self.start, self.begin)
        self.count = np.diff(self.first)
        self.doc = np.repeat(np.arange(self.n), self.count)

    def hashes(self) -> np.ndarray:
        return span_hash(self.buf, self.start, self.end)


def chunks(texts: Iterable[bytes], limit: int = 1 << 21) -> Iterator[tuple[int, list[bytes]]]:
    """(index of the first, texts) in runs of about limit bytes; a longer text comes alone and whole."""
    run, size, at = [], 0, 0
    for i, t in enumerate(texts):
        if run and size + len(t) > limit:
            yield at, run
            run, size, at = [], 0, i
        run.append(t)
        size += len(t) + 1
    if run:
        yield at, run


def as_bytes(column) -> list[bytes]:
    """A string column of an Arrow batch as UTF-8 bytes, null as empty."""
    return [x or b"" for x in column.cast("large_binary" if "large" in str(column.type) else "binary").to_pylist()]


def runs_unique(doc: np.ndarray, value: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct (doc, value) pairs, sorted; doc is ascending already."""
    order = np.lexsort((value, doc))
    d, v = doc[order], value[order]
    keep = np.ones(len(v), bool)
    keep[1:] = (d[1:] != d[:-1]) | (v[1:] != v[:-1])
    return d[keep], v[keep]
