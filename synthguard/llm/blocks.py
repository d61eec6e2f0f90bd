"""Questions between blocks of a corpus about 64-bit keys, in packed messages.

A block (some megabytes of text) sends the distinct keys it holds, sorted and packed, to buckets of the key space; a bucket
sees each key at most once from each block, so no key is hot; the answer to a message is an array in the message's own order.
"""

from __future__ import annotations

import numpy as np

U64 = np.uint64


def packed(keys: np.ndarray) -> bytes:
    """Sorted distinct keys as byte planes of their differences, whose upper planes are mostly zero and compress away."""
    d = np.diff(keys, prepend=U64(0))
    return np.ascontiguousarray(d.view(np.uint8).reshape(-1, 8).T).tobytes()


def unpacked(raw: bytes) -> np.ndarray:
    d = np.ascontiguousarray(np.frombuffer(raw, np.uint8).reshape(8, -1).T).view(U64).ravel()
    return np.cumsum(d, dtype=U64)


def bucket_of(keys: np.ndarray, n: int) -> np.ndarray:
    """Buckets 0..n-1 cut the key space into ranges of the same width; sorted keys give sorted buckets."""
    return ((keys >> U64(32)) * U64(n) >> U64(32)).astype(np.int64)


def by_bucket(keys: np.ndarray, n: int):
    """(bucket, from, to) of every bucket that sorted keys fall into."""
    cuts = np.searchsorted(bucket_of(keys, n), np.arange(n + 1))
    for b in np.flatnonzero(np.diff(cuts)):
        yield int(b), int(cuts[b]), int(cuts[b + 1])


def packed_counts(x: np.ndarray) -> bytes:
    """Non-negative integers as byte planes, as many as the largest needs; the first byte tells how many."""
    wide = max(1, (int(x.max(initial=0)).bit_length() + 7) // 8)
    return bytes([wide]) + np.ascontiguousarray(x.astype("<i8").view(np.uint8).reshape(-1, 8)[:, :wide].T).tobytes()


def unpacked_counts(raw: bytes) -> np.ndarray:
    wide = raw[0]
    planes = np.frombuffer(raw, np.uint8, offset=1).reshape(wide, -1)
    out = np.zeros((planes.shape[1], 8), np.uint8)
    out[:, :wide] = planes.T
    return out.view("<i8").ravel()
