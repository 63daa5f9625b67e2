"""Packed sorted key lists: how blocks of documents ask hash ranges about the whole corpus, and get answers.

A block (some megabytes of documents) holds each of its keys once, sorted. Keys are 64-bit hashes, so equal slices
of the key space are equal shares of the work whatever the text is like; a slice of a block's keys travels as one
row of delta-coded bytes. A range sees the keys of all blocks and answers each block in the block's own order.
"""

from __future__ import annotations

import numpy as np
import xxhash
import zstandard

_MIX1, _MIX2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit mixer."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= _MIX1
    x ^= x >> np.uint64(27)
    x *= _MIX2
    x ^= x >> np.uint64(31)
    return x


def hash_words(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(xxhash.xxh64_intdigest, words), dtype=np.uint64, count=len(words))


def pack(numbers: np.ndarray) -> bytes:
    """Unsigned numbers as compressed byte planes."""
    planes = np.ascontiguousarray(numbers.astype("<u8", copy=False)).view(np.uint8).reshape(-1, 8)
    used = 8
    while used and not planes[:, used - 1].any():
        used -= 1
    return bytes([used]) + zstandard.ZstdCompressor(1).compress(np.ascontiguousarray(planes[:, :used].T).tobytes())


def unpack(data: bytes, n: int) -> np.ndarray:
    used = data[0]
    planes = np.zeros((n, 8), dtype=np.uint8)
    if used and n:
        planes[:, :used] = np.frombuffer(zstandard.ZstdDecompressor().decompress(data[1:]), dtype=np.uint8).reshape(used, n).T
    return planes.view("<u8").reshape(-1)


def pack_sorted(keys: np.ndarray) -> bytes:
    return pack(np.diff(keys, prepend=np.uint64(0)))


def unpack_sorted(data: bytes, n: int) -> np.ndarray:
    return np.cumsum(unpack(data, n), dtype=np.uint64)


def range_bounds(keys: np.ndarray, ranges: int) -> np.ndarray:
    """Where each of ``ranges`` equal slices of the key space begins and ends in sorted ``keys``."""
    starts = [(r << 64) // ranges for r in range(ranges)]
    return np.append(np.searchsorted(keys, np.array(starts, dtype=np.uint64)), len(keys))
