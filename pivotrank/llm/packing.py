"""Sorted integers as small byte strings, and sets of sorted hashes."""

from __future__ import annotations

import numpy as np
import zstandard

U = np.uint64


def pack(values: np.ndarray) -> bytes:
    """Ascending unsigned integers: differences, by byte planes, compressed."""
    if not len(values):
        return b""
    steps = np.diff(values, prepend=values.dtype.type(0))
    planes = steps.view(np.uint8).reshape(-1, values.itemsize).T.tobytes()
    return zstandard.ZstdCompressor(level=1).compress(planes)


def unpack(data: bytes, dtype) -> np.ndarray:
    if not data:
        return np.empty(0, dtype)
    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(data), np.uint8)
    size = np.dtype(dtype).itemsize
    return np.cumsum(np.ascontiguousarray(planes.reshape(size, -1).T).view(dtype).ravel(), dtype=dtype)


def pack_any(values: np.ndarray) -> bytes:
    """Integers in any order, by byte planes, compressed."""
    planes = np.ascontiguousarray(values).view(np.uint8).reshape(-1, values.itemsize).T.tobytes()
    return zstandard.ZstdCompressor(level=1).compress(planes)


def unpack_any(data: bytes, dtype) -> np.ndarray:
    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(data), np.uint8)
    return np.ascontiguousarray(planes.reshape(np.dtype(dtype).itemsize, -1).T).view(dtype).ravel()


def within(values: np.ndarray, held: np.ndarray) -> np.ndarray:
    """Which values are in ``held``, which is ascending."""
    if not len(held):
        return np.zeros(len(values), bool)
    at = np.minimum(np.searchsorted(held, values), len(held) - 1)
    return held[at] == values


def twice(ordered: np.ndarray) -> np.ndarray:
    """The values that stand more than once in an ascending array."""
    again = ordered[1:][ordered[1:] == ordered[:-1]]
    return again[np.concatenate(([True], again[1:] != again[:-1]))] if len(again) else again


def at_most_two(ordered: np.ndarray) -> np.ndarray:
    """An ascending array with two copies of a value at most."""
    if len(ordered) < 3:
        return ordered
    return np.concatenate((ordered[:2], ordered[2:][ordered[2:] != ordered[:-2]]))


def bucketed(hashes: np.ndarray, buckets: int) -> np.ndarray:
    """The bucket, by the upper half of the hash, over the lower half."""
    return (((hashes >> U(32)) * U(buckets)) & U(0xFFFFFFFF00000000)) | (hashes & U(0xFFFFFFFF))


def slices(ordered: np.ndarray):
    """For each bucket that has values: bucket, and where its values lie in an ascending bucketed array."""
    upper = (ordered >> U(32)).astype(np.int64)
    ends = np.flatnonzero(np.diff(upper, prepend=-1, append=-1))
    for a, b in zip(ends[:-1], ends[1:], strict=True):
        yield int(upper[a]), slice(int(a), int(b))
