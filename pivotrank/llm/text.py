"""Words and hashes of many texts at once, as numpy arrays.

Words are the runs of bytes other than space and tab to carriage return (what ``bytes.split()``
keeps). Word hashes are 64-bit and do not depend on the machine or the process.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

U = np.uint64
_BASE = U(0x9E3779B97F4A7C13)  # 3 modulo 8: odd, and 1 - _BASE holds one factor of two only
_BASE_INV = U(pow(int(_BASE), -1, 1 << 64))
_K1, _K2, _K3 = U(0xBF58476D1CE4E5B9), U(0x94D049BB133111EB), U(0xD6E8FEB86659FD93)
_powers = [np.ones(1, U), np.ones(1, U)]


def splitmix(x: np.ndarray) -> np.ndarray:
    """A bijective mixer of 64-bit values."""
    x = x + U(0x9E3779B97F4A7C15)
    x ^= x >> U(30)
    x *= _K1
    x ^= x >> U(27)
    x *= _K2
    x ^= x >> U(31)
    return x


def pair_hash(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """A hash of ordered pairs of hashes."""
    x = a * _K3
    x += b
    x ^= x >> U(29)
    x *= _K1
    x ^= x >> U(32)
    return x


_BYTE = splitmix(np.arange(256, dtype=U) + U(77))
_BYTE_LOWER = _BYTE.copy()
_BYTE_LOWER[65:91] = _BYTE[97:123]
_SPACE = np.zeros(256, bool)
_SPACE[[32, *range(9, 14)]] = True


def _power(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_powers[0]) < n:
        size = 1 << (n - 1).bit_length()
        for k, base in enumerate((_BASE, _BASE_INV)):
            steps = np.full(size, base, U)
            steps[0] = 1
            _powers[k] = np.multiply.accumulate(steps)
    return _powers[0][:n], _powers[1][:n]


def forget() -> None:
    """Drops the tables that grow with the longest batch met."""
    _powers[:] = [np.ones(1, U), np.ones(1, U)]


@dataclass
class Words:
    """The words of several texts, one after another.

    start, end: byte places in ``data``; hash: one per word; doc: the text's number of each word;
    first: where each text's words begin (one entry more than texts); offset: each text's first byte.
    """

    data: bytes
    start: np.ndarray
    end: np.ndarray
    hash: np.ndarray
    doc: np.ndarray
    first: np.ndarray
    offset: np.ndarray


def to_bytes(texts) -> list[bytes]:
    """UTF-8 of each text; null counts as empty."""
    return [b"" if t is None else t.encode("utf-8", "surrogatepass") if isinstance(t, str) else bytes(t) for t in texts]


def words_of(texts: list[bytes], lower: bool = False, space: np.ndarray = _SPACE) -> Words:
    """Words of the texts. lower: A-Z hash as a-z. space: which bytes separate words."""
    data = b"\n".join(texts) + b"\n"
    raw = np.frombuffer(data, np.uint8)
    gap = np.concatenate(([True], space[raw]))
    change = np.flatnonzero(gap[1:] != gap[:-1])
    start, end = change[0::2], change[1::2]
    if len(end) < len(start):  # the separator added here is no space in a table of the caller's
        end = np.append(end, len(raw))
    sizes = np.fromiter(map(len, texts), np.int64, len(texts))
    offset = np.concatenate(([0], np.cumsum(sizes + 1)))
    up, down = _power(len(raw) + 1)
    total = np.zeros(len(raw) + 1, U)
    np.cumsum((_BYTE_LOWER if lower else _BYTE)[raw] * up[:-1], out=total[1:])
    hashes = splitmix((total[end] - total[start]) * down[start] + (end - start).astype(U))
    first = np.searchsorted(start, offset)
    doc = np.repeat(np.arange(len(texts)), np.diff(first))
    return Words(data, start, end, hashes, doc, first, offset)


def batches(texts: list[bytes], size: int = 2 << 20):
    """Ranges of texts of about ``size`` bytes together; a longer text comes alone."""
    begin, held = 0, 0
    for i, t in enumerate(texts):
        if held and held + len(t) > size:
            yield begin, i
            begin, held = i, 0
        held += len(t) + 1
    if begin < len(texts):
        yield begin, len(texts)


def rolling(h: np.ndarray, width: int) -> np.ndarray:
    """Hashes of ``width`` consecutive hashes, one for each place where so many follow."""
    if len(h) < width:
        return np.empty(0, U)
    level, span, at, out, n = h, 1, 0, None, len(h) - width + 1
    left = width
    while left:
        if left & 1:
            piece = level[at : at + n]
            out = piece.copy() if out is None else pair_hash(out, piece)
            at += span
        left >>= 1
        if left:
            level = pair_hash(level[:-span], level[span:])
            span *= 2
    return out if out is not None else np.empty(0, U)


def windows(words: Words, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Starts (as word numbers over all texts) of the windows that lie in one text, and their hashes."""
    h = rolling(words.hash, width)
    if not len(h):
        return np.empty(0, np.int64), h
    inside = np.flatnonzero(words.doc[: len(h)] == words.doc[width - 1 :])
    return inside, h[inside]
