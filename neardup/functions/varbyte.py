"""Variable-byte coding of sorted id lists: seven bits a byte, gaps between ids, high bit on a number's last byte."""

from __future__ import annotations

import numpy as np


def encode(numbers: np.ndarray) -> bytes:
    """Non-negative numbers, lowest seven bits first."""
    n = np.asarray(numbers, np.uint64)
    if not len(n):
        return b""
    size = np.ones(len(n), np.int64)
    for shift in range(7, 64, 7):
        size += n >= np.uint64(1) << np.uint64(shift)
    end = np.cumsum(size)
    out = np.zeros(end[-1], np.uint8)
    rest = n.copy()
    for k in range(int(size.max())):
        at = size > k
        out[(end - size + k)[at]] = (rest[at] & np.uint64(127)).astype(np.uint8)
        rest = rest >> np.uint64(7)
    out[end - 1] |= 128
    return out.tobytes()


def decode(data: bytes) -> np.ndarray:
    """The numbers of ``encode``."""
    b = np.frombuffer(data, np.uint8)
    if not len(b):
        return np.zeros(0, np.int64)
    last = np.flatnonzero(b & 128)
    start = np.r_[0, last[:-1] + 1]
    place = np.arange(len(b)) - np.repeat(start, last - start + 1)
    return np.add.reduceat((b & 127).astype(np.uint64) << (7 * place).astype(np.uint64), start).astype(np.int64)


def encode_ids(ids: np.ndarray) -> bytes:
    """Sorted ids as gaps, the first one from zero."""
    return encode(np.diff(np.sort(np.asarray(ids, np.int64)), prepend=0))


def decode_ids(data: bytes) -> np.ndarray:
    """The sorted ids of ``encode_ids``."""
    return np.cumsum(decode(data))
