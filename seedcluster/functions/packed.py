"""Ascending lists of 64-bit numbers as few bytes: differences in the least width that holds them, byte planes compressed."""

from __future__ import annotations

import zlib

import numpy as np


def pack_counts(x: np.ndarray) -> bytes:
    """Numbers from 0 on, in any order."""
    x = np.asarray(x, np.uint64)
    top = int(x.max(initial=0))
    width = next(w for w in (1, 2, 4, 8) if top < 1 << 8 * w)
    planes = x.astype(f"<u{width}").view(np.uint8).reshape(-1, width).T
    return bytes([width]) + zlib.compress(planes.tobytes(), 1)


def unpack_counts(data: bytes) -> np.ndarray:
    width = data[0]
    planes = np.frombuffer(zlib.decompress(data[1:]), np.uint8).reshape(width, -1)
    return np.ascontiguousarray(planes.T).view(f"<u{width}").ravel().astype(np.int64 if width < 8 else np.uint64)


def pack(ids: np.ndarray) -> bytes:
    """Ids, ascending; differences wrap around as unsigned numbers, so that any two have one."""
    ids = np.asarray(ids, np.int64)
    return b"" if not len(ids) else ids[:1].astype("<i8").tobytes() + pack_counts(np.diff(ids.view(np.uint64)))


def unpack(data: bytes) -> np.ndarray:
    if not data:
        return np.zeros(0, np.int64)
    first = np.frombuffer(data[:8], "<i8").view(np.uint64)
    return np.cumsum(np.concatenate([first, unpack_counts(data[8:]).astype(np.uint64)]), dtype=np.uint64).view(np.int64)
