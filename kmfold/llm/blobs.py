"""Arrays packed into one compressed binary cell: few wide rows move instead of many narrow ones."""

from __future__ import annotations

import ctypes
import struct

import numpy as np
import pyarrow as pa
import zstandard


def release() -> None:
    """Give freed memory back to the system: workers live on between tasks and stages."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library: nothing to trim
        pass


def pack(*arrays: np.ndarray) -> bytes:
    """Arrays of any numeric type as one compressed cell."""
    head = [struct.pack("<B", len(arrays))]
    for a in arrays:
        code = a.dtype.str.encode()
        head.append(struct.pack("<BQ", len(code), a.size) + code)
    return zstandard.ZstdCompressor(level=1).compress(b"".join([*head, *(np.ascontiguousarray(a).tobytes() for a in arrays)]))


def unpack(cell: bytes) -> list[np.ndarray]:
    """The arrays of a packed cell (read-only views)."""
    raw = zstandard.ZstdDecompressor().decompress(cell)
    n, at, kinds = raw[0], 1, []
    for _ in range(n):
        size, count = struct.unpack_from("<BQ", raw, at)
        at += 9
        kinds.append((np.dtype(raw[at : at + size].decode()), count))
        at += size
    out = []
    for kind, count in kinds:
        out.append(np.frombuffer(raw, kind, count, at))
        at += kind.itemsize * count
    return out


def gather(cells: list[bytes]) -> list[np.ndarray]:
    """Arrays of several cells, each concatenated in the order of the cells."""
    parts = [unpack(c) for c in cells]
    return [np.concatenate(p) for p in zip(*parts)]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scramble of unsigned 64-bit values."""
    x = x ^ (x >> np.uint64(32))
    x = x * np.uint64(0xD6E8FEB86659FD93)
    x ^= x >> np.uint64(29)
    x = x * np.uint64(0xA24BAED4963EE407)
    return x ^ (x >> np.uint64(32))


def byte_values() -> np.ndarray:
    """A fixed pseudo-random 64-bit value for each byte."""
    return mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))


def tidy(f):
    """A grouped function that gives its memory back after each group (by number of arguments: one table, or two)."""
    if f.__code__.co_argcount == 1:

        def one(table):
            try:
                return f(table)
            finally:
                release()

        return one

    def two(left, right):
        try:
            return f(left, right)
        finally:
            release()

    return two
