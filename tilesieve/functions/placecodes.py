"""Sorted places as bytes, close to their entropy: gaps, whose upper part is coded by zstd and whose lower bytes are kept."""

from __future__ import annotations

import struct

import numpy as np
import pyarrow as pa

_HEAD = "<IIB"
_MOST = 255


def coded(places: np.ndarray) -> bytes:
    """Ascending places below 2 ** 32, repeated ones once."""
    gaps = np.empty(len(places), np.uint32)
    gaps[:1] = places[:1]
    np.subtract(places[1:], places[:-1], out=gaps[1:], casting="unsafe")
    gaps[1:] -= np.uint32(1)  # repeated places wrap round
    if (again := gaps == np.uint32(0xFFFFFFFF)).any():
        gaps = gaps[~again]
    planes, upper = 0, gaps
    while planes < 3 and len(upper) and upper.mean() > _MOST:
        planes, upper = planes + 1, upper >> 8
    lower = b"".join(((gaps >> (8 * i)) & 0xFF).astype(np.uint8).tobytes() for i in range(planes))
    if len(upper) and upper.max() >= _MOST:  # each a byte of its own before the rest
        more = upper // np.uint32(_MOST)
        ends = np.arange(len(upper)) + np.cumsum(more, dtype=np.int64)
        sent = np.full(int(ends[-1]) + 1, _MOST, np.uint8)
        sent[ends] = upper - more * np.uint32(_MOST)
    else:
        sent = upper.astype(np.uint8)
    return struct.pack(_HEAD, len(gaps), len(sent), planes) + lower + pa.Codec("zstd", 1).compress(sent.tobytes(), asbytes=True)


def decoded(data: bytes | memoryview) -> np.ndarray:
    """The places again."""
    n, sent, planes = struct.unpack_from(_HEAD, data)
    view = memoryview(data)[struct.calcsize(_HEAD) :]
    read = np.frombuffer(pa.Codec("zstd").decompress(view[planes * n :], sent, asbytes=True), np.uint8)
    upto = np.cumsum(read, dtype=np.int64)
    if sent > n:
        upto = upto[read < _MOST]
    if not planes:
        upto += np.arange(n)
        return upto
    gaps = np.diff(upto, prepend=0) << (8 * planes)
    for i in range(planes):
        gaps |= np.frombuffer(view[i * n : (i + 1) * n], np.uint8).astype(np.int64) << (8 * i)
    gaps += 1
    return np.cumsum(gaps) - 1
