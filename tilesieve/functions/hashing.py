"""Grams to bit positions. The ``md5`` family can be replayed in any engine; ``xxhash64`` is the fast one."""

from __future__ import annotations

import hashlib
from collections.abc import Iterable

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from tilesieve.functions.sizing import BUCKET_BITS, FilterSpec

SALT = 0x7A11
FAMILIES = ("md5", "xxhash64")


def lanes(gram: Column, spec: FilterSpec) -> tuple[Column, Column]:
    """Two hashes of a gram, not negative. ``spec.salt`` keys them."""
    if spec.hash == "md5":
        digest = F.md5(F.concat(F.lit(spec.salt), gram) if spec.salt else gram)
        return tuple(F.conv(F.substring(digest, a, 15), 16, 10).cast("bigint") for a in (1, 17))
    if spec.hash == "xxhash64":
        return tuple(F.shiftrightunsigned(F.xxhash64(gram, F.lit(f"{spec.salt}{x}")), 1) for x in (0, SALT))
    raise ValueError(f"hash must be one of {FAMILIES}")


def positions_of(h1: Column, h2: Column, spec: FilterSpec) -> Column:
    """The k bits of two hashes, by double hashing over all bits (classic) or inside one bucket (blocked)."""
    steps = F.sequence(F.lit(0), F.lit(spec.k - 1)).cast("array<bigint>")
    if spec.layout == "blocked":
        base = (h1 % spec.buckets) * BUCKET_BITS
        start, odd = h2 % BUCKET_BITS, (F.call_function("div", h1, F.lit(spec.buckets)) % BUCKET_BITS).bitwiseOR(F.lit(1))
        return F.transform(steps, lambda i: base + (start + i * odd) % BUCKET_BITS)
    m = F.lit(spec.m_bits)
    jump = h2 if spec.hash == "md5" else h2.bitwiseOR(F.lit(1))
    return F.transform(steps, lambda i: (h1 % m + i * (jump % m)) % m)


def bit_positions(gram: Column, spec: FilterSpec) -> Column:
    """The k bits of a gram."""
    return positions_of(*lanes(gram, spec), spec)


def local_lanes(grams: Iterable[bytes], spec: FilterSpec) -> tuple[np.ndarray, np.ndarray]:
    """The same two hashes of UTF-8 grams, in a worker."""
    if spec.hash == "md5":
        salt, md5 = spec.salt.encode(), hashlib.md5
        raw = b"".join([md5(g).digest() for g in grams]) if not salt else b"".join([md5(salt + g).digest() for g in grams])
        both = (np.frombuffer(raw, ">u8") >> np.uint64(4)).astype(np.int64).reshape(-1, 2)
        return both[:, 0], both[:, 1]
    if spec.hash == "xxhash64":
        from xxhash import xxh64_intdigest

        first = [xxh64_intdigest(g, 42) for g in grams]
        salts = [f"{spec.salt}{x}".encode() for x in (0, SALT)]
        a, b = (np.array([xxh64_intdigest(x, h) >> 1 for h in first], np.int64) for x in salts)
        return a, b
    raise ValueError(f"hash must be one of {FAMILIES}")
