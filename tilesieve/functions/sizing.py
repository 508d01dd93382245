"""Filter sizes: bits and hashes from items and a target rate, and what they cost."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

#: Bits of a stored bitmap row: 4 KiB.
BUCKET_BITS = 32_768
LAYOUTS = ("classic", "blocked")


@dataclass(frozen=True)
class FilterSpec:
    """Everything a probe must share with the build; stored with the filter and checked on use."""

    n: int = 50
    stride: int = 50
    unit: str = "char"
    norm: str = "collapse"
    hash: str = "md5"
    layout: str = "classic"
    m_bits: int = BUCKET_BITS
    k: int = 10
    n_items: int = 0
    fpp: float = 1e-3
    salt: str = ""
    #: Names what made the tokens of a token filter; words unless given as arrays.
    tokenizer: str = "words"

    @property
    def buckets(self) -> int:
        return self.m_bits // BUCKET_BITS

    @property
    def bits_per_item(self) -> float:
        return self.m_bits / max(1, self.n_items)

    def require(self, other: FilterSpec) -> None:
        """Refuse a probe or merge with another geometry or normalisation."""
        a, b = (replace(s, n_items=0, fpp=0.0) for s in (self, other))
        if a != b:
            raise ValueError(f"filters differ: {a} and {b}")


def bits_for(n_items: int, fpp: float) -> float:
    return -max(1, n_items) * math.log(fpp) / math.log(2) ** 2


def plan_filter(n_items: int, fpp: float = 1e-3, **spec) -> FilterSpec:
    """The smallest filter of whole buckets that meets ``fpp`` at ``n_items``."""
    if not 0 < fpp < 1:
        raise ValueError("fpp must lie between 0 and 1")
    m = BUCKET_BITS * max(1, math.ceil(bits_for(n_items, fpp) / BUCKET_BITS))
    k = max(1, round(bits_for(n_items, fpp) / max(1, n_items) * math.log(2)))
    return FilterSpec(m_bits=m, k=k, n_items=n_items, fpp=fpp, **spec)


def from_budget(n_bytes: int, n_items: int, **spec) -> FilterSpec:
    """The filter that fits ``n_bytes``, and the rate to expect of it."""
    m = BUCKET_BITS * max(1, n_bytes * 8 // BUCKET_BITS)
    k = max(1, round(m / max(1, n_items) * math.log(2)))
    return FilterSpec(m_bits=m, k=k, n_items=n_items, fpp=(1 - math.exp(-k * n_items / m)) ** k, **spec)


def guess_cost(vocabulary: int, n: int, stride: int) -> float:
    """Most guesses to find the next stored element after a known one: vocabulary ** (units to guess)."""
    return float(vocabulary) ** min(n, stride)


def universe_bits(alphabet: int, n: int) -> float:
    """Log2 of the number of possible grams."""
    return n * math.log2(alphabet)


def chain_chance(fpp: float, tiles: int, windows: int) -> float:
    """Expected chains of ``tiles`` chance hits among ``windows``."""
    return windows * fpp**tiles
