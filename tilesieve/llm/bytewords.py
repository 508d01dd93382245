"""Words of many texts at once: positions and 64-bit hashes from one pass of numpy over UTF-8 bytes."""

from __future__ import annotations

import numpy as np

from tilesieve.llm.common import ship

ship(__name__)

_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
_INVERSE = np.uint64(pow(int(_BASE), -1, 1 << 64))


def mix(h: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser."""
    h = h ^ (h >> np.uint64(30))
    h = h * np.uint64(0xBF58476D1CE4E5B9)
    h = h ^ (h >> np.uint64(27))
    h = h * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def _tables() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    value = mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(0xD1B54A32D192ED03))
    lower = np.arange(256, dtype=np.uint8)
    lower[65:91] += 32
    space = np.zeros(256, bool)
    space[[9, 10, 11, 12, 13, 32]] = True
    return value[lower], value, space


class Powers:
    """Powers of the hash base and of its inverse, grown as needed and kept between calls."""

    def __init__(self):
        self.up = self.down = np.ones(1, np.uint64)

    def __call__(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            size = max(n, 1 << 20)
            grow = lambda b: np.concatenate([np.ones(1, np.uint64), np.cumprod(np.full(size - 1, b, np.uint64), dtype=np.uint64)])
            self.up, self.down = grow(_BASE), grow(_INVERSE)
        return self.up[:n], self.down[:n]


def runs(data: np.ndarray, begins: np.ndarray, breaks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the stretches without a break; no stretch crosses from a text to the next."""
    edge = np.zeros(len(data) + 1, bool)
    edge[begins] = True
    open_ = ~breaks
    starts = np.flatnonzero(open_ & np.concatenate([[True], breaks[:-1]] if len(data) else [[]]).astype(bool) | open_ & edge[:-1])
    ends = np.flatnonzero(open_ & (np.concatenate([breaks[1:], [True]]).astype(bool) | edge[1:])) + 1 if len(data) else starts
    return starts, ends


def span_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, powers: Powers, *, fold_case: bool = True) -> np.ndarray:
    """Hash of the bytes of each span; ``fold_case`` lowers A to Z first."""
    folded, exact, _ = _tables()
    up, down = powers(len(data) + 1)
    sums = np.zeros(len(data) + 1, np.uint64)
    np.cumsum((folded if fold_case else exact)[data] * up[: len(data)], out=sums[1:])
    return mix((sums[ends] - sums[starts]) * down[starts] + (ends - starts).astype(np.uint64) * np.uint64(0xA24BAED4963EE407))


def words(data: np.ndarray, begins: np.ndarray, powers: Powers, *, fold_case: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Start, end, text number and hash of each word, for texts that begin at ``begins[:-1]``."""
    starts, ends = runs(data, begins, _tables()[2][data])
    owner = np.searchsorted(begins, starts, side="right") - 1
    return starts, ends, owner, span_hashes(data, starts, ends, powers, fold_case=fold_case)
