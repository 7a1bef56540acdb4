"""Hashes of any run of numbers in an array, from running sums: sum of x[i] * BASE**i modulo 2**64."""

from __future__ import annotations

from functools import cache

import numpy as np

_BASE = np.uint64(0x9E3779B97F4A7C15)
_BACK = np.uint64(pow(0x9E3779B97F4A7C15, -1, 2**64))
#: Powers are held for arrays of up to so many numbers, and made anew for larger ones.
HELD = 1 << 20


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijection of 64 bits, so that near numbers become unlike."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _powers(size: int) -> tuple[np.ndarray, np.ndarray]:
    return tuple(np.concatenate([np.ones(1, np.uint64), np.multiply.accumulate(np.full(size, b, np.uint64))]) for b in (_BASE, _BACK))


_held = cache(_powers)


def counted(n: np.ndarray) -> np.ndarray:
    """0 .. n - 1 for each n, one after the other."""
    return np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)


def codes_of(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), "<u4")


class Runs:
    def __init__(self, x: np.ndarray) -> None:
        self.up, self.down = _held(HELD) if len(x) <= HELD else _powers(len(x))
        self.sums = np.zeros(len(x) + 1, np.uint64)
        np.cumsum(mixed(x.astype(np.uint64) + _BASE) * self.up[: len(x)], out=self.sums[1:])

    def of(self, at: np.ndarray, size: np.ndarray | int) -> np.ndarray:
        """Hashes of x[at : at + size]; equal runs have equal ones wherever they stand."""
        return (self.sums[at + size] - self.sums[at]) * self.down[at]
