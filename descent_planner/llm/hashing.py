"""Hashes of many runs of symbols at once, by prefix sums of a polynomial modulo 2^64."""

from __future__ import annotations

from functools import lru_cache

import numpy as np

from .shared import on_other_work

U = np.uint64


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser of 64-bit words: multiply, shift, xor."""
    x = x.astype(U, copy=True)
    x ^= x >> U(30)
    x *= U(0xBF58476D1CE4E5B9)
    x ^= x >> U(27)
    x *= U(0x94D049BB133111EB)
    x ^= x >> U(31)
    return x


@lru_cache(maxsize=8)
def _symbol_table(seed: int) -> np.ndarray:
    return mix(np.arange(1 << 16, dtype=U) + U((seed * 0x9E3779B97F4A7C15 + 1) % (1 << 64)))


#: The powers made so far of each seed's base and its inverse, as many as the longest input needed up to this many.
MOST_POWERS = 1 << 21
_made: dict[int, tuple[np.ndarray, np.ndarray]] = {}
on_other_work(_made.clear)


def _powers(seed: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers 0 to n of an odd base and of its inverse."""
    held = _made.get(seed)
    if held is None or len(held[0]) <= n:
        base = (0xD6E8FEB86659FD93 + 2 * seed) % (1 << 64) | 1
        size = max(1 << 16, n + n // 4 + 1)
        held = []
        for b in (base, pow(base, -1, 1 << 64)):
            p = np.full(size, b, dtype=U)
            p[0] = 1
            held.append(np.multiply.accumulate(p, out=p))
        if size <= MOST_POWERS:
            _made[seed] = tuple(held)
    return held[0], held[1]


def run_hashes(symbols: np.ndarray, starts: np.ndarray, ends: np.ndarray, seed: int = 1) -> np.ndarray:
    """A 64-bit hash of symbols[starts[i]:ends[i]] for each i; equal runs, equal hashes wherever they stand."""
    n = len(symbols)
    power, inverse = _powers(seed, n)
    table = _symbol_table(seed)
    if symbols.dtype == np.uint8:
        value = table[symbols]
    else:
        value = table[symbols & 0xFFFF]
        high = symbols >> 16
        if high.any():
            value = value + high.astype(U) * U(0x9E3779B97F4A7C15)
    total = np.empty(n + 1, dtype=U)
    total[0] = 0
    value *= power[:n]
    np.cumsum(value, out=total[1:])
    h = (total[ends] - total[starts]) * inverse[starts]
    return mix(h + (ends - starts).astype(U) * U(0xA24BAED4963EE407))
