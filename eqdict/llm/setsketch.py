"""SetSketch: registers of exponentially spaced, truncated minima.

For each register, every element of a set has an exponential variate with a fixed rate; a register keeps the smallest, as the
whole power of a base it lies under, cut to a range. A union's registers are the larger ones of its parts. Two sets' registers are
equal with a probability that grows with their Jaccard similarity, so bands of registers are keys for near copies, and the numbers
of larger, smaller and equal registers have a likelihood in that similarity.

An element's variates are the first arrivals, register by register, of one Poisson process whose points fall on registers at random.
Points beyond a bound that all registers undercut almost surely need not be made: work grows with elements + registers x
log(registers), not with their product. A set with a register still empty is done again with a larger bound.
"""

from __future__ import annotations

import numpy as np

from eqdict.llm.common import mix

REGISTERS = 256  # a power of two: a byte of the hash names the register
BASE = 1.02
RATE = 20.0
LIMIT = 65534
_GOLDEN = 0x9E3779B97F4A7C15


def minima(elements: np.ndarray, owner: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The smallest variate for each set and register: elements are distinct within a set, owner numbers their sets, none is empty."""
    m, n = REGISTERS, len(sizes)
    low = np.full(n * m, np.inf)
    bound = np.minimum((np.log(m) + 6) / (RATE * sizes), 40.0)
    todo = np.ones(n, bool)
    while todo.any():
        active = np.flatnonzero(todo[owner])
        e, o = elements[active], owner[active]
        cap = bound[o]
        at, step = np.zeros(len(e)), 0
        while len(e):
            step += 1
            h = mix(e + np.uint64(step * _GOLDEN & 0xFFFFFFFFFFFFFFFF))
            at = at - np.log(((h >> np.uint64(11)).astype(np.float64) + 0.5) * 2.0**-53) / (m * RATE)
            keep = at <= cap
            e, o, at, cap, h = e[keep], o[keep], at[keep], cap[keep], h[keep]
            np.minimum.at(low, o * m + (h & np.uint64(m - 1)).astype(np.int64), at)
        todo = ~np.isfinite(low.reshape(n, m)).all(axis=1)
        bound = np.where(todo, bound * 2, bound)
    return low.reshape(n, m)


def registers(low: np.ndarray) -> np.ndarray:
    return np.clip(np.floor(1 - np.log(low) / np.log(BASE)), 0, LIMIT + 1).astype("<u2")


def sketches(sets: list[np.ndarray]) -> list[bytes | None]:
    """Registers of each set of 64-bit hashes; None for an empty one."""
    sizes = np.array([len(s) for s in sets], np.int64)
    full = np.flatnonzero(sizes)
    out: list[bytes | None] = [None] * len(sets)
    if len(full):
        regs = registers(minima(np.concatenate([sets[i] for i in full]), np.repeat(np.arange(len(full)), sizes[full]), sizes[full]))
        for k, i in enumerate(full):
            out[i] = regs[k].tobytes()
    return out


def merged(a: bytes, b: bytes) -> bytes:
    """Registers of the union."""
    return np.maximum(np.frombuffer(a, "<u2"), np.frombuffer(b, "<u2")).tobytes()


def equal_chance(jaccard: float, u: float = 0.5, base: float = BASE) -> float:
    """Chance that a register is equal; u: the first set's share of the two sizes' sum."""
    return 1 - _less(u - (1 - u) * jaccard, base) - _less((1 - u) - u * jaccard, base)


def _less(x, base: float = BASE):
    return -np.log(1 - x * (base - 1) / base) / np.log(base)


def joint_estimate(a: np.ndarray, b: np.ndarray, size_a: np.ndarray, size_b: np.ndarray, steps: int = 40) -> np.ndarray:
    """Maximum-likelihood Jaccard similarities of pairs: a[pair, register], b likewise, and their numbers of elements."""
    return fitted((a > b).sum(axis=1), (a < b).sum(axis=1), size_a, size_b, steps)


def fitted(more: np.ndarray, less: np.ndarray, size_a: np.ndarray, size_b: np.ndarray, steps: int = 40) -> np.ndarray:
    """The same from the numbers of registers that are larger and smaller in the first set."""
    same = REGISTERS - more - less
    u = size_a / (size_a + size_b)
    v = 1 - u
    lo, hi = np.zeros(len(u)), np.minimum(u / v, v / u)
    gold = (np.sqrt(5) - 1) / 2

    def fit(j):
        p, q = _less(np.maximum(u - v * j, 0)), _less(np.maximum(v - u * j, 0))
        tiny = 1e-12
        return more * np.log(np.maximum(p, tiny)) + less * np.log(np.maximum(q, tiny)) + same * np.log(np.maximum(1 - p - q, tiny))

    for _ in range(steps):  # the likelihood has one peak
        x, y = hi - gold * (hi - lo), lo + gold * (hi - lo)
        right = fit(x) < fit(y)
        lo, hi = np.where(right, x, lo), np.where(right, hi, y)
    return (lo + hi) / 2


def surely(threshold: float) -> float:
    """An estimate that similar enough pairs undercut about once in 10^6: five deviations below the threshold."""
    return threshold - 5 * np.sqrt(threshold * (1 - threshold) / REGISTERS)
