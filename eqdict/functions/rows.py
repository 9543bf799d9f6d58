"""Coefficient rows of equations, in numpy and as columns with the same bits.

Binary rows over m <= 64 variables are one long; wider ones are several longs, made word by word. Sparse rows are t distinct
places. `kind` is dense, sparse, logsparse (an odd number of places near the logarithm of m) or local (all within a window).
"""

from __future__ import annotations

from math import ceil, log

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from eqdict.functions.hashing import long, seed_of, xxhash64_np

ROW, PLACE, SPLIT, POSITION = (seed_of(x) for x in ("row", "place", "split", "position"))
KINDS = ("dense", "sparse", "logsparse", "local")


def odd_log(m: int) -> int:
    """Non-zeros of a log-sparse row of m variables: odd, at least 3 where m allows, near ln m."""
    t = max(3, ceil(log(m))) if m > 1 else 1
    t += t % 2 == 0
    return t if t <= m else m - (m % 2 == 0)


def mask_np(m: np.ndarray) -> np.ndarray:
    """The lowest m bits, 0 <= m <= 64."""
    m = np.asarray(m, np.uint64)
    return np.where(m == 0, np.uint64(0), np.uint64(0xFFFFFFFFFFFFFFFF) >> np.minimum(np.uint64(64) - m, np.uint64(63)))


def mask_col(m: Column) -> Column:
    """The same as a column: JVM shifts wrap modulo 64, so 0 is a case of its own."""
    return F.when(m == 0, long(0)).otherwise(_shru(long(-1), 64 - m))


def _shru(x: Column, n: Column) -> Column:
    return F.call_function("shiftrightunsigned", x, n.cast("int"))


def _shl(x: Column, n: Column) -> Column:
    return F.call_function("shiftleft", x, n.cast("int"))


def places_np(seed: np.ndarray, high: np.ndarray, low: np.ndarray, m: np.ndarray, t: int, replace: bool = False) -> np.ndarray:
    """t places of 0..m-1 for each row, distinct and in order unless drawn with replacement. Needs t <= m."""
    n = len(high)
    out = np.zeros((n, t), np.int64)
    for j in range(t):
        h = xxhash64_np(PLACE, seed, np.full(n, j, np.int64), high, low)
        p = (h >> np.uint64(1)).astype(np.int64) % (m if replace else m - j)
        if not replace:
            for i in range(j):  # step over the places taken so far, which are in order
                p += out[:, i] <= p
        out[:, j] = p
        if not replace:
            out[:, : j + 1].sort(axis=1)
    return out


def places_col(seed: Column, high: Column, low: Column, m: Column, t: int | Column, replace: bool = False) -> Column:
    def step(acc: Column, j: Column) -> Column:
        h = _shru(F.xxhash64(long(PLACE), seed.cast("long"), j.cast("long"), high, low), F.lit(1))
        p = F.pmod(h, m.cast("long") if replace else m.cast("long") - j)
        if replace:
            return F.array_append(acc, p)
        p = F.aggregate(acc, p, lambda x, q: x + F.when(q <= x, long(1)).otherwise(long(0)))
        return F.array_sort(F.array_append(acc, p))

    last = F.lit(t - 1) if isinstance(t, int) else t - 1
    return F.aggregate(F.sequence(F.lit(0), last.cast("int")), F.array().cast("array<bigint>"), step)


def masks_np(seed, high: np.ndarray, low: np.ndarray, m: np.ndarray, kind: str = "dense", t: int | None = None, window: int = 16) -> np.ndarray:
    """Rows of at most 64 variables as uint64; seed and m may differ from row to row."""
    n = len(high)
    seed, m = np.broadcast_to(np.asarray(seed, np.int64), n), np.broadcast_to(np.asarray(m, np.int64), n)
    if kind == "dense":
        return xxhash64_np(ROW, np.ascontiguousarray(seed), high, low) & mask_np(m)
    if kind == "local":
        bits = xxhash64_np(ROW, np.ascontiguousarray(seed), high, low) & mask_np(np.minimum(m, window))
        start = (xxhash64_np(PLACE, np.ascontiguousarray(seed), high, low) >> np.uint64(1)).astype(np.int64) % np.maximum(m - window + 1, 1)
        return bits << start.astype(np.uint64)
    out = np.zeros(n, np.uint64)
    for size in np.unique(m):
        own = m == size
        count = (odd_log(int(size)) if kind == "logsparse" or t is None else min(t, int(size))) if size else 0
        if count:
            p = places_np(seed[own], high[own], low[own], m[own], count)
            out[own] = np.bitwise_or.reduce(np.uint64(1) << p.astype(np.uint64), axis=1)
    return out


def mask_row(seed: Column, high: Column, low: Column, m: Column, kind: str = "dense", t: int | None = None, window: int = 16) -> Column:
    """The same as a column."""
    m, seed = m.cast("long"), seed.cast("long")
    if kind == "dense":
        return F.xxhash64(long(ROW), seed, high, low).bitwiseAND(mask_col(m))
    if kind == "local":
        return _shl(*local_row(seed, high, low, m, window))
    if kind == "logsparse" or t is None:
        count = F.element_at(F.array(*(F.lit(odd_log(x) if x else 0) for x in range(65))), m.cast("int") + 1)
    else:
        count = F.least(F.lit(t), m.cast("int"))
    bits = F.aggregate(places_col(seed, high, low, m, count), long(0), lambda s, p: s.bitwiseOR(_shl(long(1), p)))
    return F.when(m == 0, long(0)).otherwise(bits)


def local_row(seed: Column, high: Column, low: Column, m: Column, window: int) -> tuple[Column, Column]:
    """(bits within the window, the window's first variable) of a local row."""
    m, seed = m.cast("long"), seed.cast("long")
    bits = F.xxhash64(long(ROW), seed, high, low).bitwiseAND(mask_col(F.least(m, long(window))))
    return bits, F.pmod(_shru(F.xxhash64(long(PLACE), seed, high, low), F.lit(1)), F.greatest(m - window + 1, long(1)))


def window_word(start: Column, words: Column, k: int) -> Column:
    """64 bits from a variable on, from the one or two words that hold them."""
    first = start * k
    word, off = (F.floor(first / 64) + 1).cast("int"), F.pmod(first, F.lit(64)).cast("int")
    low = _shru(F.element_at(words, word), off)
    rest = _shl(F.coalesce(F.try_element_at(words, word + 1), long(0)), 64 - off)
    return F.when(off == 0, low).otherwise(low.bitwiseOR(rest))


def window_value(bits: Column, held: Column, window: int, k: int) -> Column:
    """The sum of the k-bit variables that a local row names, of those in `held`."""
    value = long(0)
    for i in range(window):
        value = value.bitwiseXOR(F.getbit(bits, F.lit(i)).cast("long") * F.shiftrightunsigned(held, i * k).bitwiseAND(long((1 << k) - 1)))
    return value


def words_np(seed: int, high: np.ndarray, low: np.ndarray, m: int) -> np.ndarray:
    """Dense binary rows of any width as uint64 words [row, word]."""
    w = max(1, -(-m // 64))
    out = np.stack([xxhash64_np(ROW, seed, i, high, low) for i in range(w)], axis=1) if len(high) else np.zeros((0, w), np.uint64)
    out[:, -1] &= mask_np(np.array(m - 64 * (w - 1)))
    return out


def word_row(seed: Column, i: Column, high: Column, low: Column, m: Column) -> Column:
    """Word i of such a row."""
    return F.xxhash64(long(ROW), seed.cast("long"), i.cast("long"), high, low).bitwiseAND(mask_col(F.least(m.cast("long") - 64 * i.cast("long"), long(64))))


def coefs_np(seed: int, high: np.ndarray, low: np.ndarray, m: int, k: int) -> np.ndarray:
    """Rows over GF(2^k) [row, variable]."""
    return np.stack([(xxhash64_np(ROW, seed, i, high, low) & np.uint64((1 << k) - 1)).astype(np.int64) for i in range(m)], axis=1) if m and len(high) else np.zeros((len(high), m), np.int64)


def coefs_col(seed: Column, high: Column, low: Column, m: Column, k: int) -> Column:
    one = lambda i: F.xxhash64(long(ROW), seed.cast("long"), i.cast("long"), high, low).bitwiseAND(long((1 << k) - 1))
    return F.when(m > 0, F.transform(F.sequence(F.lit(0), m.cast("int") - 1), one)).otherwise(F.array().cast("array<bigint>"))


def parity_value(row: Column, planes: Column, k: int) -> Column:
    """Bit j of the answer is the parity of row & plane j."""
    value = long(0)
    for j in range(k):
        bit = (F.bit_count(row.bitwiseAND(F.element_at(planes, j + 1))) % 2).cast("long")
        value = value.bitwiseOR(F.shiftleft(bit, j))
    return value


