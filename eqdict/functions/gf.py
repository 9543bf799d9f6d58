"""Arithmetic in GF(2^k), 1 <= k <= 16, by tables of logarithms."""

from __future__ import annotations

from functools import cached_property, lru_cache

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

# A primitive polynomial for each k from 1 to 16.
_POLY = [0x3, 0x7, 0xB, 0x13, 0x25, 0x43, 0x83, 0x11D, 0x211, 0x409, 0x805, 0x1053, 0x201B, 0x4443, 0x8003, 0x1100B]


class Field:
    def __init__(self, k: int):
        if not 1 <= k <= 16:
            raise ValueError("k must be from 1 to 16")
        self.k, self.q = k, 1 << k
        exp, x = np.zeros(2 * self.q, np.int64), 1
        self.log = np.zeros(self.q, np.int64)
        for i in range(self.q - 1):
            exp[i], self.log[x] = x, i
            x <<= 1
            if x & self.q:
                x ^= _POLY[k - 1]
        if x != 1:
            raise AssertionError("the polynomial is not primitive")
        exp[self.q - 1 : 2 * (self.q - 1)] = exp[: self.q - 1]
        self.exp = exp

    def mul(self, a, b):
        a, b = np.asarray(a), np.asarray(b)
        return np.where((a == 0) | (b == 0), 0, self.exp[self.log[a] + self.log[b]])

    def inv(self, a):
        a = np.asarray(a)
        if (a == 0).any():
            raise ZeroDivisionError("0 has no inverse")
        return self.exp[(self.q - 1 - self.log[a]) % (self.q - 1)]

    @cached_property
    def table(self) -> np.ndarray:
        """All products, for fields of at most 8 bits."""
        if self.k > 8:
            raise ValueError("products of up to 8 bits can be listed")
        x = np.arange(self.q)
        return self.mul(x[:, None], x[None]).astype(np.uint8)

    def dot(self, a, b, axis: int = -1):
        return np.bitwise_xor.reduce(self.mul(a, b), axis=axis)


@lru_cache(maxsize=16)
def field(k: int) -> Field:
    return Field(k)


def gf_mul(a: Column, b: Column, k: int) -> Column:
    """The product of two columns of field elements, natively."""
    f = field(k)
    exp, log = F.array(*map(F.lit, f.exp[: 2 * f.q - 1].tolist())), F.array(*map(F.lit, f.log.tolist()))
    return F.when((a == 0) | (b == 0), F.lit(0)).otherwise(F.element_at(exp, (F.element_at(log, a.cast("int") + 1) + F.element_at(log, b.cast("int") + 1) + 1).cast("int"))).cast("long")


def gf_dot(a: Column, b: Column, k: int) -> Column:
    """The dot product of two arrays of field elements, natively."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: gf_mul(x, y, k)), F.lit(0).cast("long"), lambda s, x: s.bitwiseXOR(x))
