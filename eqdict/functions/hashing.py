"""Hash functions as column expressions, with the same in numpy where kernels need them.

A key is reduced to a digest of two longs once; everything else derives from both halves. Seeds of the different uses (bucket,
cell, row, fingerprint, ...) come from separate domains, so a fingerprint is independent of the equations.
"""

from __future__ import annotations

import hashlib
from functools import reduce

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T

P31 = (1 << 31) - 1
_MASK = (1 << 64) - 1
# The multipliers of the public 64-bit xxHash, and the start value of Spark's xxhash64.
_X1, _X2, _X3, _X4, _X5 = 0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5
_SPARK_SEED = 42


def seed_of(*parts: object) -> int:
    """A signed 64-bit seed for a use; equal parts give equal seeds in every process."""
    return int.from_bytes(hashlib.blake2b(repr(parts).encode(), digest_size=8).digest(), "little", signed=True)


def long(v: int) -> Column:
    return F.lit(v).cast("long")


# --- keys to digests ------------------------------------------------------------------------------------------------------------


def canonical(c: Column, kind: T.DataType) -> Column:
    """One form for values that are equal as keys: integers of any width, -0.0 and 0.0, all NaN, decimals with their scale."""
    if isinstance(kind, (T.ByteType, T.ShortType, T.IntegerType, T.LongType)):
        return c.cast("long")
    if isinstance(kind, (T.FloatType, T.DoubleType)):
        d = c.cast("double")
        return F.when(F.isnan(d), F.lit(float("nan"))).when(d == 0.0, F.lit(0.0)).otherwise(d)
    if isinstance(kind, T.TimestampType):
        return F.unix_micros(c)
    if isinstance(kind, T.TimestampNTZType):
        return F.unix_micros(F.to_timestamp(c))
    if isinstance(kind, T.DateType):
        return F.unix_date(c).cast("long")
    if isinstance(kind, T.DecimalType):
        return F.concat_ws("e", c.cast("string"), F.lit(str(kind.scale)))
    if isinstance(kind, (T.StringType, T.BinaryType, T.BooleanType)):
        return c
    if isinstance(kind, T.ArrayType):
        return F.struct(F.size(c).cast("long").alias("n"), F.transform(c, lambda x: canonical(x, kind.elementType)).alias("items"))
    if isinstance(kind, T.StructType):
        return F.struct(*(canonical(c[f.name], f.dataType).alias(f"f{i}") for i, f in enumerate(kind.fields)))
    if isinstance(kind, T.DayTimeIntervalType):
        return F.expr("0").cast("long") + (F.unix_micros(F.timestamp_micros(F.lit(0)) + c))
    raise TypeError(f"{kind.simpleString()} cannot be a key")


def digest(keys: list[tuple[Column, T.DataType]], kind: str = "xxhash") -> tuple[Column, Column]:
    """(high, low) of a key's columns. Null if any of them is null.

    xxhash: two independent 64-bit hashes (a seed goes first, as Spark chains arguments from left to right). md5: 60 + 60 bits of
    the MD5 of one string column, which other engines can repeat. identity: an integer key itself, and 0.
    """
    some = reduce(lambda a, b: a | b, (c.isNull() for c, _ in keys))
    form = [canonical(c, t) for c, t in keys]
    if kind == "xxhash":
        high, low = (F.xxhash64(long(seed_of("digest", h)), *form) for h in ("high", "low"))
    elif kind == "md5":
        if len(keys) != 1 or not isinstance(keys[0][1], T.StringType):
            raise TypeError("md5 digests take one string column")
        high, low = (F.conv(F.substring(F.md5(form[0].cast("string")), at, 15), 16, 10).cast("long") for at in (1, 16))
    elif kind == "identity":
        if len(keys) != 1 or not isinstance(keys[0][1], (T.ByteType, T.ShortType, T.IntegerType, T.LongType)):
            raise TypeError("identity digests take one integer column")
        high, low = form[0], long(0)
    else:
        raise ValueError(kind)
    return F.when(~some, high), F.when(~some, low)


# --- pairwise independent families ----------------------------------------------------------------------------------------------


def limb_coefficients(seed: int, limbs: int = 6) -> tuple[list[int], int]:
    r = np.random.Generator(np.random.PCG64(seed & _MASK))
    return [int(x) for x in r.integers(0, P31, limbs)], int(r.integers(0, P31))


def _limbs(high, low, piece):
    return [piece(w, at, bits) for w in (high, low) for at, bits in ((0, 30), (30, 30), (60, 4))]


def _piece(w: Column, at: int, bits: int) -> Column:
    return F.shiftrightunsigned(w, at).bitwiseAND(long((1 << bits) - 1))


def _piece_np(w: np.ndarray, at: int, bits: int) -> np.ndarray:
    return w >> np.uint64(at) & np.uint64((1 << bits) - 1)


def limb_affine(high: Column, low: Column, seed: int, size: int | Column) -> Column:
    """Affine in the 30-bit pieces of a digest modulo 2^31 - 1, then modulo size: pairwise independent, no overflow, native."""
    a, b = limb_coefficients(seed)
    terms = [F.pmod(F.lit(k).cast("long") * x, long(P31)) for k, x in zip(a, _limbs(high, low, _piece), strict=True)]
    return F.pmod(F.pmod(reduce(lambda x, y: x + y, terms) + long(b), long(P31)), size if isinstance(size, Column) else long(size))


def limb_affine_sql(high: str, seed: int, size: int) -> str:
    """The same in DuckDB for an identity digest of a whole number from 0 on (the low half is 0)."""
    a, b = limb_coefficients(seed)
    terms = " + ".join(f"({k} * ((({high})::BIGINT >> {at}) & {(1 << bits) - 1})) % {P31}" for k, (at, bits) in zip(a, ((0, 30), (30, 30), (60, 4)), strict=False))
    return f"((({terms} + {b}) % {P31}) % {size})"


def limb_affine_np(high: np.ndarray, low: np.ndarray, seed: int, size: int) -> np.ndarray:
    a, b = limb_coefficients(seed)
    limbs = _limbs(high.astype(np.uint64), low.astype(np.uint64), _piece_np)
    return ((sum(np.uint64(k) * x % np.uint64(P31) for k, x in zip(a, limbs, strict=True)) + np.uint64(b)) % np.uint64(P31) % np.uint64(size)).astype(np.int64)


def affine31_parameters(seed: int) -> tuple[int, int]:
    r = np.random.Generator(np.random.PCG64(seed & _MASK))
    return int(r.integers(1, P31)), int(r.integers(0, P31))


def affine31(x: Column, seed: int, size: int) -> Column:
    """(a x + b) mod (2^31 - 1) mod size, for whole numbers under 2^31."""
    a, b = affine31_parameters(seed)
    return F.pmod(F.pmod(long(a) * x.cast("long") + long(b), long(P31)), long(size))


def affine31_sql(x: str, seed: int, size: int) -> str:
    a, b = affine31_parameters(seed)
    return f"((({a} * ({x})::BIGINT + {b}) % {P31}) % {size})"


P61 = (1 << 61) - 1


def affine61_parameters(seed: int) -> tuple[int, int]:
    r = np.random.Generator(np.random.PCG64(seed & _MASK))
    return int(r.integers(1, P61)), int(r.integers(0, P61))


def affine61_sql(x: str, seed: int, size: int) -> str:
    a, b = affine61_parameters(seed)
    return f"((({a}::HUGEINT * (({x})::HUGEINT % {P61}) + {b}) % {P61}) % {size})::BIGINT"


def affine61(x: Column, seed: int, size: int) -> Column:
    """(a x + b) mod (2^61 - 1) mod size through decimals, for whole numbers of any long: wider, and many times slower than affine31."""
    a, b = affine61_parameters(seed)
    wide = lambda v: F.lit(v).cast("decimal(20,0)")
    reduced = F.pmod(x.cast("decimal(20,0)"), wide(P61)).cast("decimal(19,0)")
    product = (reduced * F.lit(a).cast("decimal(19,0)")).cast("decimal(38,0)") + wide(b)
    return F.pmod(F.pmod(product, wide(P61)), wide(size)).cast("long")


def gf2_masks(seed: int, bits: int) -> list[tuple[int, int, int]]:
    """For each output bit a mask of each half and a constant. Without the constant the digest 0 would always give 0."""
    r = np.random.Generator(np.random.PCG64(seed & _MASK))
    signed = lambda: int(r.integers(-(1 << 63), 1 << 63, dtype=np.int64))
    return [(signed(), signed(), int(r.integers(0, 2))) for _ in range(bits)]


def gf2_affine(high: Column, low: Column, seed: int, bits: int) -> Column:
    """`bits` parities of the digest under random masks: pairwise independent without bias."""
    out = [F.shiftleft(((F.bit_count(high.bitwiseAND(long(a))) + F.bit_count(low.bitwiseAND(long(c))) + b) % 2).cast("long"), i) for i, (a, c, b) in enumerate(gf2_masks(seed, bits))]
    return reduce(lambda x, y: x.bitwiseOR(y), out)


def gf2_affine_np(high: np.ndarray, low: np.ndarray, seed: int, bits: int) -> np.ndarray:
    out = np.zeros(len(high), np.int64)
    for i, (a, c, b) in enumerate(gf2_masks(seed, bits)):
        bit = (np.bitwise_count(high.view(np.uint64) & np.uint64(a & _MASK)) + np.bitwise_count(low.view(np.uint64) & np.uint64(c & _MASK)) + b) & 1
        out |= bit.astype(np.int64) << i
    return out


def gf2_affine_sql(high: str, seed: int, bits: int) -> str:
    """The same in DuckDB for an identity digest (the low half is 0)."""
    return "(" + " | ".join(f"(((bit_count(({high})::BIGINT & ({a})::BIGINT) + {b}) % 2)::BIGINT << {i})" for i, (a, _, b) in enumerate(gf2_masks(seed, bits))) + ")"


# --- uniform hash ---------------------------------------------------------------------------------------------------------------


def _rotl(x: np.ndarray, n: int) -> np.ndarray:
    return (x << np.uint64(n)) | (x >> np.uint64(64 - n))


def _xxh64_long(x: np.ndarray, seed: np.ndarray) -> np.ndarray:
    """One 8-byte step of the public XXH64 algorithm."""
    h = seed + np.uint64((_X5 + 8) & _MASK)
    h = h ^ (_rotl(x * np.uint64(_X2), 31) * np.uint64(_X1))
    h = _rotl(h, 27) * np.uint64(_X1) + np.uint64(_X4)
    h ^= h >> np.uint64(33)
    h *= np.uint64(_X2)
    h ^= h >> np.uint64(29)
    h *= np.uint64(_X3)
    return h ^ (h >> np.uint64(32))


def xxhash64_np(*longs) -> np.ndarray:
    """What Spark's xxhash64 gives for bigint columns, as uint64. Scalars and arrays may be mixed."""
    h = np.full(1, _SPARK_SEED, np.uint64)
    for x in longs:
        x = np.array([x & _MASK], np.uint64) if isinstance(x, int) else np.asarray(x)
        h = _xxh64_long(x.view(np.uint64) if x.dtype == np.int64 else x.astype(np.uint64), h)
    return h


def spark_xxhash64(*cols: Column | int) -> Column:
    return F.xxhash64(*(long(c) if isinstance(c, int) else c for c in cols))


class TableHash:
    """Random words behind a pairwise independent index: near-uniform hashing of few keys with little randomness.

    Function number f maps a digest to R_f[index_f(digest)]. The words are themselves made from a seed, so nothing is shipped; what
    the caller needs is only the index, which takes the digest's place in all later hashing.
    """

    def __init__(self, table_len: int, n_funcs: int, seed: int):
        self.table_len, self.n_funcs, self.seed = table_len, n_funcs, seed

    def _coefficients_np(self, f: int) -> list[np.ndarray]:
        return [(xxhash64_np(seed_of("table", self.seed), f, i) >> np.uint64(1)) % np.uint64(P31) for i in range(7)]

    def index_np(self, f: int, high: np.ndarray, low: np.ndarray) -> np.ndarray:
        *a, b = self._coefficients_np(f)
        limbs = _limbs(high.astype(np.uint64), low.astype(np.uint64), _piece_np)
        return ((sum(k * x % np.uint64(P31) for k, x in zip(a, limbs, strict=True)) + b) % np.uint64(P31) % np.uint64(self.table_len)).astype(np.int64)

    def words_np(self, f: int) -> np.ndarray:
        return xxhash64_np(seed_of("words", self.seed), f, np.arange(self.table_len, dtype=np.int64))

    def index(self, f: Column, high: Column, low: Column) -> Column:
        a = [F.pmod(F.shiftrightunsigned(F.xxhash64(long(seed_of("table", self.seed)), f.cast("long"), long(i)), 1), long(P31)) for i in range(7)]
        terms = [F.pmod(k * x, long(P31)) for k, x in zip(a, _limbs(high, low, _piece), strict=False)]
        return F.pmod(F.pmod(reduce(lambda x, y: x + y, terms) + a[6], long(P31)), long(self.table_len))
