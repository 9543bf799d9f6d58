"""What the dictionaries are compared with: exact tables, Bloom filters in three forms, fingerprint sets, Spark's own filter.

Integer keys may be hashed by the affine family, which any SQL engine can repeat; other keys by the digest.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce
from math import ceil, e, log2

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from eqdict.functions.hashing import affine31, digest, gf2_affine, limb_affine, long, seed_of
from eqdict.operators.build import key_columns
from eqdict.operators.probe import BROADCAST_BYTES

BLOCK_BITS = 4096  # bits of a row of the filter's table
WORDS = BLOCK_BITS // 64


@dataclass
class Bloom:
    """Planes of bits in blocks: table(plane, block, words). k probes: one in each plane, or all in one plane (shared)."""

    table: DataFrame
    bits: int
    k: int
    seed: int
    affine: bool
    shared: bool = False


def position(df: DataFrame, keys: list[str] | str, bits: int, seed: int, plane: int, affine: bool) -> Column:
    if affine:
        name = keys if isinstance(keys, str) else keys[0]
        return affine31(F.col(name), seed_of("bloom", seed, plane), bits)
    hi, lo = digest(key_columns(df, keys))
    return limb_affine(hi, lo, seed_of("bloom", seed, plane), bits)


def _set_bits(df: DataFrame, keys, bits: int, k: int, seed: int, affine: bool, shared: bool) -> DataFrame:
    at = F.array(*(F.struct(F.lit(0 if shared else j).alias("plane"), position(df, keys, bits, seed, j, affine).alias("p")) for j in range(k)))
    bit = df.select(F.inline(at)).where("p is not null")
    word = bit.groupBy("plane", F.floor(F.col("p") / 64).alias("w")).agg(F.bit_or(F.call_function("shiftleft", long(1), F.pmod("p", F.lit(64)).cast("int"))).alias("v"))
    return _blocks(word.select("plane", F.floor(F.col("w") / WORDS).alias("block"), F.pmod("w", F.lit(WORDS)).cast("int").alias("i"), "v"))


def _blocks(words: DataFrame) -> DataFrame:
    """(plane, block, words): the WORDS words of each block in order, from (plane, block, i, v)."""
    found = F.map_from_entries(F.collect_list(F.struct("i", "v")))
    blocks = words.groupBy("plane", "block").agg(found.alias("_m"))
    return blocks.select("plane", "block", F.transform(F.sequence(F.lit(0), F.lit(WORDS - 1)), lambda i: F.coalesce(F.try_element_at("_m", i), long(0))).alias("words"))


def bloom_single(df: DataFrame, keys, n: int | None = None, seed: int = 1, affine: bool = False) -> Bloom:
    """One probe, n log2 e bits: an error of a half."""
    return bloom_repeated(df, keys, 1, n, seed, affine)


def bloom_repeated(df: DataFrame, keys, k: int, n: int | None = None, seed: int = 1, affine: bool = False) -> Bloom:
    """k one-probe filters: n k log2 e bits, k probes, an error of 2^-k."""
    n = n if n is not None else df.count()
    bits = max(1, ceil(n * log2(e)))
    return Bloom(_set_bits(df, keys, bits, k, seed, affine, False), bits, k, seed, affine)


def bloom_shared(df: DataFrame, keys, k: int, n: int | None = None, seed: int = 1, affine: bool = False) -> Bloom:
    """The same memory as one array for all k hashes."""
    n = n if n is not None else df.count()
    bits = max(1, ceil(n * k * log2(e)))
    return Bloom(_set_bits(df, keys, bits, k, seed, affine, True), bits, k, seed, affine, True)


def bloom_insert(filter_: Bloom, df: DataFrame, keys) -> Bloom:
    """More keys, which Bloom filters take and equation stores do not; the error grows with them."""
    new = _set_bits(df, keys, filter_.bits, filter_.k, filter_.seed, filter_.affine, filter_.shared)
    both = filter_.table.unionByName(new).select("plane", "block", F.posexplode("words").alias("i", "v")).groupBy("plane", "block", "i").agg(F.bit_or("v").alias("v"))
    return Bloom(_blocks(both), filter_.bits, filter_.k, filter_.seed, filter_.affine, filter_.shared)


def bloom_bytes(filter_: Bloom) -> int:
    """What the filter's blocks hold in memory: their words and some 64 bytes a row."""
    return (1 if filter_.shared else filter_.k) * -(-filter_.bits // BLOCK_BITS) * (8 * WORDS + 64)


def bloom_contains(filter_: Bloom, df: DataFrame, keys, out: str = "hit", most_broadcast: int = BROADCAST_BYTES) -> DataFrame:
    """df with a boolean, null for null keys.

    While the blocks are at most most_broadcast bytes, each probe meets its plane without moving. Beyond, the distinct keys' probes
    are rows that join the blocks once, and their conjunction joins df.
    """
    if bloom_bytes(filter_) > most_broadcast:
        return _contains_joined(filter_, df, keys, out)
    got = df
    for j in range(filter_.k):
        got = got.withColumn(f"_p{j}", position(df, keys, filter_.bits, filter_.seed, j, filter_.affine))
    hit = None
    for j in range(filter_.k):
        plane = filter_.table.where(F.col("plane") == (0 if filter_.shared else j)).select(F.col("block").alias(f"_b{j}"), F.col("words").alias(f"_w{j}"))
        got = got.join(F.broadcast(plane), F.floor(F.col(f"_p{j}") / BLOCK_BITS) == F.col(f"_b{j}"), "left")
        bit = F.when(F.col(f"_p{j}").isNotNull(), _bit(F.col(f"_w{j}"), F.col(f"_p{j}")))
        hit = bit if hit is None else hit & bit
    return got.select(*df.columns, hit.alias(out))


def _bit(words: Column, p: Column) -> Column:
    word = F.coalesce(F.try_element_at(words, F.pmod(F.floor(p / 64), F.lit(WORDS)).cast("int") + 1), long(0))
    return F.getbit(word, F.pmod(p, F.lit(64)).cast("int")) == 1


def _contains_joined(filter_: Bloom, df: DataFrame, keys, out: str) -> DataFrame:
    names = [keys] if isinstance(keys, str) else list(keys)
    once = df.select(*(F.col(n).alias(f"_k{i}") for i, n in enumerate(names))).distinct().select("*", *(F.col(f"_k{i}").alias(n) for i, n in enumerate(names)))
    probes = F.array(*(F.struct(F.lit(0 if filter_.shared else j).alias("plane"), position(once, keys, filter_.bits, filter_.seed, j, filter_.affine).alias("_p")) for j in range(filter_.k)))
    own = [f"_k{i}" for i in range(len(names))]
    each = once.select(*own, F.inline(probes)).where("_p is not null").withColumn("block", F.floor(F.col("_p") / BLOCK_BITS))
    hits = each.join(filter_.table, ["plane", "block"], "left").groupBy(*own).agg(F.bool_and(_bit(F.col("words"), F.col("_p"))).alias("_hit"))
    same = reduce(lambda a, b: a & b, (F.col(n) == F.col(k) for n, k in zip(names, own, strict=True)))
    return df.join(hits, same, "left").select(*df.columns, F.col("_hit").alias(out))


def exact_dictionary(stored: DataFrame, probe: DataFrame, keys: list[str] | str, value: str, out: str = "value") -> DataFrame:
    """A table that keeps its keys, as a join."""
    names = [keys] if isinstance(keys, str) else list(keys)
    return probe.join(stored.select(*names, F.col(value).alias(out)), names, "left")


@dataclass
class FingerprintSet:
    """table(quotient, remainders): n quotients, the sorted distinct k-bit remainders of each."""

    table: DataFrame
    n: int
    k: int
    seed: int
    affine: bool


def _quotient(df: DataFrame, keys, n: int, k: int, seed: int, affine: bool) -> tuple[Column, Column]:
    if affine:
        name = keys if isinstance(keys, str) else keys[0]
        return affine31(F.col(name), seed_of("quotient", seed), n), affine31(F.col(name), seed_of("remainder", seed), 1 << k)
    hi, lo = digest(key_columns(df, keys))
    return limb_affine(hi, lo, seed_of("quotient", seed), n), gf2_affine(hi, lo, seed_of("remainder", seed), k)


def fingerprint_set(df: DataFrame, keys, k: int, n: int | None = None, seed: int = 1, affine: bool = False) -> FingerprintSet:
    """A quotient to n places and k bits beside: n k + O(n) bits, with uniform hashing."""
    n = max(1, n if n is not None else df.count())
    q, r = _quotient(df, keys, n, k, seed, affine)
    table = df.select(q.alias("quotient"), r.alias("r")).where("quotient is not null").groupBy("quotient").agg(F.array_sort(F.collect_set("r")).alias("remainders"))
    return FingerprintSet(table, n, k, seed, affine)


def fingerprint_contains(s: FingerprintSet, df: DataFrame, keys, out: str = "hit") -> DataFrame:
    q, r = _quotient(df, keys, s.n, s.k, s.seed, s.affine)
    got = df.withColumns({"_q": q, "_r": r}).join(s.table.withColumnRenamed("quotient", "_q"), "_q", "left")
    hit = F.when(F.col("_q").isNotNull(), F.coalesce(F.array_contains("remainders", F.col("_r")), F.lit(False)))
    return got.select(*df.columns, hit.alias(out))


def spark_bloom(df: DataFrame, column: str, n: int, error: float):
    """Spark's own filter of a long column, on the driver, by the JVM's DataFrame statistics. Optional: it is not a public Python API."""
    return df._jdf.stat().bloomFilter(column, n, error)
