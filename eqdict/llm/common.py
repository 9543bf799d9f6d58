"""What the operators share: work folders, staged tables, word hashing and components of a link table."""

from __future__ import annotations

import hashlib
import re
import tempfile
import uuid

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SPACE = r"[\x20\x09-\x0D]+"


def workdir(spark: SparkSession, name: str) -> str:
    """A fresh folder that driver and executors share.

    It lies in the folder named by spark.checkpoint.dir. Where that is unset, a local master gets a temporary folder (tests); on a
    cluster, whose machines do not share their folders, that is an error.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if spark.sparkContext.master != "local" and not spark.sparkContext.master.startswith("local["):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        base = tempfile.mkdtemp(prefix="llm-work-")
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def staged(df: DataFrame, path: str) -> DataFrame:
    """Write df as a table and read it again: later steps read files, so a lost executor costs no recomputation of what made them."""
    spark, schema = df.sparkSession, df.schema
    df.write.parquet(path)
    return spark.read.schema(schema).parquet(path)


def drop(spark: SparkSession, path: str) -> None:
    """Delete a staged table that no later step reads."""
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


def parts_of(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


# --- words and their hashes, in numpy -------------------------------------------------------------------------------------------

LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
_IS_WORD = np.array([not (c == 0x20 or 0x09 <= c <= 0x0D) for c in range(256)])
_ODD = (0x9E3779B97F4A7C15, 0xD1B54A32D192ED03, 0x8CB92BA72F3D8DD7)
#: Longer words are hashed by BLAKE2b.
SHORT = 16


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (bijective)."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def word_bounds(raw: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First bytes and ends (exclusive) of the words [^\\x20\\x09-\\x0D]+ of UTF-8 bytes."""
    edge = np.diff(_IS_WORD[raw].view(np.int8), prepend=np.int8(0), append=np.int8(0))
    return np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)


def word_hashes(data: bytes, seed: int = 0) -> np.ndarray:
    """A 64-bit hash for each word, in order. Equal words have equal hashes wherever they stand; other seeds give independent hashes.

    A word of at most SHORT bytes is its two halves of eight bytes and its length, mixed; words of one length up to eight never
    collide. A longer one gets eight bytes of a keyed BLAKE2b digest, as sums over a word's bytes are not safe from words that are
    made of the same parts again and again.
    """
    raw = np.frombuffer(data, np.uint8)
    if len(raw) == 0:
        return np.zeros(0, np.uint64)
    starts, ends = word_bounds(raw)
    size = (ends - starts).astype(np.uint64)
    long_ = np.flatnonzero(size > SHORT)
    # eight bytes from any place on, whatever its alignment
    filled = data + bytes(SHORT)
    eight = np.ndarray(len(data) + 9, "<u8", filled, strides=(1,))
    first, second = eight[starts], eight[np.minimum(starts + 8, len(data))]
    first &= np.uint64(0xFFFFFFFFFFFFFFFF) >> (np.uint64(64) - np.uint64(8) * np.minimum(size, np.uint64(8)))
    rest = np.minimum(np.maximum(size, np.uint64(8)) - np.uint64(8), np.uint64(8))
    second = np.where(rest > 0, second & (np.uint64(0xFFFFFFFFFFFFFFFF) >> np.minimum(np.uint64(64) - np.uint64(8) * rest, np.uint64(63))), np.uint64(0))
    key = np.uint64((seed * 2 + 1) * _ODD[0] & 0xFFFFFFFFFFFFFFFF)
    out = mix(mix(first ^ key) * np.uint64(_ODD[1]) ^ mix(second + np.uint64(_ODD[2]) * (size ^ key)))
    if len(long_):
        name = seed.to_bytes(8, "little")
        digests = b"".join(hashlib.blake2b(data[a:b], digest_size=8, key=name).digest() for a, b in zip(starts[long_].tolist(), ends[long_].tolist(), strict=True))
        out[long_] = np.frombuffer(digests, "<u8")
    return out


def pair_hash(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The hash of a sequence from those of its two parts."""
    return mix(a * np.uint64(0xD6E8FEB86659FD93) + mix(b + np.uint64(0x2545F4914F6CDD1D)))


def window_hashes(words: np.ndarray, length: int) -> np.ndarray:
    """A hash for each run of `length` consecutive words, made by doubling."""
    n = len(words) - length + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    power, have, out, done = words, 1, None, 0
    while True:
        if length & have:
            part = power[done : done + n]
            out = part if out is None else pair_hash(out, part)
            done += have
        if done == length:
            return out
        power = pair_hash(power[:-have], power[have:])
        have *= 2


def rows_of(batch, *names: str):
    """Python values of the named columns of an Arrow batch, row by row."""
    return zip(*(batch.column(n).to_pylist() for n in names), strict=True)


def is_word_space(c: str) -> bool:
    return bool(re.fullmatch(SPACE, c))


# --- components -----------------------------------------------------------------------------------------------------------------


def components(links: DataFrame, work: str) -> DataFrame:
    """(node, root) for every node of an undirected link table (a, b): root is the smallest node that can be reached.

    Alternates two star steps until the table no longer changes: each node hangs its larger neighbours on its smallest one, then
    its smaller neighbours and itself on the smallest. A round is two grouped minima and two joins by node; a node with very many
    links is a skewed join key, which adaptive execution splits. Rounds grow with the logarithm of the longest chain. Every round
    is a written table. Self links give nodes alone; nulls are dropped.
    """
    spark = links.sparkSession
    e = links.where("a is not null and b is not null").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    selves = e.where("a = b").select(F.col("a").alias("node"))
    e = staged(e.where("a <> b").distinct(), f"{work}/links-0")

    def mark(t: DataFrame) -> tuple:
        r = t.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        return r[0], r[1]

    last, i = mark(e), 0
    while last[0]:
        i += 1
        both = e.union(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"))
        large = both.where("b > a").join(low, "a").select(F.col("b").alias("a"), F.col("m").alias("b"))
        large = large.where("a <> b").distinct()
        low = large.groupBy("a").agg(F.min("b").alias("m"))
        joined = large.join(low, "a")
        small = joined.where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).union(low.select("a", F.col("m").alias("b")))
        e = staged(small.where("a <> b").distinct(), f"{work}/links-{i}")
        drop(spark, f"{work}/links-{i - 1}")
        now = mark(e)
        if now == last:
            break
        last = now
    # at rest every node hangs on its root
    return e.select(F.col("a").alias("node"), F.col("b").alias("root")).union(e.select(F.col("b").alias("node"), F.col("b").alias("root"))).union(selves.select("node", F.col("node").alias("root"))).groupBy("node").agg(F.min("root").alias("root"))
