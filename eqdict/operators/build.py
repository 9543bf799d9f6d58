"""Building dictionaries: key and value columns in, a store out.

One wide shuffle carries 24 bytes a key: the digest's halves and the value, by group of buckets. Duplicates are settled inside
that partitioning, then each group is solved by one kernel call. All redraws but those of the bucket hash are local to a task.
"""

from __future__ import annotations

from dataclasses import replace as with_
from math import log2

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from eqdict.functions.hashing import digest, limb_affine, seed_of
from eqdict.plans import kernels
from eqdict.sources.store import BUCKETS, Store, save, workdir
from eqdict.spec import DictSpec

GROUP, GROUP_KEYS = 8, 32_768  # buckets that one kernel call solves together, or more that hold about so many keys
PART = 2048  # keys of a system, where one for all would be too large
H1_TRIES = 8
MOST_APART = 4096
MOST_LABELS = 1 << 16


def key_columns(df: DataFrame, keys: list[str] | str) -> list:
    names = [keys] if isinstance(keys, str) else list(keys)
    return [(F.col(n), df.schema[n].dataType) for n in names]


def type_names(df: DataFrame, keys: list[str] | str) -> tuple[str, ...]:
    """Types as far as they matter to hashing: all integers are one."""
    whole = {"tinyint": "bigint", "smallint": "bigint", "int": "bigint", "float": "double"}
    names = (t.simpleString() for _, t in key_columns(df, keys))
    return tuple(whole.get(t, t) for t in names)


def refuse(condition: Column, message: str, otherwise: Column) -> Column:
    return F.when(condition, F.raise_error(F.lit(message)).cast("long")).otherwise(otherwise)


def prepared(df: DataFrame, keys: list[str] | str, value: str | Column, spec: DictSpec) -> DataFrame:
    """(key_hi, key_lo, value): checked as they stream by, in the same pass."""
    hi, lo = digest(key_columns(df, keys), spec.digest)
    v = (F.col(value) if isinstance(value, str) else value).cast("long")
    out = df.select(hi.alias("key_hi"), lo.alias("key_lo"), v.alias("value"))
    if spec.on_null == "drop":
        out = out.where("key_hi is not null")
    checked = refuse(F.col("value").isNull(), "a value is null", refuse((F.col("value") < 0) | (F.col("value") >= 1 << spec.k), f"a value does not fit {spec.k} bits", F.col("value")))
    return out.select(refuse(F.col("key_hi").isNull(), "a key is null", F.col("key_hi")).alias("key_hi"), "key_lo", checked.alias("value"))


def bucket_of(spec: DictSpec, n_buckets: int, h1_seed: int) -> Column:
    return limb_affine(F.col("key_hi"), F.col("key_lo"), seed_of("bucket", spec.seed, h1_seed), n_buckets) if n_buckets > 1 else F.lit(0).cast("long")


def group_of(spec: DictSpec) -> int:
    return max(GROUP, GROUP_KEYS // spec.bucket_mean) if spec.method in ("one_level", "two_level", "shared_inverse") else 1


def most_keys(spec: DictSpec) -> int:
    """Keys that one system may have where the method makes a single one."""
    if spec.method == "dense":
        return spec.most_single or (8192 if spec.field == "binary" else 1024)
    return spec.most_global or {"block": 4096, "krylov": 8192}.get(spec.solver, 20_000)


def systems_of(spec: DictSpec, keys: int) -> int:
    """How many systems such a method makes of so many keys: one as long as it may have them all, else some of PART keys on average.

    Over the field a probe computes a product for each variable of its system, so those are smaller.
    Where the spec names the most itself, more keys are refused.
    """
    most, named = most_keys(spec), spec.most_single if spec.method == "dense" else spec.most_global
    if keys <= most:
        return 1
    if named is not None:
        raise ValueError(f"method {spec.method} makes one system and takes at most {most} keys; leave that limit out or use two_level")
    return -(-keys // (PART // 8 if spec.field == "full" else PART // 2 if spec.solver in ("krylov", "block") else PART))


def settled(clustered: DataFrame, *by: str, spec: DictSpec) -> DataFrame:
    """One value for each key: equal ones collapse, several follow the policy."""
    out = clustered.groupBy(*by, "key_hi", "key_lo").agg(F.min("value").alias("_lo"), F.max("value").alias("_hi"))
    value = F.col("_hi") if spec.on_conflict == "max" else F.col("_lo")
    if spec.on_conflict == "error":
        value = refuse(F.col("_lo") != F.col("_hi"), "a key has several values", value)
    return out.select(*by, "key_hi", "key_lo", value.alias("value"))


def solved(data: DataFrame, spec: DictSpec, n_buckets: int, h1_seed: int, n: int) -> DataFrame:
    """The plan of a build: digest, one exchange by group, duplicates, kernel.

    Keys that repeat often meet in a partial aggregate first, at the price of a second exchange, so no task gets all rows of one key.
    """
    with_bucket = data.withColumn("bucket", bucket_of(spec, n_buckets, h1_seed)).withColumn("_group", F.floor(F.col("bucket") / group_of(spec)))
    # a system of thousands of keys is much work for few bytes, so tasks with one are not joined
    apart = (min(n_buckets, MOST_APART),) if group_of(spec) == 1 and n_buckets > 1 else ()
    if spec.pre_dedupe is not False:
        with_bucket = settled(with_bucket, "_group", "bucket", spec=spec)
        keyed = with_bucket.repartition(*apart, "_group")
    else:
        keyed = settled(with_bucket.repartition(*apart, "_group"), "_group", "bucket", spec=spec)
    kernel = kernels.two_level(spec, n) if spec.method in ("two_level", "shared_inverse") else kernels.single(spec)
    return keyed.groupBy("_group").applyInArrow(kernel, BUCKETS)


def bucket_loads(data: DataFrame, spec: DictSpec, n_buckets: int, h1_seed: int) -> DataFrame:
    """(bucket, keys) of distinct digests."""
    return data.select("key_hi", "key_lo").distinct().select(bucket_of(spec, n_buckets, h1_seed).alias("bucket")).groupBy("bucket").agg(F.count("*").alias("keys"))


def bad_key_share(loads: DataFrame, cap: int) -> tuple[int, int]:
    """(keys in buckets over the cap, all keys)."""
    r = loads.agg(F.coalesce(F.sum(F.when(F.col("keys") > cap, F.col("keys"))), F.lit(0)).alias("bad"), F.coalesce(F.sum("keys"), F.lit(0)).alias("n")).first()
    return r["bad"], r["n"]


def choose_h1(data: DataFrame, spec: DictSpec, n_buckets: int, limit: float | None = None, candidates: int = H1_TRIES) -> int:
    """The first bucket hash that leaves at most `limit` keys in overfull buckets (one-level: none).

    Distinct digests are made once, and the loads of all candidates counted in one pass over them.
    """
    tried = F.array(*(F.struct(F.lit(s).alias("h1"), bucket_of(spec, n_buckets, s).alias("bucket")) for s in range(candidates)))
    loads = data.select("key_hi", "key_lo").distinct().select(F.inline(tried)).groupBy("h1", "bucket").agg(F.count("*").alias("keys"))
    bad = F.coalesce(F.sum(F.when(F.col("keys") > spec.cap, F.col("keys"))), F.lit(0))
    found = {r["h1"]: (r["bad"], r["n"]) for r in loads.groupBy("h1").agg(bad.alias("bad"), F.sum("keys").alias("n")).collect()}
    for s in range(candidates):
        bad_keys, n = found.get(s, (0, 0))
        if bad_keys <= (limit if limit is not None else 0 if spec.method == "one_level" else n / _log2(n) ** 2):
            return s
    raise RuntimeError(f"{candidates} bucket hashes left too many keys in overfull buckets")


def _log2(n: int) -> float:
    return log2(max(n, 2))


def build(df: DataFrame, keys: list[str] | str, value: str | Column, spec: DictSpec, path: str | None = None, n_rows: int | None = None) -> Store:
    """A store of the dictionary keys -> value.

    Keys may be any columns but maps; null keys follow spec.on_null, null values and values of more than k bits are errors. n_rows
    saves a count of df. Methods with one system make several, by a hash of the keys, where one would have too many (see systems_of).
    """
    spec = with_(spec, key_types=type_names(df, keys))
    data = prepared(df, keys, value, spec)
    n = n_rows
    if n is None:
        hashed = F.approx_count_distinct(F.xxhash64(*(F.col(c) for c in ([keys] if isinstance(keys, str) else keys))), 0.02)
        n, about = df.agg(F.count("*"), hashed).first()
        if spec.pre_dedupe is None:
            spec = with_(spec, pre_dedupe=n > 1.2 * about)
    if spec.hashing == "table":  # the number of functions is part of the store
        h = kernels.table_hash(spec, n)
        spec = with_(spec, table_len=h.table_len, n_funcs=h.n_funcs)
    n_buckets, h1_seed = 1, 0
    if spec.method in ("one_level", "two_level", "shared_inverse"):
        n_buckets = max(1, -(-n // spec.bucket_mean))
    else:
        n_buckets = systems_of(spec, data.select("key_hi", "key_lo").distinct().count())
        if n_buckets > 1:
            h1_seed = choose_h1(data, spec, n_buckets, limit=0)
    if spec.method == "one_level":
        h1_seed = choose_h1(data, spec, n_buckets)
    path = path or workdir(df.sparkSession, "store")
    if spec.method not in ("two_level", "shared_inverse"):
        return save(spec, n_buckets, h1_seed, solved(data, spec, n_buckets, h1_seed, n), path)
    # the bucket hash is judged by what it left over, before the store is committed, and redrawn if overfull buckets hold too many keys
    for s in range(H1_TRIES):
        limit = -1.0 if spec.bad_share is None else spec.bad_share
        store = save(spec, n_buckets, s, solved(data, spec, n_buckets, s, n), path, limit)
        if store is not None:
            return store
    raise RuntimeError(f"{H1_TRIES} bucket hashes left too many keys in overfull buckets; allow more of them, or larger buckets")


def encoded(df: DataFrame, column: str) -> tuple[DataFrame, DataFrame]:
    """(codebook(code, label), df with _code): for values with few distinct labels. Nulls stay null; more than MOST_LABELS are refused."""
    labels = df.select(F.col(column).alias("label")).where("label is not null").distinct().limit(MOST_LABELS + 1).collect()
    if len(labels) > MOST_LABELS:
        raise ValueError(f"{column} has more than {MOST_LABELS} labels")
    ordered = sorted(r["label"] for r in labels)
    book = df.sparkSession.createDataFrame([(i, x) for i, x in enumerate(ordered)], f"code long, label {df.schema[column].dataType.simpleString()}")
    return book, df.join(F.broadcast(book.withColumnRenamed("code", "_code")), F.col(column) == F.col("label"), "left").drop("label")
