"""Costs and errors: logical and physical size, probes, work of a build, false positives, loads, and the experiments behind the bounds."""

from __future__ import annotations

import tracemalloc
from math import ceil, log2, sqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from eqdict.functions import rows as R
from eqdict.functions.hashing import TableHash, digest, xxhash64_np
from eqdict.functions.theory import bloom_bits
from eqdict.operators.build import group_of, key_columns, systems_of
from eqdict.operators.probe import RANK_EVERY, looked_up
from eqdict.plans import kernels
from eqdict.plans import solve as S
from eqdict.sources.store import Store
from eqdict.spec import DictSpec


def space(store: Store) -> dict[str, float]:
    """Bits by item. Payload: k for each variable. The packed layout's overhead: sizes, seeds, rank samples, headers, side, functions."""
    f, spec = store.facts, store.spec
    payload = spec.k * f["variables"]
    size_bits = ceil(log2(max(spec.cell_cap + spec.c, 1) + 1)) if spec.method in ("two_level", "shared_inverse") else 32
    seed_bits = max(1, ceil(log2(f["top_seed"] + 1))) * (2 if spec.method == "shared_inverse" else 1)
    items = {
        "payload": payload,
        "sizes": f["cells"] * size_bits,
        "seeds": f["cells"] * seed_bits,
        "ranks": f["cells"] // RANK_EVERY * 17,
        "headers": f["buckets"] * (64 + 6 + 7 * (spec.hashing == "table")),
        "side": f["n_side"] * (128 + spec.k),
        "table": 64 * (spec.table_len or 0) if spec.hashing == "table" else 0,
    }
    overhead = sum(v for k, v in items.items() if k != "payload")
    n = max(1, f["n_keys"])
    return items | {"overhead": overhead, "bits_per_key": (payload + overhead) / n, "to_ideal": (payload + overhead) / (n * spec.k), "to_bloom": (payload + overhead) / bloom_bits(n, spec.k)}


def store_bytes(store: Store) -> int:
    """Bytes of the store's files."""
    spark = store.buckets.sparkSession
    p = spark._jvm.org.apache.hadoop.fs.Path(store.path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).getContentSummary(p).getLength()


def probe_cost(store: Store) -> dict[str, float]:
    """Words read and operations for a query, from the counts of the store."""
    f, spec = store.facts, store.spec
    m = f["variables"] / max(1, f["cells"])
    if spec.method in ("sparse", "global_sparse"):
        t = spec.t or (3 if spec.method == "sparse" else R.odd_log(max(2, f["n_keys"])))
        return {"words": 1.0 + t, "operations": float(t)}
    if spec.method in ("dense", "one_level"):
        return {"words": 1.0 + spec.k * ceil(m / 64), "operations": m}
    if spec.field == "full":
        return {"words": 2.0 + ceil(m * spec.k / 64), "operations": m}
    t = {"dense": m / 2, "local": min(spec.window, m) / 2, "logsparse": float(R.odd_log(max(2, round(m)))), "sparse": float(spec.t or 3)}[spec.kind]
    # a window of variables lies in one word, or over the edge of two; other rows read a word of each plane
    return {"words": 2.0 + (1 + (spec.window * spec.k - 1) / 64 if spec.by_variable else spec.k), "operations": t}


def build_memory(spec: DictSpec, n: int) -> float:
    """Peak bytes a key that solving takes in Python, measured on one kernel call: a group of full buckets, or one system."""
    many = spec.method in ("two_level", "shared_inverse", "one_level")
    size = max(1, min(n, group_of(spec) * spec.bucket_mean) if many else -(-n // systems_of(spec, n)))
    hi, lo = _keys(size, 77)
    buckets = max(1, -(-size // spec.bucket_mean)) if many else 1
    table = pa.table({"bucket": np.arange(size, dtype=np.int64) % buckets, "key_hi": hi, "key_lo": lo, "value": (hi & ((1 << spec.k) - 1))})
    kernel = kernels.two_level(spec, n) if spec.method in ("two_level", "shared_inverse") else kernels.single(spec)
    tracemalloc.start()
    try:
        kernel(table)
        return tracemalloc.get_traced_memory()[1] / size
    finally:
        tracemalloc.stop()


def expected_count(hits: Column, n: Column, chance: Column) -> Column:
    """Whether a count of n independent events is within six deviations, and six, of what their chance says."""
    return F.abs(hits - n * chance) <= 6 * F.sqrt(n * chance * (1 - chance)) + 6


def verify_members(store: Store, df: DataFrame, keys, value: str) -> int:
    """Stored keys with a wrong answer: must be 0."""
    return looked_up(store, df, keys, "_got").where(F.coalesce(F.col("_got") != F.col(value), F.lit(True))).count()


def wilson(hits: int, n: int, z: float = 3.29) -> tuple[float, float]:
    if n == 0:
        return 0.0, 1.0
    p, d = hits / n, 1 + z * z / n
    mid, half = (p + z * z / (2 * n)) / d, z * sqrt(p * (1 - p) / n + z * z / (4 * n * n)) / d
    return mid - half, mid + half


def fp_rate(tested: DataFrame, hit: str = "hit") -> tuple[int, int, float, float]:
    """(hits, keys, interval) of keys that are not stored."""
    r = tested.agg(F.coalesce(F.sum(F.col(hit).cast("long")), F.lit(0)).alias("h"), F.count(hit).alias("n")).first()
    return r["h"], r["n"], *wilson(r["h"], r["n"])


def nonmember_histogram(store: Store, df: DataFrame, keys) -> DataFrame:
    """(value, n) of answers to keys that are not stored, empty cells left out."""
    return looked_up(store, df, keys, "value", filled="_full").where("_full").groupBy("value").agg(F.count("*").alias("n"))


def chi_square(counts: list[int], cells: int) -> float:
    n = sum(counts)
    return sum((c - n / cells) ** 2 for c in counts + [0] * (cells - len(counts))) / (n / cells)


def load_report(loads: DataFrame, cap: int) -> DataFrame:
    """(buckets, keys, largest, bad_buckets, bad_keys) of bucket loads(bucket, keys)."""
    bad = F.col("keys") > cap
    return loads.agg(F.count("*").alias("buckets"), F.sum("keys").alias("keys"), F.max("keys").alias("largest"), F.count(F.when(bad, 1)).alias("bad_buckets"), F.coalesce(F.sum(F.when(bad, F.col("keys"))), F.lit(0)).alias("bad_keys"))


# --- experiments: the keys of a table, dealt into draws of so many, each of which a task solves on its own ------------------------

DEALT = 4096  # buckets in which keys are numbered
CALL = 8192  # keys of the draws that one kernel call takes, or one draw that has more


def _keys(n: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    i = np.arange(n, dtype=np.int64)
    return xxhash64_np(seed, i).view(np.int64), xxhash64_np(seed + 1, i).view(np.int64)


def numbered(keys: DataFrame) -> DataFrame:
    """(key_hi, key_lo, no): the digests of distinct keys without nulls, numbered from 0 without a gap.

    Keys are numbered within buckets by a hash, and buckets by their sizes, so no task meets all keys.
    """
    hi, lo = digest(key_columns(keys, keys.columns))
    made = keys.dropna().select(hi.alias("key_hi"), lo.alias("key_lo")).withColumn("_bucket", F.pmod("key_hi", F.lit(DEALT)))
    dealt = made.repartition("_bucket").distinct()
    sizes = dealt.groupBy("_bucket").agg(F.count("*").alias("_n"))
    before = sizes.select("_bucket", (F.sum("_n").over(Window.orderBy("_bucket")) - F.col("_n")).alias("_before"))
    within = F.row_number().over(Window.partitionBy("_bucket").orderBy("key_hi", "key_lo"))
    return dealt.withColumn("_r", within).join(F.broadcast(before), "_bucket").select("key_hi", "key_lo", (F.col("_before") + F.col("_r") - 1).alias("no"))


def _experiment(keys: DataFrame, grid: list[tuple], size: int, names: str, one) -> DataFrame:
    """(grid columns, draws, solved): one(params, hi, lo) -> bool for each draw, a row of hi and lo, for every grid entry.

    Column `size` of the grid says how many keys a draw has. All distinct keys are dealt, but for the fewer than that which are left over.
    """
    spark = keys.sparkSession
    many = {n: max(1, CALL // n) for n in sorted({int(g[size]) for g in grid})}
    calls = F.array(*(F.struct(F.lit(n).alias("size"), F.floor(F.col("no") / (n * d)).alias("call")) for n, d in many.items()))
    # much work for few bytes, so tasks are not joined
    apart = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 4 * spark.sparkContext.defaultParallelism)
    rows = numbered(keys).select("key_hi", "key_lo", "no", F.inline(calls)).repartition(apart, "size", "call")

    def run(table: pa.Table) -> pa.Table:
        n, order = table.column("size")[0].as_py(), np.argsort(table.column("no").to_numpy())
        draws = len(order) // n
        hi, lo = (table.column(c).to_numpy()[order][: draws * n].reshape(draws, n) for c in ("key_hi", "key_lo"))
        cells = [i for i, g in enumerate(grid) if int(g[size]) == n]
        return pa.table({"cell": pa.array(cells, pa.int64()), "draws": pa.array([draws] * len(cells), pa.int64()), "solved": pa.array([int(one(grid[i], hi, lo).sum()) if draws else 0 for i in cells], pa.int64())})

    found = rows.groupBy("size", "call").applyInArrow(run, "cell long, draws long, solved long").groupBy("cell").agg(F.sum("draws").alias("draws"), F.sum("solved").alias("solved"))
    table = spark.createDataFrame([(i, *g) for i, g in enumerate(grid)], "cell long, " + names)
    return table.join(found, "cell", "left").fillna(0, ["draws", "solved"]).drop("cell")


def independence_experiment(keys: DataFrame, grid: list[tuple[int, int, int]]) -> DataFrame:
    """(k, n, c, draws, solved): how often the equations of n keys in n + c variables over GF(2^k) are independent."""

    def one(g, hi, lo):
        k, n, c = g
        if k == 1:
            rows = R.words_np(0, hi.ravel(), lo.ravel(), n + c).reshape(len(hi), n, -1)
            return S.eliminate_many(rows, np.zeros(hi.shape, np.uint64), np.ones(hi.shape, bool), np.full(len(hi), n + c))[0]
        return S.independent_field(R.coefs_np(0, hi.ravel(), lo.ravel(), n + c, k).reshape(len(hi), n, n + c), k)

    return _experiment(keys, grid, 1, "k int, n int, c int", one)


def sparse_experiment(keys: DataFrame, grid: list[tuple[int, int, float]]) -> DataFrame:
    """(n, t, slack, draws, solved): how often n keys' equations with t places in slack * n variables are independent over GF(2)."""

    def one(g, hi, lo):
        n, t, slack = g
        m = ceil(n * slack)
        places = R.places_np(np.zeros(hi.size, np.int64), hi.ravel(), lo.ravel(), np.full(hi.size, m), t)
        rows = S.dense_words(places, m).reshape(len(hi), n, -1)  # only their rank counts, so all draws are eliminated together
        return S.eliminate_many(rows, np.zeros(hi.shape, np.uint64), np.ones(hi.shape, bool), np.full(len(hi), m))[0]

    return _experiment(keys, grid, 0, "n int, t int, slack double", one)


def split_experiment(keys: DataFrame, grid: list[tuple[int, float, float]]) -> DataFrame:
    """(keys, mean, cap, draws, solved): how often no cell of a split bucket is over the cap."""

    def one(g, hi, lo):
        n, mean, cap = g
        cells = max(1, ceil(n / mean))
        at = (xxhash64_np(R.SPLIT, 0, hi.ravel(), lo.ravel()) >> np.uint64(1)).astype(np.int64) % cells + np.repeat(np.arange(len(hi)) * cells, n)
        return np.bincount(at, minlength=len(hi) * cells).reshape(len(hi), cells).max(axis=1) <= cap

    return _experiment(keys, grid, 0, "keys int, mean double, cap double", one)


def all_differ(x: np.ndarray) -> np.ndarray:
    """Whether a row has no value twice."""
    return (np.diff(np.sort(x, axis=1), axis=1) != 0).all(axis=1)


def position_experiment(keys: DataFrame, sizes: list[int]) -> DataFrame:
    """(s, draws, solved): how often s keys fall on different ones of s^2 positions."""

    def one(g, hi, lo):
        s = g[0]
        return all_differ(((xxhash64_np(R.POSITION, 0, hi.ravel(), lo.ravel()) >> np.uint64(1)) % np.uint64(s * s)).reshape(hi.shape))

    return _experiment(keys, [(s,) for s in sizes], 0, "s int", one)


def table_hash_experiment(keys: DataFrame, grid: list[tuple[int, int, int]]) -> DataFrame:
    """(keys, table_len, funcs, draws, solved): how often one of so many functions keeps a bucket's keys on different words."""

    def one(g, hi, lo):
        _, table_len, funcs = g
        h = TableHash(table_len, funcs, 1)
        return np.logical_or.reduce([all_differ(h.index_np(f, hi.ravel(), lo.ravel()).reshape(hi.shape)) for f in range(funcs)])

    return _experiment(keys, grid, 0, "keys int, table_len int, funcs int", one)


def between_shares(hits: Column, n: Column, least: Column, most: Column) -> Column:
    """Whether a count of n independent events has a chance between two shares, within six deviations of them."""
    return (hits >= n * least - 6 * F.sqrt(n * least * (1 - least))) & (hits <= n * most + 6 * F.sqrt(n * most * (1 - most)))
