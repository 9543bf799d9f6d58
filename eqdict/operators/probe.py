"""Looking keys up: a digest, a join with the bucket's row, and native bit operations.

A lookup never claims that a key is stored: other keys get an arbitrary value, 0 where their cell is empty. Null keys give null.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from eqdict.functions import rows as R
from eqdict.functions.gf import gf_dot
from eqdict.functions.hashing import digest, long, xxhash64_np
from eqdict.operators.build import bucket_of, key_columns, type_names
from eqdict.plans.kernels import table_hash
from eqdict.plans.solve import answer_table
from eqdict.sources.store import Store

BROADCAST_BYTES = 64 << 20


def store_bytes(store: Store) -> int:
    """What the bucket rows hold in memory, from the counts in the manifest: files may be far smaller."""
    f = store.facts
    words = f["variables"] if store.spec.field == "full" or store.spec.method in ("sparse", "global_sparse") else f["cells"] * store.spec.k if store.spec.method in ("two_level", "shared_inverse") else f["variables"] // 64 * store.spec.k
    return 8 * words + 64 * f["cells"] + 64 * f["buckets"]


def sized(rows: DataFrame, held: int) -> DataFrame:
    """rows as one side of a join: broadcast up to BROADCAST_BYTES, else never, as Spark judges by files that may hold much in few bytes."""
    return F.broadcast(rows) if held <= BROADCAST_BYTES else rows.hint("merge")


def joined(probe: DataFrame, store: Store) -> DataFrame:
    """probe(key_hi, key_lo, ...) with its bucket's row: the store is broadcast up to BROADCAST_BYTES, else both are shuffled."""
    rows = store.buckets.select("bucket", "split_seed", "func_no", "cells")
    with_bucket = probe.withColumn("bucket", bucket_of(store.spec, store.n_buckets, store.h1_seed))
    return with_bucket.join(sized(rows, store_bytes(store)), "bucket", "left")


def let(rows: DataFrame, **columns: Column) -> DataFrame:
    """rows with more columns, each computed once for a row: no filter is pushed through a generator, so none copies their expressions."""
    return rows.select("*", F.inline(F.array(F.struct(*(c.alias(n) for n, c in columns.items())))))


def located(rows: DataFrame, store: Store) -> DataFrame:
    """rows of `joined` with the key's cell (_m, _seed, _extra, _planes), _x and _y, the digest as later hashing sees it, and for narrow rows _row, for binary ones of any width _words."""
    spec, x, y = store.spec, F.col("key_hi"), F.col("key_lo")
    if spec.hashing == "table":
        rows = let(rows, _x=table_hash(spec, store.n_keys).index(F.col("func_no"), x, y), _y=F.col("func_no").cast("long"))
    else:
        rows = rows.withColumns({"_x": x, "_y": y})
    at = F.lit(1)
    if spec.method in ("two_level", "shared_inverse"):
        h = F.shiftrightunsigned(F.xxhash64(long(R.SPLIT), F.col("split_seed").cast("long"), F.col("_x"), F.col("_y")), 1)
        at = F.when(F.size("cells") > 0, F.pmod(h, F.size("cells").cast("long")).cast("int") + 1).otherwise(F.lit(1))
    rows = let(rows, _cell=F.try_element_at("cells", at))
    cell = {f"_{c}": F.col("_cell")[c] for c in ("m", "seed", "extra", "planes")}
    rows = rows.withColumns(cell | {"_m": F.coalesce(cell["_m"], F.lit(0))})
    if spec.method in ("dense", "one_level") and spec.field == "binary":
        words = F.sequence(F.lit(0), F.greatest(F.ceil(F.col("_m") / 64), F.lit(1)).cast("int") - 1)
        return let(rows, _words=F.transform(words, lambda i: R.word_row(F.col("_seed"), i, F.col("_x"), F.col("_y"), F.col("_m"))))
    if spec.method not in ("two_level", "shared_inverse") or spec.field == "full":
        return rows
    m, seed = F.col("_m"), F.coalesce("_seed", F.lit(0))
    if spec.method == "shared_inverse":
        side = F.greatest(m, F.lit(1))
        p = F.pmod(F.shiftrightunsigned(F.xxhash64(long(R.POSITION), F.coalesce("_extra", F.lit(0)).cast("long"), F.col("_x"), F.col("_y")), 1), (side * side).cast("long"))
        return let(rows, _row=R.mask_row(seed, p, long(0), m))
    if spec.by_variable:
        bits, start = R.local_row(seed, F.col("_x"), F.col("_y"), m, spec.window)
        return let(let(rows, _row=bits, _start=start), _held=R.window_word(F.col("_start"), F.col("_planes"), spec.k))
    return let(rows, _row=R.mask_row(seed, F.col("_x"), F.col("_y"), m, spec.kind, spec.t, spec.window))


def answer(store: Store, evaluator: str = "native") -> tuple[Column, Column]:
    """(value, whether the cell has variables) from the columns of `located`."""
    spec, x, y = store.spec, F.col("_x"), F.col("_y")
    m, seed, extra, planes = (F.col(f"_{c}") for c in ("m", "seed", "extra", "planes"))
    if spec.method in ("sparse", "global_sparse"):
        places = R.places_col(seed, x, y, m, extra, spec.replace)
        value = F.aggregate(places, long(0), lambda s, p: s.bitwiseXOR(F.element_at(planes, p.cast("int") + 1)))
    elif spec.field == "full":
        value = gf_dot(R.coefs_col(seed, x, y, m, spec.k), planes, spec.k)
    elif spec.method in ("dense", "one_level"):
        width = F.size("_words")

        def bit(j: int) -> Column:
            parities = F.aggregate(F.sequence(F.lit(0), width - 1), long(0), lambda s, i: s.bitwiseXOR(F.element_at("_words", i + 1).bitwiseAND(F.element_at(planes, i + 1 + j * width))))
            return F.shiftleft((F.bit_count(parities) % 2).cast("long"), j)

        value = bit(0)
        for j in range(1, spec.k):
            value = value.bitwiseOR(bit(j))
    else:
        row = F.col("_row")
        if evaluator == "table":  # one look in a list of all rows and planes, for cells of at most 4 keys
            if spec.cell_cap > 4:
                raise ValueError("answer tables are made for cells of at most 4 keys")
            table = F.lit(bytes(answer_table(4)))  # one constant: an array of so many columns takes the driver's memory
            value = long(0)
            for j in range(spec.k):
                value = value.bitwiseOR(F.shiftleft((F.substring(table, (row * 16 + F.element_at(planes, j + 1)).cast("int") + 1, F.lit(1)) == F.lit(b"\x01")).cast("long"), j))
        else:
            value = R.window_value(row, F.col("_held"), spec.window, spec.k) if spec.by_variable else R.parity_value(row, planes, spec.k)
    return F.when(m > 0, value), m > 0


def with_digest(store: Store, df: DataFrame, keys: list[str] | str) -> DataFrame:
    have, want = type_names(df, keys), store.spec.key_types
    if have != want:
        raise TypeError(f"the store has keys of {want}, the probe of {have}")
    hi, lo = digest(key_columns(df, keys), store.spec.digest)
    return df.withColumns({"key_hi": hi, "key_lo": lo})


def looked_up(store: Store, df: DataFrame, keys: list[str] | str, out: str = "value", evaluator: str = "native", filled: str | None = None) -> DataFrame:
    """df with the dictionary's value; with `filled`, also whether anything stands behind it."""
    keep = df.columns
    value, full = answer(store, evaluator)
    got = located(joined(with_digest(store, df, keys), store), store).withColumns({"_v": value, "_full": full})
    if store.facts["n_side"]:
        side = store.side.withColumnRenamed("value", "_side")
        got = got.join(sized(side, store.facts["n_side"] * 96), ["key_hi", "key_lo"], "left").withColumns({"_v": F.coalesce("_side", "_v"), "_full": F.col("_full") | F.col("_side").isNotNull()})
    value = F.when(F.col("key_hi").isNotNull(), F.when(F.col("_full"), F.col("_v")).otherwise(long(0)))
    return got.select(*keep, value.alias(out), *([F.col("_full").alias(filled)] if filled else []))


def looked_up_distinct(store: Store, df: DataFrame, keys: list[str] | str, out: str = "value") -> DataFrame:
    """The same with each distinct key looked up once, for probes in which a few keys are very frequent."""
    names = [keys] if isinstance(keys, str) else list(keys)
    once = looked_up(store, df.select(*names).distinct(), names, "_v").select(*(F.col(n).alias(f"_k{i}") for i, n in enumerate(names)), F.col("_v").alias(out))
    same = reduce(lambda a, b: a & b, (F.col(n).eqNullSafe(F.col(f"_k{i}")) for i, n in enumerate(names)))
    return df.join(once, same, "left").select(*df.columns, out)


# --- packed layout --------------------------------------------------------------------------------------------------------------

PACKED = "bucket long, n_keys int, split_seed int, func_no int, cell_sizes binary, seeds binary, rank_samples array<int>, payload binary"
RANK_EVERY = 16


def packed(store: Store) -> DataFrame:
    """Bucket rows with nothing but k bits a variable, a byte a size and two a seed, and a rank sample for every 16 cells.

    The payload of a bucket is one string of bits: cell after cell, in each plane after plane.
    """
    spec = store.spec
    if spec.method != "two_level" or spec.field != "binary":
        raise ValueError("the packed layout is for two-level stores with binary rows")

    def pack(batches):
        for b in batches:
            out = []
            for r in b.to_pylist():
                sizes = np.array([c["m"] for c in r["cells"]], np.uint8)
                seeds = np.array([c["seed"] for c in r["cells"]], "<u2")
                if spec.by_variable:  # plane after plane here, too
                    bits = [np.unpackbits(np.array(c["planes"], np.int64).view(np.uint8), bitorder="little")[: c["m"] * spec.k].reshape(c["m"], spec.k).T.ravel() for c in r["cells"] if c["m"]]
                else:
                    bits = [np.unpackbits(np.array([p], np.int64).view(np.uint8), bitorder="little")[: c["m"]] for c in r["cells"] for p in (c["planes"] if c["m"] else [])]
                rank = np.concatenate([[0], np.cumsum(sizes, dtype=np.int64)])[::RANK_EVERY] if len(sizes) else np.zeros(0, np.int64)
                payload = np.packbits(np.concatenate([np.zeros(0, np.uint8), *bits]), bitorder="little").tobytes()
                out.append((r["bucket"], r["n_keys"], r["split_seed"], r["func_no"], sizes.tobytes(), seeds.tobytes(), rank.tolist(), payload))
            cols = list(zip(*out, strict=True)) or [()] * 8
            kinds = (pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.binary(), pa.binary(), pa.list_(pa.int32()), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], [f.split()[0] for f in PACKED.split(", ")])

    return store.buckets.select("bucket", "n_keys", "split_seed", "func_no", "cells").mapInArrow(pack, PACKED)


def looked_up_packed(store: Store, table: DataFrame, df: DataFrame, keys: list[str] | str, out: str = "value") -> DataFrame:
    """df's distinct keys with their values, from a packed table: probe and store meet by bucket, and a kernel reads the bits."""
    spec, n_keys = store.spec, store.n_keys
    names = [keys] if isinstance(keys, str) else list(keys)
    probe = with_digest(store, df.select(*names), names).where("key_hi is not null").select("key_hi", "key_lo").distinct()
    probe = probe.withColumn("bucket", bucket_of(spec, store.n_buckets, store.h1_seed))

    def read(left: pa.Table, right: pa.Table) -> pa.Table:
        hi, lo = left.column("key_hi").to_numpy(), left.column("key_lo").to_numpy()
        value = np.zeros(len(hi), np.int64)
        if right.num_rows and len(hi):
            r = right.to_pylist()[0]
            sizes, seeds = np.frombuffer(r["cell_sizes"], np.uint8).astype(np.int64), np.frombuffer(r["seeds"], "<u2").astype(np.int64)
            if len(sizes):
                x, y = hi, lo
                if spec.hashing == "table":
                    x, y = table_hash(spec, n_keys).index_np(r["func_no"], hi, lo), np.full(len(hi), r["func_no"], np.int64)
                h = xxhash64_np(R.SPLIT, np.full(len(x), r["split_seed"], np.int64), x, y)
                cell = (h >> np.uint64(1)).astype(np.int64) % len(sizes)
                # the nearest rank sample, then the sizes from there
                start = np.array([r["rank_samples"][c // RANK_EVERY] + int(sizes[c // RANK_EVERY * RANK_EVERY : c].sum()) for c in range(len(sizes))])
                m = sizes[cell]
                row = R.masks_np(seeds[cell], x, y, m, spec.kind, spec.t, spec.window)
                bits = np.unpackbits(np.frombuffer(r["payload"], np.uint8), bitorder="little")
                bits = np.concatenate([bits, np.zeros(64, np.uint8)])
                place = np.arange(64)
                used = ((row[:, None] >> place.astype(np.uint64)) & np.uint64(1)).astype(bool)
                for j in range(spec.k):
                    at = (start[cell] * spec.k + j * m)[:, None] + place
                    bit = np.where(used, bits[np.minimum(at, len(bits) - 1)], 0).sum(axis=1) & 1
                    value |= bit.astype(np.int64) << j
        return pa.table({"key_hi": hi, "key_lo": lo, "_v": value})

    got = probe.groupBy("bucket").cogroup(table.groupBy("bucket")).applyInArrow(read, "key_hi long, key_lo long, _v long")
    if store.facts["n_side"]:
        got = got.join(store.side.withColumnRenamed("value", "_side"), ["key_hi", "key_lo"], "left").withColumn("_v", F.coalesce("_side", "_v"))
    whole = with_digest(store, df, names)
    return whole.join(got.select("key_hi", "key_lo", "_v"), ["key_hi", "key_lo"], "left").select(*df.columns, F.col("_v").alias(out))
