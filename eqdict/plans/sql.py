"""Stores for SQL users: views of their tables, and table functions."""

from __future__ import annotations

import re

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from eqdict.functions import theory
from eqdict.operators.membership import ALPHABET
from eqdict.sources.store import Store


@F.udtf(returnType="variant string")
class Edit1:
    """Words within one edit of a word, itself first."""

    def eval(self, word: str):
        if word is None:
            return
        seen = [word]
        seen += [word[:i] + c + word[i:] for i in range(len(word) + 1) for c in ALPHABET]
        seen += [word[:i] + word[i + 1 :] for i in range(len(word))]
        seen += [word[:i] + c + word[i + 1 :] for i in range(len(word)) for c in ALPHABET]
        for w in dict.fromkeys(seen):
            yield (w,)


@F.udtf(returnType="method string, bits double, probes double, build string, hashing string, error double")
class Theory:
    """The comparison of structures for n keys and k bits."""

    def eval(self, n: int, k: int):
        for r in theory.comparison_table(n, k):
            yield r["method"], r["bits"], r["probes"], r["build"], r["hashing"], r["error"]


def explained(store: Store, high: int, low: int) -> list[tuple[str, str]]:
    """The steps of one lookup from a key's digest, for two-level stores with dense binary rows."""
    from eqdict.functions import rows as R
    from eqdict.functions.hashing import limb_affine_np, seed_of, xxhash64_np

    spec = store.spec
    h, w = np.array([high], np.int64), np.array([low], np.int64)
    bucket = int(limb_affine_np(h, w, seed_of("bucket", spec.seed, store.h1_seed), store.n_buckets)[0]) if store.n_buckets > 1 else 0
    out = [("bucket", str(bucket))]
    row = store.buckets.where(F.col("bucket") == bucket).first()
    if row is None or not row["cells"]:
        return [*out, ("answer", "0 (nothing stored)")]
    at = int(xxhash64_np(R.SPLIT, row["split_seed"], h, w)[0] >> np.uint64(1)) % len(row["cells"])
    cell = row["cells"][at]
    mask = int(R.masks_np(cell["seed"], h, w, cell["m"])[0])
    bits = [(mask & (p & (1 << 64) - 1)).bit_count() & 1 for p in cell["planes"]]
    return [*out, ("cell", str(at)), ("variables", str(cell["m"])), ("seed", str(cell["seed"])), ("row", f"{mask:064b}"), ("answer", str(sum(b << j for j, b in enumerate(bits))))]


def register(spark: SparkSession, store: Store, name: str) -> None:
    """Views <name>_cells (a row for each cell) and <name>_side, and the table functions edit1 and equation_theory."""
    if not re.fullmatch(r"\w+", name):
        raise ValueError("a view's name has letters, digits and underscores")
    cells = store.buckets.select("bucket", "split_seed", "func_no", F.posexplode("cells").alias("cell", "_c")).select("bucket", "split_seed", "func_no", "cell", "_c.*")
    cells.createOrReplaceTempView(f"{name}_cells")
    store.side.createOrReplaceTempView(f"{name}_side")
    spark.udtf.register("edit1", Edit1)
    spark.udtf.register("equation_theory", Theory)
