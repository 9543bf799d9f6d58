"""Measured tables: costs and errors of the methods and baselines side by side, and what filters save the applications.

Registered queries compare these with what is expected of them; here are the figures themselves.
"""

from __future__ import annotations

import time
from dataclasses import replace as with_

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from eqdict.operators import baselines, measures
from eqdict.operators.build import build
from eqdict.operators.membership import build_filter, contains, fingerprint, where_contains
from eqdict.operators.probe import looked_up
from eqdict.spec import DictSpec

KS = (1, 2, 4, 8, 16)
#: Methods that solve one system, so the key set must be small; then the bucketed ones.
SINGLE = {"dense": {"method": "dense"}, "sparse": {"method": "sparse", "slack": 1.3}, "global sparse": {"method": "global_sparse"}}
BUCKETED = {
    "one level": {"method": "one_level", "bucket_mean": 64, "bucket_cap": 160, "seed_tries": 64},
    "two levels": {},
    "log-sparse rows": {"kind": "logsparse", "seed_tries": 256},
    "local rows": {"kind": "local", "seed_tries": 1024, "cell_mean": 24, "cell_cap": 40},
    "shared inverses": {"method": "shared_inverse", "cell_mean": 2.5, "cell_cap": 6, "bucket_mean": 64},
    "table hashing": {"hashing": "table", "bucket_mean": 512, "bucket_cap": 1024},
}
LADDER = "method string, k int, n long, bits_per_key double, words_read double, misses long, tested long, hits long, build_s double, probe_s double, build_bytes_per_key double"


def _timed(f) -> tuple[object, float]:
    t = time.time()
    return f(), time.time() - t


def ladder(few: DataFrame, many: DataFrame, key: str, absent: DataFrame, ks: tuple[int, ...] = KS, only: tuple[str, ...] | None = None) -> DataFrame:
    """LADDER: each method and baseline as a membership filter, for each number of bits.

    Methods with one system hold `few`, all others `many`. The choice of seeds depends on keys and coefficients only, and each bit of
    the values has its own right side, so the first k planes of a store for max(ks) bits are the store for k bits: one build and one
    probe serve all. absent are keys that neither table has.
    """
    spark, top, rows = many.sparkSession, max(ks), []
    for name, how in (SINGLE | BUCKETED).items():
        if only is not None and name not in only:
            continue
        members = few if name in SINGLE else many
        n = members.count()
        store, built = _timed(lambda members=members, n=n, how=how: build_filter(members, key, top, n_rows=n, pre_dedupe=False, **how))
        differ = F.col("_got").bitwiseXOR(F.col("_fp"))

        both = members.select(key, F.lit(True).alias("_in")).unionByName(absent.select(key, F.lit(False).alias("_in")))

        def agreeing(store=store, differ=differ, both=both):
            got = looked_up(store, both.withColumn("_fp", fingerprint(both, key, store.spec)), key, "_got", filled="_filled")
            same = lambda k: F.col("_filled") & (differ.bitwiseAND(F.lit((1 << k) - 1)) == 0)
            return {r["_in"]: r for r in got.groupBy("_in").agg(F.count("*").alias("n"), *(F.count_if(same(k)).alias(f"k{k}") for k in ks)).collect()}

        counts, probed = _timed(agreeing)
        inside, outside = counts[True], counts[False]
        memory = measures.build_memory(store.spec, n)
        for k in ks:
            # what the smaller store differs in: its payload, and values in the side dictionary
            smaller = with_(store, spec=with_(store.spec, k=k))
            rows.append((name, k, n, measures.space(smaller)["bits_per_key"], measures.probe_cost(smaller)["words"], inside["n"] - inside[f"k{k}"], outside["n"], outside[f"k{k}"], built, probed, memory))
    n = many.count()
    key_bits = many.agg(F.avg(F.octet_length(F.col(key).cast("string"))) * 8).first()[0] or 0.0
    for k in ks:
        made = {
            "exact table": (lambda k=k: many.select(key, F.lit(True).alias("hit")), lambda t, df: baselines.exact_dictionary(t, df, key, "hit", "hit").withColumn("hit", F.coalesce("hit", F.lit(False))), key_bits + k, 1.0),
            "k-fold Bloom": (lambda k=k: baselines.bloom_repeated(many, key, k, n), lambda f, df: baselines.bloom_contains(f, df, key), None, float(k)),
            "shared Bloom": (lambda k=k: baselines.bloom_shared(many, key, k, n), lambda f, df: baselines.bloom_contains(f, df, key), None, float(k)),
            "fingerprint set": (lambda k=k: baselines.fingerprint_set(many, key, k, n), lambda f, df: baselines.fingerprint_contains(f, df, key), k + 2.0, 2.0),
        }
        both = many.select(key, F.lit(True).alias("_in")).unionByName(absent.select(key, F.lit(False).alias("_in")))
        inside = F.col("_in")
        for name, (make, test, bits, words) in made.items():
            if only is not None and name not in only:
                continue
            f, built = _timed(make)
            if bits is None:
                bits = f.bits * (1 if f.shared else k) / max(1, n)
            (missed, tested, hits), probed = _timed(lambda f=f, test=test: test(f, both).agg(F.count_if(inside & ~F.col("hit")), F.count_if(~inside), F.count_if(~inside & F.col("hit"))).first())  # noqa: B023
            rows.append((name, k, n, float(bits), words, missed, tested, hits, built, probed, None))
    return spark.createDataFrame(rows, LADDER)


def false_positives(members: DataFrame, key: str, absent: DataFrame, ks=(1, 2, 4, 8, 12)) -> DataFrame:
    """(k, keys, hits, rate, low, high, expected) of absent keys for filters of the members."""
    rows = []
    for k in ks:
        h, n, lo, hi = measures.fp_rate(contains(build_filter(members, key, k), absent, key))
        rows.append((k, n, h, h / n, lo, hi, 2.0**-k))
    return members.sparkSession.createDataFrame(rows, "k int, keys long, hits long, rate double, low double, high double, expected double")


SPACE = "method string, n long, k int, side long, variables long, payload_bits double, overhead_bits double, bits_per_key double, to_bloom double, file_bytes double, words_read double, operations double, tries_per_system double"


def space(specs: list[tuple[str, DataFrame, str, DictSpec]], value: str = "v") -> DataFrame:
    """SPACE of each (name, df, key, spec)."""
    rows = []
    for name, df, key, spec in specs:
        st = build(df, key, value, spec)
        sp, pc, f = measures.space(st), measures.probe_cost(st), st.facts
        rows.append((name, st.n_keys, spec.k, f["n_side"], f["variables"], float(sp["payload"]), float(sp["overhead"]), sp["bits_per_key"], sp["to_bloom"], float(measures.store_bytes(st)), pc["words"], pc["operations"], f["tries"] / max(1, f["cells"])))
    return specs[0][1].sparkSession.createDataFrame(rows, SPACE)


def prefilter_saving(left: DataFrame, right: DataFrame, on: str, k: int = 8) -> DataFrame:
    """(rows, sent, needed, row_bytes, saved_bytes): what a filter of right's keys keeps from the shuffle of left.

    row_bytes is an unsafe row of left: eight bytes a fixed column and eight for its nulls, and what strings hold.
    """
    keys = right.select(on).distinct()
    store = build_filter(keys.dropna(), on, k)
    strings = [c for c, t in left.dtypes if t in ("string", "binary")]
    width = F.lit(8.0 + 8 * len(left.columns))
    for c in strings:
        width = width + F.coalesce(F.octet_length(c), F.lit(0))
    sent = where_contains(store, left, on).agg(F.count("*").alias("sent"))
    needed = left.join(keys, on, "left_semi").agg(F.count("*").alias("needed"))
    whole = left.agg(F.count("*").alias("rows"), F.avg(width).alias("row_bytes")).first()
    out = left.sparkSession.createDataFrame([(whole["rows"], sent.first()[0], needed.first()[0], float(whole["row_bytes"] or 0.0))], "rows long, sent long, needed long, row_bytes double")
    return out.withColumn("saved_bytes", (F.col("rows") - F.col("sent")) * F.col("row_bytes"))
