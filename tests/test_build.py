"""Stores: every stored key has its value, whatever the method, and everything that should be refused is."""

import json

import pytest
from pyspark.sql import functions as F

from eqdict.operators import measures
from eqdict.operators.build import bad_key_share, bucket_loads, build, choose_h1, encoded, prepared, solved, systems_of
from eqdict.operators.membership import ALPHABET, build_filter, checked_lookup, contains, contains_within1, edit1_variants
from eqdict.operators.probe import looked_up, looked_up_distinct, looked_up_packed, packed
from eqdict.plans.sql import explained, register
from eqdict.sources.keylists import read_keys
from eqdict.sources.store import load
from eqdict.spec import DictSpec
from eqdict.streaming import Tiers, active_sessions, events_stream, first_seen, probe_stream, rebuild_by_batch, run_available, windowed_filters, with_late_keys

METHODS = {
    "two_level": {}, "extra": {"c": 3, "cell_cap": 61}, "side": {"bucket_mean": 100, "bucket_cap": 104, "bad_share": 1.0}, "logsparse": {"kind": "logsparse", "seed_tries": 256}, "local": {"kind": "local", "seed_tries": 256},
    "sparse_rows": {"kind": "sparse", "t": 5, "seed_tries": 256}, "table": {"hashing": "table", "bucket_mean": 200, "bucket_cap": 400}, "listed": {"solver": "listed", "cell_mean": 1.5, "cell_cap": 4, "bucket_mean": 64},
    "shared": {"method": "shared_inverse", "cell_mean": 2.5, "cell_cap": 6, "bucket_mean": 64}, "full_cells": {"field": "full", "cell_mean": 8, "cell_cap": 20}, "one_level": {"method": "one_level", "bucket_mean": 50, "bucket_cap": 100},
    "dense": {"method": "dense"}, "dense_full": {"method": "dense", "field": "full", "c": 1, "n": 60}, "sparse": {"method": "sparse", "slack": 1.3}, "replace": {"method": "sparse", "slack": 1.4, "replace": True},
    "local_planes": {"kind": "local", "window": 40, "seed_tries": 256}, "global": {"method": "global_sparse", "n": 300}, "krylov": {"method": "global_sparse", "solver": "krylov", "n": 200}, "dedupe": {"pre_dedupe": True},
}


def table(spark, n, k, start=0):
    return spark.range(start, start + n).select(F.col("id").alias("key"), F.pmod(F.xxhash64(F.lit(5), "id"), F.lit(1 << k)).alias("v"))


def wrong(store, df, **how):
    return looked_up(store, df, "key", **how).where("value is null or value <> v").count()


@pytest.mark.parametrize("k", [1, 5])
@pytest.mark.parametrize("name", METHODS)
def test_every_stored_key_has_its_value(spark, name, k):
    how = dict(METHODS[name])
    df = table(spark, how.pop("n", 900), k)
    store = build(df, "key", "v", DictSpec(k=k, **how))
    assert wrong(store, df) == 0
    f = store.facts
    assert f["n_keys"] == df.count()
    if store.spec.method == "two_level" and not store.spec.c:
        assert f["variables"] == f["n_keys"] - f["n_side"]
    if name == "side":
        assert f["n_side"] > 0
    if name == "listed":
        assert wrong(store, df, evaluator="table") == 0
    again = load(spark, store.path)
    assert again.spec == store.spec and wrong(again, df) == 0


@pytest.mark.parametrize("k", [1, 3, 4])
def test_cells_by_listed_matrices_over_the_field(spark, k):
    df = table(spark, 900, k)
    store = build(df, "key", "v", DictSpec(k=k, field="full", solver="listed", cell_mean=0.7, cell_cap=2, bucket_mean=8))
    assert wrong(store, df) == 0 and store.facts["n_side"] < 90


@pytest.mark.parametrize("k", [2, 8, 12, 32])
def test_wide_values(spark, k):
    df = table(spark, 700, min(k, 31))
    assert wrong(build(df, "key", "v", DictSpec(k=k)), df) == 0


@pytest.mark.parametrize("n", [0, 1, 2, 63, 64, 65])
def test_small_numbers_of_keys(spark, n):
    df = table(spark, n, 3)
    for spec in (DictSpec(k=3), DictSpec(k=3, cell_mean=64, cell_cap=64, seed_tries=200)):
        store = build(df, "key", "v", spec)
        assert wrong(store, df) == 0 and looked_up(store, table(spark, 20, 3, 10**6), "key").where("value is null").count() == 0
    f = build_filter(df, "key", 4)
    assert contains(f, df, "key").where("not hit").count() == 0


def test_packed_layout(spark):
    df = table(spark, 3000, 6)
    for how in ({}, {"hashing": "table", "bucket_mean": 200, "bucket_cap": 400}, {"bucket_mean": 300, "bucket_cap": 301, "bad_share": 1.0}, {"kind": "local", "window": 10, "seed_tries": 256}):
        store = build(df, "key", "v", DictSpec(k=6, **how))
        p = packed(store)
        got = looked_up_packed(store, p, df, "key")
        assert got.where("value is null or value <> v").count() == 0
        bits = p.agg(F.sum(F.octet_length("payload") * 8)).first()[0]
        assert store.facts["variables"] * 6 <= bits <= store.facts["variables"] * 6 + 8 * p.count()


def test_same_store_whatever_the_partitions(spark):
    df = table(spark, 2500, 4)
    rows = [sorted(map(str, build(x, "key", "v", DictSpec(k=4, bucket_mean=256)).buckets.collect())) for x in (df.repartition(1), df.repartition(7), df.orderBy(F.desc("key")))]
    assert rows[0] == rows[1] == rows[2]


def test_conflicts_nulls_and_ranges(spark):
    df = spark.createDataFrame([("a", 1), ("a", 1), ("b", 3), ("b", 2), ("", 0), ("é", 4), ("ç", 5), ("x" * 100_000, 6)], "key string, v int")
    with pytest.raises(Exception, match="several values"):
        build(df, "key", "v", DictSpec(k=3))
    for policy, want in (("min", 2), ("max", 3)):
        store = build(df, "key", "v", DictSpec(k=3, on_conflict=policy))
        got = {r.key: r.value for r in looked_up(store, df, "key").collect()}
        assert got["b"] == want and got["a"] == 1 and got["é"] == 4 and got["x" * 100_000] == 6
    one = df.where("key <> 'b'")
    with pytest.raises(Exception, match="key is null"):
        build(one.union(spark.createDataFrame([(None, 1)], df.schema)), "key", "v", DictSpec(k=3))
    nulls = one.union(spark.createDataFrame([(None, 1)], df.schema))
    store = build(nulls, "key", "v", DictSpec(k=3, on_null="drop"))
    assert [r.value for r in looked_up(store, nulls, "key").where("key is null").collect()] == [None]
    for bad in ((8,), (-1,), (None,)):
        with pytest.raises(Exception, match="value"):
            build(spark.createDataFrame([("k", *bad)], "key string, v int"), "key", "v", DictSpec(k=3))


def test_types_of_keys(spark):
    df = spark.range(200).select(F.col("id").cast("int").alias("key"), F.pmod("id", F.lit(7)).alias("v"))
    store = build(df, "key", "v", DictSpec(k=3))
    assert wrong(store, df.withColumn("key", F.col("key").cast("long"))) == 0
    with pytest.raises(TypeError):
        looked_up(store, df.withColumn("key", F.col("key").cast("string")), "key")
    for kind in ("double", "string", "date", "timestamp", "binary", "decimal(9,2)", "array<double>", "struct<a:int,b:string>", "boolean"):
        c = {"date": F.date_add(F.lit("2020-01-01").cast("date"), F.col("key")), "timestamp": F.timestamp_seconds("key"), "binary": F.col("key").cast("string").cast("binary"), "array<double>": F.array(F.col("key") * 0.5, F.lit(1.0)), "struct<a:int,b:string>": F.struct(F.col("key").alias("a"), F.lit("z").alias("b")), "boolean": F.col("key") == 0}.get(kind, F.col("key").cast(kind))
        typed = df.where("key < 2" if kind == "boolean" else "true").select(c.alias("key"), "v")
        assert wrong(build(typed, "key", "v", DictSpec(k=3)), typed) == 0, kind
    floats = spark.createDataFrame([(0.0, 1), (float("nan"), 2), (1.5, 3)], "key double, v int")
    s = build(floats, "key", "v", DictSpec(k=2))
    assert sorted(r.value for r in looked_up(s, spark.createDataFrame([(-0.0,), (float("nan"),), (1.5,)], "key double"), "key").collect()) == [1, 2, 3]
    with pytest.raises(TypeError):
        build(spark.createDataFrame([({"a": 1}, 1)], "key map<string,int>, v int"), "key", "v", DictSpec(k=2))
    two = df.select("key", (F.col("key") + 1).alias("b"), "v")
    s = build(two, ["key", "b"], "v", DictSpec(k=3))
    assert looked_up(s, two, ["key", "b"]).where("value <> v").count() == 0


def test_digests(spark):
    df = table(spark, 500, 3)
    assert wrong(build(df, "key", "v", DictSpec(k=3, digest="identity")), df) == 0
    text = df.select(F.col("key").cast("string").alias("key"), "v")
    assert wrong(build(text, "key", "v", DictSpec(k=3, digest="md5")), text) == 0
    with pytest.raises(TypeError):
        build(text, "key", "v", DictSpec(k=3, digest="identity"))


def test_halves_of_digests_that_collide(spark):
    """Equal low or high halves are still different keys; equal digests with other values are a conflict."""
    rows = [(i // 2, i % 2 + 10 * (i // 20), i % 8) for i in range(200)]
    data = spark.createDataFrame(rows, "key_hi long, key_lo long, value long").dropDuplicates(["key_hi", "key_lo"])
    got = solved(data, DictSpec(k=3), 1, 0, data.count())
    assert got.agg(F.sum("n_keys")).first()[0] == data.count()
    with pytest.raises(Exception, match="several values"):
        solved(data.union(data.withColumn("value", (F.col("value") + 1) % 8)), DictSpec(k=3), 1, 0, 10).collect()


def test_refusals(spark):
    df = table(spark, 200, 3)
    for bad in ({"method": "nope"}, {"k": 0}, {"k": 33}, {"cell_cap": 65}, {"solver": "listed"}, {"method": "global_sparse", "t": 4}, {"method": "sparse", "t": 2}, {"hashing": "table", "method": "dense"}):
        with pytest.raises(ValueError):
            DictSpec(**({"k": 3} | bad))
    with pytest.raises(ValueError, match="at most"):
        build(df, "key", "v", DictSpec(k=3, method="dense", most_single=100))
    store = build(df, "key", "v", DictSpec(k=3))
    with pytest.raises(NotImplementedError):
        store.insert(1, 2)
    with pytest.raises(ValueError, match="not a filter"):
        contains(store, df, "key")
    with pytest.raises(ValueError, match="version"):
        DictSpec.from_json(json.dumps(json.loads(store.spec.to_json()) | {"format": 99}))


def test_one_exchange_to_build_and_none_to_probe(spark):
    df = spark.range(3000).select(F.col("id").alias("key"), (F.col("id") % 8).alias("v"))
    spec = DictSpec(k=3, bucket_mean=512, pre_dedupe=False)
    plan = solved(prepared(df, "key", "v", spec), spec, 4, 0, 3000)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1
    store = build(df, "key", "v", spec)
    plan = looked_up(store, df, "key")._jdf.queryExecution().executedPlan().toString()
    assert "Exchange hashpartitioning" not in plan and "BroadcastHashJoin" in plan and "Python" not in plan and "Arrow" not in plan


def test_bucket_hash_is_redrawn_before_a_store_is_committed(spark, tmp_path):
    """Buckets at the cap: the first hash that leaves few enough keys counts, for a named path too; if none does, nothing is there."""
    df, path = table(spark, 3000, 3), str(tmp_path / "s")
    spec = DictSpec(k=3, bucket_mean=100, bucket_cap=118)
    data = prepared(df, "key", "v", spec)
    shares = [bad_key_share(bucket_loads(data, spec, 30, s), spec.cap)[0] for s in range(8)]
    limit = (sorted(shares)[1] + 0.5) / 3000
    want = next(s for s, bad in enumerate(shares) if bad <= limit * 3000)
    store = build(df, "key", "v", DictSpec(k=3, bucket_mean=100, bucket_cap=118, bad_share=limit), path=path)
    assert store.h1_seed == want and store.facts["bad_keys"] == shares[want] and load(spark, path).h1_seed == want and wrong(load(spark, path), df) == 0
    with pytest.raises(RuntimeError, match="overfull"):
        build(df, "key", "v", DictSpec(k=3, bucket_mean=100, bucket_cap=60), path=str(tmp_path / "none"))
    assert not (tmp_path / "none" / "manifest").exists()
    assert choose_h1(data, spec, 30, limit * 3000) == want


def test_frequent_keys_meet_before_they_move(spark):
    often = spark.range(3000).select(F.when(F.col("id") % 3 == 0, 7).otherwise(F.col("id")).alias("key"), F.lit(1).alias("v"))
    assert build(often, "key", "v", DictSpec(k=1)).spec.pre_dedupe and not build(spark.range(3000).select(F.col("id").alias("key"), F.lit(1).alias("v")), "key", "v", DictSpec(k=1)).spec.pre_dedupe
    assert build(often, "key", "v", DictSpec(k=1), n_rows=3000).n_keys == 2000


def test_bucket_hash_leaves_few_keys_in_overfull_buckets(spark):
    for digest in ("xxhash", "identity"):
        spec = DictSpec(k=1, digest=digest, bucket_cap=80)
        data = prepared(table(spark, 4000, 1), "key", "v", spec)
        shares = [bad_key_share(bucket_loads(data, spec, 100, s), spec.cap) for s in range(6)]
        assert sum(bad <= n / 12**2 for bad, n in shares) >= 3


def test_space(spark):
    df = table(spark, 100_000, 8)
    for k in (1, 4, 8):
        s = measures.space(build(df.withColumn("v", F.pmod("v", F.lit(1 << k))), "key", "v", DictSpec(k=k)))
        assert s["payload"] == k * 100_000 and s["to_bloom"] < 1
    long_keys = table(spark, 500, 4).select(F.lpad(F.col("key").cast("string"), 800, "0").alias("key"), "v")
    short = table(spark, 500, 4).select(F.col("key").cast("string").alias("key"), "v")
    a, b = (measures.space(build(x, "key", "v", DictSpec(k=4)))["payload"] for x in (long_keys, short))
    assert a == b == 2000
    costs = [measures.probe_cost(build(table(spark, n, 3), "key", "v", DictSpec(k=3)))["words"] for n in (200, 2000)]
    assert costs[0] == costs[1] == 5


@pytest.mark.parametrize("k", [1, 2, 4, 8])
def test_false_positives(spark, k):
    members, absent = table(spark, 3000, 1), table(spark, 20_000, 1, 10**9)
    for how in ({}, {"digest": "identity"}, {"hashing": "table", "bucket_mean": 200, "bucket_cap": 400}):
        f = build_filter(members, "key", k, **how)
        assert contains(f, members, "key").where("not hit").count() == 0
        hits, n, low, high = measures.fp_rate(contains(f, absent, "key"))
        assert n == 20_000 and low <= 2.0**-k <= high


def test_empty_cells_answer_no(spark):
    few = table(spark, 3, 1)
    strict, plain = build_filter(few, "key", 1, bucket_mean=1, cell_mean=1), build_filter(few, "key", 1, bucket_mean=1, cell_mean=1, strict_empty=False)
    absent = table(spark, 4000, 1, 10**6)
    assert contains(strict, absent, "key").where("hit").count() < contains(plain, absent, "key").where("hit").count()


def test_answers_to_absent_keys_are_even(spark):
    store = build(table(spark, 5000, 3), "key", "v", DictSpec(k=3))
    counts = [r.n for r in measures.nonmember_histogram(store, table(spark, 40_000, 3, 10**9), "key").collect()]
    assert measures.chi_square(counts, 8) < 40


def test_checked_lookup(spark):
    df = table(spark, 800, 4)
    _, probe = checked_lookup(df, "key", "v", 4, 10)
    assert probe(df).where("value is null or value <> v").count() == 0
    assert probe(table(spark, 5000, 4, 10**7)).where("value is not null").count() < 25


def test_distinct_lookup_and_codebook(spark, sf):
    df = table(spark, 300, 3)
    store = build(df, "key", "v", DictSpec(k=3))
    hot = df.union(df.where("key = 7").crossJoin(spark.range(500)).select("key", "v")).union(spark.createDataFrame([(None, 0)], "key long, v long"))
    got = looked_up_distinct(store, hot, "key")
    assert got.count() == 801 and got.where("value <> v").count() == 0 and got.where("key is null and value is null").count() == 1
    orders = spark.read.parquet(f"{sf}/orders.parquet").select("o_orderkey", "o_orderstatus")
    book, coded = encoded(orders, "o_orderstatus")
    s = build(coded, "o_orderkey", "_code", DictSpec(k=2))
    back = looked_up(s, orders, "o_orderkey", "code").join(book, "code")
    assert back.where("label <> o_orderstatus").count() == 0 and back.count() == orders.count()


def test_edits(spark):
    words = ["abc", "hello", "x"]
    df = spark.createDataFrame([(w,) for w in ["abc", "abd", "ac", "abxc", "hello", "helo", "hexyo", "zzz", "", None]], "word string")
    f = build_filter(spark.createDataFrame([(w,) for w in words], "word string"), "word", 16)
    got = {r.word: r.hit for r in contains_within1(f, df, "word").collect()}
    assert all(got[w] for w in ("abc", "abd", "ac", "abxc", "hello", "helo", "")) and got["hexyo"] is False and got["zzz"] is False and got[None] is None
    n = spark.createDataFrame([("ab",)], "w string").select(F.size(edit1_variants(F.col("w")))).first()[0]
    a = len(ALPHABET)
    assert n == 1 + (3 * a - 2) + 2 + 2 * (a - 1)


def test_sql_surface(spark):
    df = table(spark, 400, 3)
    store = build(df, "key", "v", DictSpec(k=3, digest="identity"))
    register(spark, store, "mine")
    assert spark.sql("SELECT sum(m) FROM mine_cells").first()[0] == 400 - spark.sql("SELECT count(*) FROM mine_side").first()[0]
    assert spark.sql("SELECT count(*) FROM edit1('ab')").first()[0] == spark.createDataFrame([("ab",)], "w string").select(F.size(edit1_variants(F.col("w")))).first()[0]
    assert spark.sql("SELECT * FROM equation_theory(1000, 8)").count() == 9
    for key in (0, 17, 399):
        steps = dict(explained(store, key, 0))
        assert int(steps["answer"]) == df.where(f"key = {key}").first()["v"]


def test_sources(spark, tmp_path):
    (tmp_path / "words.txt").write_text("one\ntwo\ntwo\n")
    words = read_keys(spark, str(tmp_path / "words.txt"), format="text")
    assert contains(build_filter(words, "value", 8), words, "value").where("hit").count() == 3
    table(spark, 20, 2).write.orc(str(tmp_path / "o"))
    table(spark, 20, 2).write.json(str(tmp_path / "j"))
    assert read_keys(spark, str(tmp_path / "o"), ["key"], "orc").columns == ["key"] and read_keys(spark, str(tmp_path / "j"), format="json", schema="key long").count() == 20


def test_streams(spark, sf):
    events = spark.read.parquet(f"{sf}/events.parquet")
    users = events.where("user_id % 3 = 0").select("user_id").distinct()
    f = build_filter(users, "user_id", 8)
    stream = events_stream(spark, sf, events.schema)
    got = run_available(probe_stream(f, stream.select("event_id", "user_id"), "user_id", "hit"), "probe")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, contains(f, events.select("event_id", "user_id"), "user_id").collect()))
    days = run_available(windowed_filters(stream, "ts", "user_id"), "days")
    exact = events.groupBy(F.window("ts", "1 day").start.alias("start"), "user_id").count()
    assert 0 < days.count() <= exact.count() and days.join(exact, ["start", "user_id"]).where("n <> count").count() == 0


def test_stores_by_day(spark, sf, tmp_path):
    events = spark.read.parquet(f"{sf}/events.parquet")
    stream = events_stream(spark, sf, events.schema).where("ts < timestamp_ntz '2024-01-04'")
    for _ in range(2):  # the second run finds nothing new
        rebuild_by_batch(stream, str(tmp_path / "days"), F.to_date("ts"), "user_id").awaitTermination()
    for day in ("2024-01-01", "2024-01-03"):
        store = load(spark, str(tmp_path / "days" / day / "batch-0"))
        users = events.where(F.to_date("ts") == day).select("user_id").distinct()
        assert users.count() == store.n_keys and contains(store, users, "user_id").where("not hit").count() == 0


def test_tiers(spark):
    t = Tiers("key", 10)
    assert t.contains(table(spark, 5, 1)).where("hit").count() == 0
    for start in (0, 1000, 500):
        t.add_batch(table(spark, 700, 1, start))
    everything = table(spark, 1700, 1)
    assert t.contains(everything).where("not hit").count() == 0
    t.compact()
    assert len(t.tiers) == 1 and t.contains(everything).where("not hit").count() == 0 and t.tiers[0].n_keys == 1700
    assert t.contains(table(spark, 3000, 1, 10**8)).where("hit").count() < 20


def test_data_source(spark, tmp_path):
    from eqdict.sources import datasource

    datasource.register(spark)
    store = build(table(spark, 500, 3), "key", "v", DictSpec(k=3, bucket_mean=128), path=str(tmp_path / "s"))
    got = spark.read.format("eqdict").option("path", str(tmp_path / "s")).load()
    assert got.agg(F.sum("m")).first()[0] == store.facts["variables"] and got.count() == store.facts["cells"]
    with pytest.raises(Exception, match="manifest"):
        spark.read.format("eqdict").option("path", str(tmp_path)).load().collect()


def test_fluent_surface(spark, tmp_path):
    from eqdict.api import dictionary, opened

    df = table(spark, 300, 3)
    d = dictionary(df).key("key").value("v").bits(3).method("two_level").option(bucket_mean=128).write(str(tmp_path / "d"))
    again = opened(spark, str(tmp_path / "d"))
    assert d.verify(df, "key", value="v") == again.verify(df, "key", value="v") == 0
    assert again.lookup(df, "key", distinct=True).where("value <> v").count() == 0 and again.space()["payload"] == 900 and again.describe()["n_keys"] == 300
    f = dictionary(df).key("key").bits(10).write()
    assert f.where_contains(df, "key").count() == 300 and f.contains(df, "key").where("hit").count() == 300
    again.views("fluent")
    with pytest.raises(NotImplementedError):
        f.insert(1)
    with pytest.raises(ValueError):
        dictionary(df).write()


def test_late_keys(spark):
    df, late = table(spark, 400, 3), spark.createDataFrame([(5, 6), (10**6, 3)], "key long, v long")
    store = with_late_keys(build(df, "key", "v", DictSpec(k=3)), late, "key", "v")
    got = {r.key: r.value for r in looked_up(store, df.select("key").union(late.select("key")), "key").collect()}
    assert got[5] == 6 and got[10**6] == 3 and all(got[r.key] == r.v for r in df.where("key <> 5").collect())
    f = with_late_keys(build_filter(df, "key", 12), late, "key")
    assert contains(f, late, "key").where("not hit").count() == 0


def test_sessions_and_first_seen(spark, sf):
    events = spark.read.parquet(f"{sf}/events.parquet")
    stream = events_stream(spark, sf, events.schema)
    sessions = run_available(active_sessions(stream, "ts", "user_id", "2 hours"), "sessions")
    assert 0 < sessions.agg(F.sum("n")).first()[0] <= events.count()
    seen = run_available(first_seen(stream.select("ts", "user_id"), "ts", "user_id"), "seen")
    assert seen.select("user_id").distinct().count() == events.select("user_id").distinct().count() <= seen.count() <= events.count()


@pytest.mark.parametrize(
    ("n", "how"),
    [(9000, {"method": "dense"}), (9000, {"method": "dense", "c": 2}), (4200, {"method": "dense", "field": "full"}), (20_100, {"method": "sparse", "slack": 1.3}), (20_100, {"method": "global_sparse"}), (8200, {"method": "global_sparse", "solver": "krylov"}), (4100, {"method": "global_sparse", "solver": "block"})],
)
def test_more_keys_than_one_system_may_have(spark, n, how):
    """They make several systems, each of the method asked for, and every key returns its value."""
    df = spark.range(n).select(F.col("id").alias("key"), (F.col("id") % 8).alias("v"))
    store = build(df, "key", "v", DictSpec(k=3, **how))
    assert store.n_keys == n and store.facts["n_side"] == 0 and store.facts["cells"] == store.n_buckets > 1
    assert looked_up(store, df, "key").where("value = v").count() == n


def test_field_systems_are_small_beyond_a_thousand_keys():
    """A probe over the field computes a product for each variable."""
    spec = DictSpec(k=5, method="dense", field="full")
    assert [systems_of(spec, n) for n in (1000, 1024, 1025, 6000)] == [1, 1, 5, 24]


def test_store_of_few_bytes_on_disk_is_not_broadcast_beyond_its_size(spark, monkeypatch):
    """Spark would broadcast what its files say is small; what rows hold in memory decides."""
    from eqdict.operators import probe

    df = spark.range(3000).select(F.col("id").alias("key"), (F.col("id") % 2).alias("v"))
    store = build(df, "key", "v", DictSpec(k=3, bucket_mean=512, bucket_cap=520, bad_share=1.0))
    assert store.facts["n_side"]
    plan = lambda: looked_up(store, df, "key")._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan()
    monkeypatch.setattr(probe, "BROADCAST_BYTES", 0)
    assert "Broadcast" not in plan()
    assert looked_up(store, df, "key").where("value = v").count() == 3000


def test_answer_table_is_one_constant(spark):
    df = spark.range(500).select(F.col("id").alias("key"), (F.col("id") % 8).alias("v"))
    store = build(df, "key", "v", DictSpec(k=3, solver="listed", cell_mean=1.5, cell_cap=4, bucket_mean=32))
    got = looked_up(store, df, "key", evaluator="table")
    assert len(got._jdf.queryExecution().analyzed().toString()) < 1_000_000
    assert got.where("value = v").count() == 500
