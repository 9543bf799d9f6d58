import zlib
from collections import defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from eqdict.llm import packing, token_counts, tokenizing
from eqdict.llm.queries import byte_bpe


@pytest.fixture(scope="module")
def plain():
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(byte_bpe())
    return lambda s: t.encode(s, add_special_tokens=False).ids


def test_fast_ids_equal_the_librarys(plain):
    enc = tokenizing.encoder(byte_bpe())
    assert enc.fast is not None
    chars = [chr(c) for c in [*range(9, 14), *range(0x20, 0x7F), *range(0xA0, 0x250), *range(0x2010, 0x2028), *range(0x2030, 0x205F), 0x20AC]]
    for c in chars:
        for t in (f"ab{c}cd", f" {c}{c} 1{c}", f"'{c} {c}'s", f"{c}  x\n{c}", f"x {c}"):
            assert tokenizing.PLAIN.fullmatch(t) and enc.fast.encode_ordinary(t) == plain(t), ascii(t)
    r = np.random.default_rng(0)
    for _ in range(300):
        t = "".join(r.choice(chars, 60))
        assert enc.ids(t) == plain(t), ascii(t)
    for t in ("a<|endoftext|>b <|endoftext|>", "日本 😀", "a" * 20_000, " " * 20_000, "\x1c\x1d a \u2028 b\u3000c", "e\u0301"):
        assert enc.ids(t) == plain(t)


def test_counts_and_cache(spark, small, edge, empty, plain, tmp_path):
    df, texts = small
    cache = str(tmp_path / "cache")
    got = {r.doc_id: r for r in token_counts.token_counts(df, byte_bpe(), cache).collect()}
    assert {k: (r.n_bytes, r.n_tokens, r.over_limit) for k, r in got.items()} == {k: (len(t.encode()), n := len(plain(t)), n > 512) for k, t in texts.items()}
    stored = spark.read.parquet(cache)
    assert stored.count() == len(set(texts.values())) == stored.select("digest").distinct().count()
    # what is stored is not encoded again, and is what is used
    spark.read.parquet(cache).withColumn("n_tokens", F.col("n_tokens") + 1000).write.parquet(str(tmp_path / "other"))
    again = token_counts.token_counts(df.limit(20), byte_bpe(), str(tmp_path / "other")).collect()
    assert all(r.n_tokens == got[r.doc_id].n_tokens + 1000 for r in again) and spark.read.parquet(str(tmp_path / "other")).count() == stored.count()
    odd = token_counts.token_counts(edge, byte_bpe()).collect()
    assert sorted((r.doc_id or -1, r.n_tokens) for r in odd) == sorted((r.doc_id or -1, len(plain(r.text or ""))) for r in edge.collect())
    assert token_counts.token_counts(empty, byte_bpe()).count() == 0


def check_packing(docs, rows, plain, capacity):
    """Pieces of each text, sequences without gaps; the number of sequences."""
    want = defaultdict(int)
    for d, t in docs:
        ids = np.array([*plain(t or ""), 0], "<u4")
        n = len(ids)
        cuts = [0, n] if n <= capacity else [0, *range(n % capacity or capacity, n + 1, capacity)]
        for i, (a, b) in enumerate(zip(cuts, cuts[1:])):
            want[(d, i, a, b - a, zlib.crc32(ids[a:b].tobytes()))] += 1
    have, places = defaultdict(int), defaultdict(list)
    for r in rows:
        have[(r.doc_id, r.piece, r.start, r.length, r.ids_crc32)] += 1
        places[r.sequence_id].append((r.offset, r.length))
    assert want == have
    for p in places.values():
        at = 0
        for o, n in sorted(p):
            assert o == at
            at += n
        assert at <= capacity
    return len(places)


def test_packing(small, edge, empty, plain):
    df, texts = small
    rows = packing.packed(df, byte_bpe()).collect()
    bound = -(-sum(r.length for r in rows) // 2048)
    assert check_packing(texts.items(), rows, plain, 2048) <= bound + 2
    odd = packing.packed(edge, byte_bpe(), capacity=64).collect()
    check_packing([(r.doc_id, r.text) for r in edge.collect()], odd, plain, 64)
    assert packing.packed(empty, byte_bpe()).count() == 0


def test_one_hot_length(spark, plain):
    docs = spark.range(5000).select(F.col("id").alias("doc_id"), F.when(F.col("id") % 3 == 0, F.lit("same text")).otherwise(F.repeat(F.lit("ab "), F.pmod("id", F.lit(50)).cast("int"))).alias("text"))
    rows = packing.packed(docs, byte_bpe(), capacity=100).collect()
    n = check_packing([(r.doc_id, r.text) for r in docs.collect()], rows, plain, 100)
    assert n <= -(-sum(r.length for r in rows) // 100) * 1.01 + 1


def best_fit_decreasing(counts, capacity):
    plan = packing._Plan(counts, capacity)
    for x in sorted(counts, reverse=True):
        plan.best_fit(x)
    return plan.bins


def test_configurations_are_near_the_least():
    """Sizes that fill sequences exactly take as many as their volume needs; rounding down leaves out a pattern a size at most."""
    stock = [(60, 500), (40, 500), (25, 400)]
    got = packing.configurations(stock, 100)
    held = sum(p * n for p, n in got)
    assert all(p @ np.array([x for x, _ in stock]) <= 100 for p, _ in got) and 597 <= sum(n for _, n in got) <= 600
    assert all(n - h <= 4 * 3 for (_, n), h in zip(stock, held.tolist()))
    worth = np.array([0.6, 0.45, 0.3, 0.27])
    import itertools

    sizes = np.array([60, 45, 30, 26])
    best = max(worth @ p for p in itertools.product(range(2), range(3), range(4), range(4)) if sizes @ p <= 100)
    assert abs(worth @ packing.best_pattern(worth, sizes, 100) - best) < 1e-9


def test_equal_rows_without_identifiers(spark, plain):
    docs = spark.range(3000).select(F.lit(None).cast("long").alias("doc_id"), F.lit("the same short text").alias("text"))
    n = len(plain("the same short text")) + 1
    got = packing.packed(docs, byte_bpe(), capacity=4 * n)
    assert got.groupBy("sequence_id").agg(F.count("*").alias("c"), F.count_distinct("offset").alias("d")).where("c = 4 and d = 4").count() == 750


@pytest.mark.parametrize("seed", range(4))
def test_plan(seed):
    r = np.random.default_rng(seed)
    lengths = np.clip(r.lognormal([3, 4, 5, 6][seed], 1, 3000).astype(int), 1, 512)
    counts = dict(zip(*(x.tolist() for x in np.unique(lengths, return_counts=True))))
    for settings in ((16, 0.2, 0),), ((48, 0.3, 20),), packing.SETTINGS:
        runs, bins = packing.packing_plan(counts, 512, settings)
        free, seen = np.full(bins, 512), defaultdict(list)
        for length, first, n, at, offset in sorted(runs, key=lambda x: x[4]):
            assert (512 - free[at : at + n] == offset).all()
            free[at : at + n] -= length
            seen[length].append((first, n))
        assert (free >= 0).all()
        for length, parts in seen.items():
            at = 0
            for first, n in sorted(parts):
                assert first == at
                at += n
            assert at == counts[length]
        assert set(seen) == set(counts)
    assert bins <= min(-(-lengths.sum() // 512) * 1.03 + 1, best_fit_decreasing(counts, 512) * 1.01 + 1)
    assert packing.packing_plan({}, 512) == ([], 0)


def test_groups_are_as_equal_as_whole_lengths_allow():
    got = packing.linear_groups(dict.fromkeys(range(1, 101), 3), 21, 8)
    assert got == [(x, 30) for x in range(100, 20, -10)]
