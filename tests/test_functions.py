import numpy as np
import pytest
from pyspark.sql import functions as F

from eqdict.functions import gf, hashing, rows, theory


def digests(n, seed=3):
    r = np.random.default_rng(seed)
    return r.integers(-(2**63), 2**63, n, dtype=np.int64), r.integers(-(2**63), 2**63, n, dtype=np.int64)


@pytest.mark.parametrize("k", [1, 2, 3, 4])
def test_field_axioms(k):
    f, a = gf.field(k), np.arange(1 << k)
    x, y = np.meshgrid(a, a)
    assert (f.mul(x, y) == f.mul(y, x)).all() and (f.mul(a, 1) == a).all()
    for c in a:
        assert (f.mul(c, x ^ y) == f.mul(c, x) ^ f.mul(c, y)).all()
        assert (f.mul(f.mul(x, y), c) == f.mul(x, f.mul(y, c))).all()
    assert (f.mul(a[1:], f.inv(a[1:])) == 1).all()
    with pytest.raises(ZeroDivisionError):
        f.inv(0)


def test_all_polynomials_are_primitive():
    for k in range(1, 17):
        f = gf.Field(k)
        assert len(set(f.exp[: f.q - 1].tolist())) == f.q - 1


@pytest.fixture(scope="module")
def frame(spark):
    hi, lo = digests(4000)
    m = np.arange(4000) % 65
    return spark.createDataFrame([(int(a), int(b), int(c)) for a, b, c in zip(hi, lo, m)], "hi long, lo long, m long"), hi, lo, m


def test_rows_are_equal_in_numpy_and_columns(frame):
    df, hi, lo, m = frame
    got = df.select("m", *(rows.mask_row(F.lit(9), F.col("hi"), F.col("lo"), F.col("m"), k, t=5).alias(k) for k in rows.KINDS)).toPandas()
    for k in rows.KINDS:
        mine = rows.masks_np(9, hi, lo, m, k, t=5)
        assert (mine.view(np.int64) == got[k].to_numpy()).all()
        assert (np.bitwise_count(mine & ~rows.mask_np(m)) == 0).all()


def test_hashes_are_equal_in_numpy_and_columns(frame):
    df, hi, lo, m = frame
    h, f = hashing.TableHash(1000, 6, 4), F.pmod("m", F.lit(6))
    got = df.select(
        F.xxhash64(hashing.long(77), "hi", "lo").alias("x"), hashing.limb_affine(F.col("hi"), F.col("lo"), 5, 333).alias("l"),
        hashing.gf2_affine(F.col("hi"), F.col("lo"), 5, 16).alias("g"), h.index(f, F.col("hi"), F.col("lo")).alias("t"),
    ).toPandas()
    assert (hashing.xxhash64_np(77, hi, lo).view(np.int64) == got.x.to_numpy()).all()
    assert (hashing.limb_affine_np(hi, lo, 5, 333) == got.l.to_numpy()).all()
    assert (hashing.gf2_affine_np(hi, lo, 5, 16) == got.g.to_numpy()).all()
    for i in range(6):
        assert (h.index_np(i, hi, lo) == got.t.to_numpy())[m % 6 == i].all()


def test_field_products_are_equal_in_numpy_and_columns(spark):
    f = gf.field(4)
    got = spark.range(256).select((F.col("id") % 16).alias("a"), F.floor(F.col("id") / 16).alias("b")).withColumn("p", gf.gf_mul(F.col("a"), F.col("b"), 4)).toPandas()
    assert (f.mul(got.a.to_numpy(), got.b.to_numpy()) == got.p.to_numpy()).all()


def test_pairwise_families_are_even():
    hi, lo = np.arange(20000, dtype=np.int64), np.zeros(20000, np.int64)
    for seed in range(5):
        c = np.bincount(hashing.limb_affine_np(hi, lo, seed, 50), minlength=50)
        assert ((c - 400) ** 2 / 400).sum() < 110
        g = np.bincount(hashing.gf2_affine_np(hi, lo, seed, 4), minlength=16)
        assert g.max() < 20000


def test_row_weights():
    hi, lo = digests(2000)
    assert set(np.bitwise_count(rows.masks_np(1, hi, lo, 40, "sparse", t=4)).tolist()) == {4}
    assert all(rows.odd_log(m) % 2 == 1 and rows.odd_log(m) <= m for m in range(1, 65))
    local = rows.masks_np(1, hi, lo, 60, "local", window=12)
    spread = [int(x).bit_length() - (int(x) & -int(x)).bit_length() for x in local if x]
    assert max(spread) < 12


def test_theory():
    assert theory.independence_bound(1, 0) == 0
    for (k, c), want in {(1, 0): 0.2888, (1, 1): 0.5776, (1, 2): 0.7701, (2, 0): 0.6885, (8, 0): 0.9961}.items():
        exact = theory.independence_exact(k, 64, c)
        assert abs(exact - want) < 1e-4 and exact >= theory.independence_bound(k, c)
    assert abs(theory.bloom_bits(10**8) - 1.4427e8) < 1e4
    assert [theory.bits_for_error(e) for e in (0.5, 0.25, 0.1, 2**-8)] == [1, 2, 4, 8]
    p = theory.PaperParams(10**9, 8)
    assert p.cell_cap < 2 and p.bucket_cap > p.bucket_mean
    assert [round(theory.no_collision(s, s * s), 3) for s in (3, 4, 5, 6)] == [0.691, 0.667, 0.653, 0.644]
    with pytest.raises(ValueError):
        theory.slack_for(2)


def test_wide_affine_hash(spark):
    r = np.random.Generator(np.random.PCG64(9))
    a, b = int(r.integers(1, hashing.P61)), int(r.integers(0, hashing.P61))
    x = [0, 1, -1, 7, 2**62, -(2**63), 2**63 - 1, 123456789012345]
    got = [tuple(v) for v in spark.createDataFrame([(v,) for v in x], "x long").select("x", hashing.affine61(F.col("x"), 9, 1000)).collect()]
    assert got == [(v, (a * (v % hashing.P61) + b) % hashing.P61 % 1000) for v in x]
