"""Operators whose rows SQL can express, on the given tables and on odd ones."""

import re

import duckdb
import pytest
from pyspark.sql import functions as F

from eqdict.llm import exact_dedup, mixing, url_filter
from eqdict.llm.queries import ORACLES, QUERIES
from tests.test_queries import SF, rows_of, views


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_query_matches_sql(spark, name):
    got = QUERIES[name](spark, SF)
    c = views(SF).execute(ORACLES[name])
    assert sorted(got.columns) == sorted(d[0] for d in c.description)
    assert rows_of(got.columns, got.collect()) == rows_of([d[0] for d in c.description], c.fetchall())


def in_duckdb(name, sql, df):
    c = duckdb.connect()
    c.register(name, df.toArrow())
    r = c.execute(sql)
    return [d[0] for d in r.description], r.fetchall()


def test_exact_groups_on_odd_rows(edge):
    got = {(r.doc_id, r.text_sha256): r for r in exact_dedup.exact_groups(edge).collect()}
    all_ = exact_dedup.exact_groups(edge).collect()
    assert len(all_) == edge.count()
    by = {r.doc_id: r for r in all_ if r.doc_id is not None}
    assert (by[2].keep_id, by[2].group_size, by[2].kept) == (1, 3, False)
    assert by[3].text_sha256 == by[4].text_sha256 and by[5].text_sha256 != by[4].text_sha256
    assert by[4].keep_id == 3 and by[4].group_size == 3 and by[7].keep_id == 6 and by[8].group_size == 2 and by[8].kept
    assert len(got) == edge.count() - 1


def test_exact_distinct_keeps_one_row_of_each_text(edge, empty):
    got = exact_dedup.exact_distinct(edge)
    assert got.columns == edge.columns
    assert sorted(r.doc_id for r in got.collect()) == [1, 3, 5, 6, 8, 9, 10, 11]
    assert exact_dedup.exact_distinct(empty).count() == 0 and exact_dedup.exact_groups(empty).count() == 0


@pytest.mark.parametrize("runs", [1, 2, 7, 500])
def test_rounds_do_not_matter(small, runs):
    df, _ = small
    want = sorted(map(tuple, exact_dedup.exact_groups(df).collect()))
    assert sorted(map(tuple, exact_dedup.exact_groups(df.repartition(13), runs=runs).collect())) == want


def test_leaf_runs_are_sorted_and_have_one_entry_a_text(spark, small, tmp_path):
    import glob

    import pyarrow.parquet as pq

    rows = exact_dedup.with_digest(small[0].repartition(9), "doc_id", "text")
    exact_dedup.leaf_runs(rows, 4, str(tmp_path / "runs"))
    seen, total = set(), 0
    for f in glob.glob(f"{tmp_path}/runs/*.parquet"):
        t = pq.read_table(f)
        keys = list(zip(t.column("_run").to_pylist(), t.column("_digest").to_pylist()))
        assert keys == sorted(keys) and not seen & set(keys)
        seen |= set(keys)
        total += sum(t.column("size").to_pylist())
    assert total == small[0].count() and {r for r, _ in seen} == {0, 1, 2, 3}


def test_entries_must_agree_in_all_parts_of_their_key(spark, tmp_path):
    rows = [(1, b"d", b"x", 3), (2, b"d", b"x", 3), (0, b"d", b"y", 3), (3, b"d", b"x", 4)]
    df = spark.createDataFrame(rows, "_id long, _digest binary, _check binary, _bytes int").repartition(3)
    got = {(bytes(r._check), r._bytes): (r.keep_id, r.group_size) for r in exact_dedup.merged_runs(df, str(tmp_path / "r"), 4).collect()}
    assert got == {(b"x", 3): (1, 2), (b"y", 3): (0, 1), (b"x", 4): (3, 1)}


def test_null_identifiers_alone(spark):
    df = spark.createDataFrame([(None, "a b"), (None, "a  b")], "doc_id long, text string")
    rows = exact_dedup.exact_groups(df).collect()
    assert all(r.kept and r.keep_id is None and r.group_size == 2 for r in rows)
    assert exact_dedup.exact_distinct(df).count() == 1


URLS = [
    ("http://a.example.net/en/x?q#f", "a.example.net", "/en/x", "example.net/en/", "allow"),
    ("HTTP://EXAMPLE.NET/EN/x", "example.net", "/EN/x", "net/", "block"),
    ("x://example.com/de/", "example.com", "/de/", "example.com/de/", "block"),
    ("https://badexample.com/de/", "badexample.com", "/de/", None, "allow"),
    ("https://w.org/fr/?a", "w.org", "/fr/", "org/fr/", "allow"),
    ("https://w.net", "w.net", "", None, "allow"),
    ("https://w.net?/", "w.net", "", None, "allow"),
    ("https://net/", "net", "/", "net/", "block"),
    (None, "", "", None, "allow"),
    ("", "", "", None, "allow"),
    ("w.net/en/", "", "", None, "allow"),
    ("http://ads.w.com/", "ads.w.com", "/", None, "block"),
    ("http://w.com/a\nb/login", "w.com", "/a\nb/login", None, "block"),
    ("http://É.W.org/fr/é", "É.w.org", "/fr/é", "org/fr/", "allow"),
    ("http://" + "a." * 5000 + "net/" + "p/" * 5000, "a." * 5000 + "net", "/" + "p/" * 5000, "net/", "block"),
]


@pytest.mark.parametrize("most", [1000, 0])
def test_urls(spark, monkeypatch, most):
    monkeypatch.setattr(url_filter, "MOST_INLINE_RULES", most)
    pages = spark.createDataFrame([(i, u[0], "x", 1) for i, u in enumerate(URLS)] + [(0, URLS[0][0], "y", 2)], "page_id long, url string, rule string, _tokens int")
    got = url_filter.judge(pages, url_filter.rule_table(spark)).collect()
    assert len(got) == len(URLS) + 1
    for r in got:
        assert (r.host, r.path, r.rule, r.verdict) == URLS[r.page_id][1:], URLS[r.page_id][0][:80]
    assert url_filter.judge(pages.limit(0), url_filter.rule_table(spark)).count() == 0


@pytest.mark.parametrize("most", [1000, 0])
def test_every_general_rule_runs_where_it_matches(spark, monkeypatch, most):
    """As if all patterns ran on all URLs, whatever their optional parts hold."""
    monkeypatch.setattr(url_filter, "MOST_INLINE_RULES", most)
    hosts = [f"{a}spam{b}farm{c}{d}" for a in ("", "x.", "x-", "x") for b in ("", ".", "-", "_") for c in ("", "1", "12", "a") for d in (".com", ".x.org", "-x.com", "")]
    hosts += [f"{a}{w}{b}com" for w in ("ads", "tracker") for a in ("", "w.", "w-") for b in (".", "1.", "-")]
    paths = [f"/{w}{e}" for w in ("login", "cart", "wp-admin", "wp.admin", "wpadmin", "cgi-bin", "spam-farm3.x", "a/spamfarm.x") for e in ("", "/", "/x", "1", "-x")]
    urls = [f"http://{h}/" for h in hosts] + [f"http://w.com{p}" for p in paths] + ["http://SPAM-Farm7.com/Login", "http://spamfarm.com/cart/login", None]
    pages = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")
    got = {r.page_id: (r.general, r.verdict) for r in url_filter.judge(pages, url_filter.rule_table(spark, [("block", "nowhere", "/")])).collect()}
    for i, url in enumerate(urls):
        n = sum(bool(re.search(p, (url or "http://")[7:].lower())) for p, _ in url_filter.GENERAL_RULES)
        assert got[i] == (n, "block" if n else "allow"), url
    only = url_filter.judge(pages, url_filter.rule_table(spark, [], [(r"farm\d*\.", None)])).collect()
    assert {r.page_id: r.general for r in only} == {i: int(bool(re.search(r"farm\d*\.", (url or "").lower()))) for i, url in enumerate(urls)}


def test_rules_are_filed_under_their_rarest_token(spark):
    rules = url_filter.rule_table(spark)
    counts = spark.createDataFrame([("net", 100), ("example", 50), ("en", 7), ("com", 9), ("de", 20)], "token string, n long")
    by = {r.rule: r.token for r in url_filter.indexed(rules, counts).collect()}
    assert by["example.net/en/"] == "en" and by["example.com/de/"] == "com" and by["net/"] == "net"
    with pytest.raises(ValueError):
        url_filter.rule_table(spark, [], [("/x", [])])


def test_mixing_reaches_its_weights(spark):
    docs = spark.range(30_000).select(F.col("id").alias("doc_id"), F.lit("abcd").alias("text"), F.when(F.col("id") % 10 < 7, "big").otherwise("small").alias("source"))
    got = {r.source: r.n for r in mixing.mixed(docs, {"big": 1, "small": 3}).groupBy("source").agg(F.count("*").alias("n")).collect()}
    assert abs(got["small"] / 22_500 - 1) < 0.03 and abs(got["big"] / 7_500 - 1) < 0.05
    counts = mixing.mixed(docs.where("source = 'small'"), {"small": 1}, total=4 * 9000 * 2).groupBy("doc_id").agg(F.count("*").alias("n"))
    mean, var = counts.agg(F.sum("n") / 9000, F.sum(F.pow(F.col("n") - 2, 2)) / 9000).first()
    assert abs(mean - 2) < 0.06 and 1.5 < var + 4 * (1 - counts.count() / 9000) < 2.6


def test_poisson_inversion(spark):
    from math import exp

    for rate in (0.0, 0.3, 4.0, 90.0):
        us = [i / 997 for i in range(997)]
        got = [r.n for r in spark.createDataFrame([(u,) for u in us], "u double").coalesce(1).select(mixing.poisson_count(F.lit(rate), F.col("u")).alias("n")).collect()]
        for u, n in zip(us, got):
            p, c, k = exp(-rate), exp(-rate), 0
            while c <= u:
                k += 1
                p *= rate / k
                c += p
            assert n == k
    huge = spark.createDataFrame([(1, "abc", "s")], "doc_id long, text string, source string")
    assert abs(mixing.mixed(huge, {"s": 1}, total=3 * 2000).count() - 2000) < 300


def test_mixing_is_repeatable_and_takes_odd_rows(edge, empty, small):
    got = mixing.mixed(edge.drop("copy_no"), extra=True)
    assert got.columns == [*edge.drop("copy_no").columns, "copy_no", "order_key"]
    a, b = (sorted(map(repr, x.collect())) for x in (got, mixing.mixed(edge.drop("copy_no").repartition(5), extra=True)))
    assert a == b and mixing.mixed(edge).columns == edge.columns
    assert mixing.mixed(empty).count() == 0
    keys = [r.order_key for r in mixing.mixed(small[0], extra=True).collect()]
    assert len(set(keys)) == len(keys)
    zero = mixing.mixed(small[0], {"src0": 1.0})
    assert {r.source for r in zero.select("source").distinct().collect()} == {"src0"}
