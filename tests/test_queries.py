"""Every query with SQL gives the rows that DuckDB gives."""

import hashlib
import math
import os
import re

import duckdb
import pytest

import __spark_entry__ as entry
from eqdict.queries import ORACLES, QUERIES

SF = "/root/testdata/sf0.001"


def plain(v):
    if isinstance(v, float):
        return None if math.isnan(v) else round(v, 6)
    return v


def rows_of(columns, rows):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return sorted(repr(tuple(plain(r[i]) for i in order)) for r in rows)


def views(sf):
    c = duckdb.connect()
    for f in os.listdir(sf):
        c.execute(f"CREATE VIEW {f.split('.')[0]} AS SELECT * FROM '{sf}/{f}'")
    return c


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_query_matches_sql(spark, name):
    got = QUERIES[name](spark, SF)
    c = views(SF).execute(ORACLES[name])
    assert sorted(got.columns) == sorted(d[0] for d in c.description)
    assert rows_of(got.columns, got.collect()) == rows_of([d[0] for d in c.description], c.fetchall())


def test_entry_and_names(spark):
    assert entry.entry(spark).count() == 1500
    assert set(ORACLES) <= set(entry.queries()) and set(entry.oracle_sql()) <= set(entry.queries())


def test_every_query_has_sql():
    assert set(QUERIES) == set(ORACLES)


def within1(a, b):
    """Whether one edit at most makes b of a."""
    if len(a) > len(b):
        a, b = b, a
    i = next((i for i, (x, y) in enumerate(zip(a, b)) if x != y), len(a))
    return len(b) - len(a) <= 1 and a[i + (len(a) == len(b)) :] == b[i + 1 :]


def test_passwords_of_all_lengths_and_letters(spark, tmp_path):
    docs = ["Straße größeßt übermäßig élèves", "unbelievableness hippopotamus naïveté", "benchmark pangram ab", None]
    said = ["Strase größßt übermäßigq élèvesé", "nbelievableness hippopotamusses naiveté", "hippopotamuz benchmurk rhythms", "überm2ßig"]
    for name, rows, schema in (("documents", docs, "text string"), ("conversations", said, "text string"), ("customer", ["Benchmärk", "Customer#000000001", None], "c_name string")):
        spark.createDataFrame([(i, x) for i, x in enumerate(rows)], f"{'c_custkey' if name == 'customer' else 'doc_id'} long, {schema}").write.parquet(f"{tmp_path}/{name}.parquet")
    split = lambda texts: {w for t in texts if t for w in re.split(r"[\W\d_]+", t.lower()) if len(w) >= 6}
    listed, change = split(docs), lambda w: (w, w[1:], w + "qx")[(len(w) + ord(w[0])) % 3]
    want = {"benchmärk", "customer#000000001"} | {hashlib.md5(f"token:{i}".encode()).hexdigest()[:10] for i in range(3)} | {change(w) for w in listed | split(said)}
    got = QUERIES["password_edit1_verified"](spark, str(tmp_path)).collect()
    assert len(got) == len(want) and {r.word: r.unsuitable for r in got} == {w: any(within1(w, d) for d in listed) for w in want}
    bad = {r.word for r in got if r.unsuitable}
    assert any(len(w) > 9 for w in bad) and any(not w.isascii() for w in bad) and len(bad) < len(got)


@pytest.mark.parametrize("name", ["theory_error_bits", "theory_independence", "theory_space_table", "theory_paper_params", "theory_comparison"])
def test_closed_forms_are_of_given_tables(spark, tmp_path, name):
    """Their sizes come from the tables, without which they fail."""
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        QUERIES[name](spark, str(tmp_path)).collect()


@pytest.mark.parametrize("name", ["position_rates", "solve_rates", "sparse_rates", "split_rates", "table_hash_rates"])
def test_rates_are_of_given_tables(spark, tmp_path, name):
    """Draws are the keys of a table, all of them; more than the smallest tables give."""
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        QUERIES[name](spark, str(tmp_path)).collect()
    key, n, other = {"solve_rates": ("p_partkey", 1300, ""), "sparse_rates": ("p_partkey", 7300, ""), "split_rates": ("l_orderkey", 41_000, ", (id % 3)::INTEGER AS l_linenumber")}.get(name, ("o_orderkey", 30_000, ""))
    file = {"p": "part", "l": "lineitem", "o": "orders"}[key[0]]
    duckdb.sql(f"COPY (SELECT 7 * id AS {key}{other} FROM range({n}) t(id)) TO '{tmp_path}/{file}.parquet'")
    got = QUERIES[name](spark, str(tmp_path)).collect()
    sizes = [n // next(r[c] for c in ("n", "s", "keys") if c in r) for r in got]
    assert [r.draws for r in got] == sizes and all(sizes) and all(r.as_expected for r in got)


@pytest.mark.parametrize("name, file", [("solve_rates", "part"), ("split_rates", "lineitem")])
def test_rates_have_spark_read_their_table(spark, name, file):
    """The file is scanned by the result's own plan, not by the driver."""
    assert QUERIES[name](spark, SF).inputFiles() == [f"file://{SF}/{file}.parquet"]
