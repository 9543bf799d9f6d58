"""A fluent surface: dictionary(df).key("a").value("b").bits(3).write(path); opened(spark, path).lookup(df, "a")."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from eqdict.operators import measures
from eqdict.operators.build import build
from eqdict.operators.membership import build_filter, contains, where_contains
from eqdict.operators.probe import looked_up, looked_up_distinct
from eqdict.plans.sql import register
from eqdict.sources.store import Store, load
from eqdict.spec import DictSpec


class Builder:
    def __init__(self, df: DataFrame):
        self._df, self._keys, self._value, self._how = df, [], None, {"k": 8}

    def key(self, *names: str) -> Builder:
        self._keys = list(names)
        return self

    def value(self, name: str) -> Builder:
        self._value = name
        return self

    def bits(self, k: int) -> Builder:
        self._how["k"] = k
        return self

    def method(self, name: str) -> Builder:
        self._how["method"] = name
        return self

    def option(self, **how) -> Builder:
        """Any field of DictSpec."""
        self._how |= how
        return self

    def write(self, path: str | None = None) -> Dictionary:
        """Without a value column, a membership filter."""
        if not self._keys:
            raise ValueError("key columns are missing")
        if self._value is None:
            k = self._how["k"]
            return Dictionary(build_filter(self._df, self._keys, k, path, **{n: v for n, v in self._how.items() if n != "k"}))
        return Dictionary(build(self._df, self._keys, self._value, DictSpec(**self._how), path))


class Dictionary:
    def __init__(self, store: Store):
        self.store = store

    def lookup(self, df: DataFrame, *keys: str, out: str = "value", distinct: bool = False) -> DataFrame:
        return (looked_up_distinct if distinct else looked_up)(self.store, df, list(keys), out)

    def contains(self, df: DataFrame, *keys: str, out: str = "hit") -> DataFrame:
        return contains(self.store, df, list(keys), out)

    def where_contains(self, df: DataFrame, *keys: str) -> DataFrame:
        return where_contains(self.store, df, list(keys))

    def space(self) -> dict[str, float]:
        return measures.space(self.store)

    def describe(self) -> dict:
        s = self.store
        return {"method": s.spec.method, "k": s.spec.k, "path": s.path, "buckets": s.n_buckets} | s.facts | measures.probe_cost(s)

    def verify(self, df: DataFrame, *keys: str, value: str) -> int:
        """Wrong answers for stored keys: must be 0."""
        return measures.verify_members(self.store, df, list(keys), value)

    def views(self, name: str) -> None:
        register(self.store.buckets.sparkSession, self.store, name)

    def insert(self, *args):
        return self.store.insert(*args)


def dictionary(df: DataFrame) -> Builder:
    return Builder(df)


def opened(spark: SparkSession, path: str) -> Dictionary:
    return Dictionary(load(spark, path))
