"""What users of differential files, runs and dictionaries do around them: as-of and range look-ups, comparisons, splits."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

MOST_BROADCAST_RANGES = 10_000


def latest(changes: DataFrame, key: str, time: str, tie: str, until: Column | None = None) -> DataFrame:
    """The last change of each key up to a time; of simultaneous ones the one with the larger tie column."""
    rows = changes if until is None else changes.where(F.col(time) <= until)
    others = [c for c in changes.columns if c != key]
    best = rows.groupBy(key).agg(F.max_by(F.struct(*others), F.struct(time, tie)).alias("_r"))
    return best.select(key, "_r.*")


def current(base: DataFrame, changes: DataFrame, key: str, time: str, tie: str) -> DataFrame:
    """base with the latest change of each key in its place; both have the same columns but for time and tie."""
    last = latest(changes, key, time, tie).drop(time, tie)
    names = [c for c in base.columns if c != key]
    other = last.select(F.col(key), *(F.col(c).alias(f"_{c}") for c in names), F.lit(True).alias("_changed"))
    joined = base.join(other, key, "full")
    return joined.select(key, *(F.when(F.col("_changed"), F.col(f"_{c}")).otherwise(F.col(c)).alias(c) for c in names))


def split_by_range(keys: DataFrame, key: str, runs: int) -> DataFrame:
    """(run, low, high) of `runs` ranges of about equal numbers of keys, by approximate quantiles: one aggregate, no global window."""
    at = [i / runs for i in range(1, runs)]
    q = keys.agg(F.percentile_approx(key, at, 100_000).alias("q"), F.min(key).alias("lo"), F.max(key).alias("hi")).first()
    cuts = [q["lo"], *(q["q"] or []), None]
    rows = [(i, a, b) for i, (a, b) in enumerate(zip(cuts[:-1], cuts[1:], strict=True))]
    return keys.sparkSession.createDataFrame(rows, "run int, low long, high long")


def run_of_range(keys: DataFrame, ranges: DataFrame, key: str) -> DataFrame:
    """keys with their run. Ranges are broadcast if they are at most MOST_BROADCAST_RANGES; more are joined as they are."""
    inside = (F.col(key) >= F.col("low")) & (F.col("high").isNull() | (F.col(key) < F.col("high")))
    few = ranges.limit(MOST_BROADCAST_RANGES + 1).count() <= MOST_BROADCAST_RANGES
    return keys.join(F.broadcast(ranges) if few else ranges, inside, "left").select(*keys.columns, "run")


def dictionary_diff(old: DataFrame, new: DataFrame, key: str, value: str) -> DataFrame:
    """(key, old, new, kind) of keys that were added, removed or given another value."""
    a, b = old.select(key, F.col(value).alias("old")), new.select(key, F.col(value).alias("new"))
    both = a.join(b, key, "full")
    kind = F.when(F.col("old").isNull(), "added").when(F.col("new").isNull(), "removed").when(F.col("old") != F.col("new"), "changed")
    return both.select(key, "old", "new", kind.alias("kind")).where("kind is not null")


def changes_by_day(events: DataFrame, time: str, key: str) -> DataFrame:
    """(day, keys, new): the keys changed on each day, and how many more than on the day before there are.

    The window has no partition, over a row a day: centuries of days fit one task.
    """
    day = events.groupBy(F.to_date(time).alias("day")).agg(F.count_distinct(key).alias("keys"))
    return day.select("day", "keys", (F.col("keys") - F.lag("keys", 1, 0).over(Window.orderBy("day"))).alias("new"))
