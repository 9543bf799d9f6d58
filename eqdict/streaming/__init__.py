"""Streams meet stores: probes of a static store, stores rebuilt by window, and tiers that stand in for insertion."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from eqdict.operators.build import prepared, settled
from eqdict.operators.membership import build_filter, contains, fingerprint
from eqdict.operators.probe import looked_up
from eqdict.sources.store import Store, drop, staged, workdir


def probe_stream(store: Store, stream: DataFrame, keys, out: str = "value") -> DataFrame:
    """A stream with looked-up values: a stream-static join, with no state. For filters, `out` is a boolean."""
    return contains(store, stream, keys, out) if store.spec.membership else looked_up(store, stream, keys, out)


def run_available(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run a stream over all that is there now, into a table, and read that."""
    spark = stream.sparkSession
    folder = workdir(spark, name)
    q = stream.writeStream.format("parquet").outputMode(mode).option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{folder}/out")


def events_stream(spark: SparkSession, folder: str, schema, file: str = "events.parquet", files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("pathGlobFilter", file).option("maxFilesPerTrigger", files_per_batch).parquet(folder)


class Tiers:
    """Several static filters that together take more keys: every batch is a new tier, compact() makes one of all.

    An extension: a single store takes no insertions. The error is at most the number of tiers times 2^-k. Keys are kept
    beside, as a rebuild needs them.
    """

    def __init__(self, keys: list[str] | str, k: int = 8):
        self.keys, self.k = keys, k
        self.tiers: list[Store] = []
        self.batches: list[DataFrame] = []

    def add_batch(self, df: DataFrame) -> None:
        names = [self.keys] if isinstance(self.keys, str) else list(self.keys)
        only = df.select(*names).dropna().distinct()
        self.batches.append(only)
        self.tiers.append(build_filter(only, names, self.k))

    def contains(self, df: DataFrame, out: str = "hit") -> DataFrame:
        got, columns = df, df.columns
        if not self.tiers:
            return df.withColumn(out, F.lit(False))
        for i, t in enumerate(self.tiers):
            got = contains(t, got, self.keys, f"_t{i}")
        hit = F.col("_t0")
        for i in range(1, len(self.tiers)):
            hit = hit | F.col(f"_t{i}")
        return got.select(*columns, hit.alias(out))

    def compact(self) -> None:
        if len(self.tiers) > 1:
            whole = self.batches[0]
            for b in self.batches[1:]:
                whole = whole.unionByName(b)
            names = [self.keys] if isinstance(self.keys, str) else list(self.keys)
            self.batches = [whole.distinct()]
            self.tiers = [build_filter(self.batches[0], names, self.k)]


def windowed_filters(stream: DataFrame, time: str, key: str, window: str = "1 day", delay: str = "1 hour", slide: str | None = None) -> DataFrame:
    """(window, key) of a stream, each once, as windows close: what a filter of each window is built of. Late rows past the watermark go."""
    stream = stream.withColumn(time, F.col(time).cast("timestamp"))
    return stream.withWatermark(time, delay).groupBy(F.window(time, window, slide) if slide else F.window(time, window), key).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), F.col("window.end").alias("end"), key, "n")


def active_sessions(stream: DataFrame, time: str, key: str, gap: str = "30 minutes", delay: str = "1 hour") -> DataFrame:
    """(start, end, key, n) of a stream's sessions as they close."""
    stream = stream.withColumn(time, F.col(time).cast("timestamp")).withWatermark(time, delay)
    return stream.groupBy(F.session_window(time, gap), key).agg(F.count("*").alias("n")).select(F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), key, "n")


def first_seen(stream: DataFrame, time: str, key: str, delay: str = "1 hour") -> DataFrame:
    """Each key of a stream once within the watermark: what a filter takes, without state for older keys."""
    return stream.withColumn(time, F.col(time).cast("timestamp")).withWatermark(time, delay).dropDuplicatesWithinWatermark([key])


def with_late_keys(store: Store, late: DataFrame, keys, value: str | None = None) -> Store:
    """The store with keys that came after it was closed in its exact side dictionary, where they go before what is stored.

    The next rebuild takes them over. A filter needs no value.
    """
    names = [keys] if isinstance(keys, str) else list(keys)
    v = fingerprint(late, names, store.spec) if store.spec.membership else F.col(value)
    data = settled(prepared(late, names, v, store.spec), spec=store.spec)
    old = store.side.join(data, ["key_hi", "key_lo"], "left_anti")
    side = staged(old.unionByName(data.select("key_hi", "key_lo", "value")), f"{workdir(late.sparkSession, 'late')}/side")
    return replace(store, side=side, facts=store.facts | {"n_side": side.count()})


def rebuild_by_batch(stream: DataFrame, folder: str, day, key: str, k: int = 8):
    """A query that builds one store for each day of a micro-batch, below folder; a batch that runs again writes the same place anew."""

    def one(batch: DataFrame, number: int) -> None:
        days = [r[0] for r in batch.select(day.cast("string").alias("d")).distinct().collect()]
        for d in days:
            path = f"{folder}/{d}/batch-{number}"
            drop(batch.sparkSession, path)  # what an earlier try of this batch left
            build_filter(batch.where(day.cast("string") == d), key, k, path=path, on_null="drop")

    return stream.writeStream.foreachBatch(one).option("checkpointLocation", f"{folder}/_state").trigger(availableNow=True).start()
