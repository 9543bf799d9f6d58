"""Mixing sources to target weights by Poisson replication.

A source's repetition rate is the characters it should have in the mixture over those it has. Each document draws how often it
appears by inverting a Poisson distribution with that mean at a uniform number hashed from a seed and its identifier, so a draw
does not depend on partitions or retries. Documents are exploded by their counts and shuffled globally by a second hash.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from eqdict.llm.common import staged, workdir

MOST_BROADCAST_SOURCES = 100_000
SMOOTHING = 0.5
SEED = "mix-1"
#: exp(-rate) must not vanish; a larger rate is drawn as the sum of several Poisson numbers.
LARGEST_RATE = 500.0


def uniform(*cols: Column | str) -> Column:
    """A number in [0, 1) with 52 bits from the MD5 of the columns."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", *cols)), 1, 13), 16, 10).cast("long").cast("double") / F.lit(float(1 << 52))


def poisson_count(rate: Column, u: Column) -> Column:
    """The smallest k with P(X <= k) > u. The terms go so far that what lies beyond them is less than a step of u."""
    last = F.ceil(rate + 12 * F.sqrt(rate) + 30).cast("int")
    start = F.struct(F.exp(-rate).alias("p"), F.exp(-rate).alias("c"), F.when(F.exp(-rate) <= u, 1).otherwise(0).alias("n"))

    def step(acc: Column, k: Column) -> Column:
        p = acc["p"] * rate / k
        return F.struct(p.alias("p"), (acc["c"] + p).alias("c"), (acc["n"] + F.when(acc["c"] + p <= u, 1).otherwise(0)).alias("n"))

    return F.aggregate(F.sequence(F.lit(1), last), start, step, lambda acc: acc["n"])


def rates(docs: DataFrame, weights: dict[str | None, float] | None = None, total: float | None = None, smoothing: float = SMOOTHING, source_col: str = "source", text_col: str = "text") -> DataFrame:
    """(source, rate): target characters over present ones.

    weights: a share for each source, and 0 for those not named; None: shares in proportion to size ** smoothing. total: characters
    of the mixture, by default as many as there are. A source without characters has rate 1.
    """
    spark = docs.sparkSession
    size = docs.groupBy(F.col(source_col).alias("_source")).agg(F.sum(F.length(F.coalesce(F.col(text_col), F.lit("")))).cast("double").alias("_size"))
    if weights is None:
        size = size.withColumn("_want", F.when(F.col("_size") > 0, F.pow("_size", F.lit(smoothing))).otherwise(0.0))
    else:
        wanted = spark.createDataFrame([(k, float(v)) for k, v in weights.items()], "_name string, _want double")
        size = size.join(wanted, F.col("_source").cast("string").eqNullSafe(F.col("_name")), "left").select("_source", "_size", F.coalesce("_want", F.lit(0.0)).alias("_want"))
    # one row a source, written, so that the texts are measured once
    size = staged(size, f"{workdir(spark, 'mixing')}/sizes")
    all_ = size.agg(F.sum("_want").alias("w"), F.sum("_size").alias("s")).first()
    want, have = all_["w"] or 1.0, all_["s"] or 0.0
    return size.select("_source", F.when(F.col("_size") > 0, F.col("_want") / F.lit(want) * F.lit(float(total if total is not None else have)) / F.col("_size")).otherwise(1.0).alias("_rate"))


def mixed(docs: DataFrame, weights: dict[str | None, float] | None = None, total: float | None = None, smoothing: float = SMOOTHING, seed: str = SEED, id_col: str = "doc_id", source_col: str = "source", text_col: str = "text", extra: bool = False) -> DataFrame:
    """docs with each row repeated by its draw, in a global random order; with extra also `copy_no` (from 0) and `order_key`.

    Null sources are a source of their own. Null identifiers all draw as the text 'null'; repeated rows draw alike and each is
    repeated. Null texts have no characters. An empty table stays empty. Columns of docs keep their names, whatever they are; with
    extra, they must not be called copy_no or order_key.
    """
    rate = rates(docs, weights, total, smoothing, source_col, text_col)
    n_sources, top = rate.agg(F.count("*"), F.max("_rate")).first()
    few = n_sources <= MOST_BROADCAST_SOURCES
    pieces = max(1, int(-(-(top or 0.0) // LARGEST_RATE)))
    names = docs.columns
    ident = F.coalesce(F.col(f"_row.{id_col}").cast("string"), F.lit("null"))
    rows = docs.select(F.struct(*(F.col(f"`{c}`") for c in names)).alias("_row"))
    joined = rows.join(F.broadcast(rate) if few else rate, F.col(f"_row.{source_col}").eqNullSafe(F.col("_source")))
    draws = [poisson_count(F.col("_rate") / pieces, uniform(F.lit(seed if i == 0 else f"{seed}/{i}"), ident)) for i in range(pieces)]
    drawn = joined.select("_row", ident.alias("_ident"), reduce(lambda a, b: a + b, draws).alias("_n")).where("_n > 0")
    copies = drawn.select("_row", "_ident", F.explode(F.sequence(F.lit(0), F.col("_n") - 1)).alias("copy_no"))
    keyed = copies.select("_row", "copy_no", F.md5(F.concat_ws(":", F.lit(seed), F.lit("order"), "_ident", F.col("copy_no").cast("string"))).alias("order_key"))
    shuffled = keyed.repartition("order_key").sortWithinPartitions("order_key")
    return shuffled.select("_row.*", *(["copy_no", "order_key"] if extra else []))
