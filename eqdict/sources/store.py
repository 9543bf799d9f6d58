"""Stores: tables of solved buckets, their side dictionary and a manifest that is written last."""

from __future__ import annotations

import json
import tempfile
import uuid
from dataclasses import dataclass
from math import log2

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from eqdict.spec import DictSpec

CELL = "struct<m:int,seed:int,extra:int,planes:array<bigint>>"
BUCKETS = f"bucket long, n_keys int, split_seed int, func_no int, cells array<{CELL}>, side array<struct<key_hi:bigint,key_lo:bigint,value:bigint>>, tries long, splits long"


def workdir(spark: SparkSession, name: str) -> str:
    """A fresh folder that driver and executors share, below spark.checkpoint.dir; where that is unset, a temporary one under a local
    master (tests), and an error on a cluster, whose machines do not share their folders."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if spark.sparkContext.master != "local" and not spark.sparkContext.master.startswith("local["):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        base = tempfile.mkdtemp(prefix="eqdict-")
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def staged(df: DataFrame, path: str) -> DataFrame:
    spark, schema = df.sparkSession, df.schema
    df.write.parquet(path)
    return spark.read.schema(schema).parquet(path)


def drop(spark: SparkSession, path: str) -> None:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


@dataclass
class Store:
    spec: DictSpec
    n_buckets: int
    h1_seed: int
    buckets: DataFrame
    side: DataFrame
    facts: dict
    path: str

    def insert(self, *_):
        raise NotImplementedError("a store is static: build it again, or keep tiers (streaming.tiers)")

    @property
    def n_keys(self) -> int:
        return self.facts["n_keys"]


def save(spec: DictSpec, n_buckets: int, h1_seed: int, solved: DataFrame, path: str, most_bad: float | None = None) -> Store | None:
    """Write solved buckets (BUCKETS) and what they leave to the side dictionary; the manifest is the commit.

    With most_bad, buckets over their cap may hold that share of the keys, or 1 / log^2 n of them if it is below 0; if they hold more,
    what was written is deleted, nothing is committed and None is returned.
    """
    spark = solved.sparkSession
    solved = staged(solved, f"{path}/buckets")
    cells = F.size("cells")
    m = F.aggregate("cells", F.lit(0).cast("long"), lambda s, c: s + c["m"])
    facts = solved.agg(
        F.coalesce(F.sum("n_keys"), F.lit(0)).alias("n_keys"), F.coalesce(F.sum(cells), F.lit(0)).alias("cells"), F.coalesce(F.sum(m), F.lit(0)).alias("variables"),
        F.coalesce(F.sum(F.size("side")), F.lit(0)).alias("n_side"), F.coalesce(F.sum("tries"), F.lit(0)).alias("tries"), F.coalesce(F.sum("splits"), F.lit(0)).alias("splits"),
        F.count("*").alias("buckets"), F.coalesce(F.max("n_keys"), F.lit(0)).alias("largest"), F.coalesce(F.sum(F.when(F.col("n_keys") > spec.cap, F.col("n_keys"))), F.lit(0)).alias("bad_keys"),
        F.coalesce(F.max(F.aggregate("cells", F.lit(0), lambda s, c: F.greatest(s, c["seed"]))), F.lit(0)).alias("top_seed"),
    ).first().asDict()
    if most_bad is not None and facts["bad_keys"] > facts["n_keys"] * (most_bad if most_bad >= 0 else 1 / log2(max(facts["n_keys"], 2)) ** 2):
        drop(spark, f"{path}/buckets")
        return None
    side = solved.where(F.size("side") > 0).select(F.inline("side"))
    if facts["n_side"]:
        side = staged(side, f"{path}/side")
    manifest = json.dumps({"spec": json.loads(spec.to_json()), "n_buckets": n_buckets, "h1_seed": h1_seed, "facts": facts})
    spark.range(1, numPartitions=1).select(F.lit(manifest).alias("value")).write.text(f"{path}/manifest")
    return Store(spec, n_buckets, h1_seed, solved, side, facts, path)


def load(spark: SparkSession, path: str) -> Store:
    manifest = json.loads(spark.read.text(f"{path}/manifest").first()["value"])
    spec = DictSpec.from_json(json.dumps(manifest["spec"]))
    buckets = spark.read.schema(BUCKETS).parquet(f"{path}/buckets")
    side = spark.read.schema("key_hi long, key_lo long, value long").parquet(f"{path}/side") if manifest["facts"]["n_side"] else buckets.where(F.size("side") > 0).select(F.inline("side"))
    return Store(spec, manifest["n_buckets"], manifest["h1_seed"], buckets, side, manifest["facts"], path)
