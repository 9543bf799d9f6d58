"""Token counts through a digest cache.

Each text has a digest of its content, each tokenizer one of its file. A count is looked up in a stored table by both; of the texts
that miss, each distinct one is encoded once and its count is appended to the table. The rows that shuffle by digest hold no text;
texts move once, by a key of their own row, to meet the list of misses.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from eqdict.llm.common import staged, workdir
from eqdict.llm.tokenizing import encoder, file_digest

CACHE = "tokenizer string, digest binary, n_tokens long"


def body(c):
    """Content is normalised only as far as it cannot change a count: null is empty."""
    return F.coalesce(F.col(c), F.lit(""))


def row_key(ident, digest):
    """What moves a row: its identifier, so that copies of one text part; where that is null, its text's digest, so that texts part."""
    return F.when(F.col(ident).isNotNull(), F.xxhash64(F.lit(0), F.col(ident))).otherwise(F.xxhash64(F.lit(1), digest))


def cached(spark: SparkSession, path: str) -> DataFrame:
    """The cache table; an empty one if nothing has been stored at path."""
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    there = p.getFileSystem(spark._jsc.hadoopConfiguration()).exists(p)
    return spark.read.schema(CACHE).parquet(path) if there else spark.createDataFrame([], CACHE)


def token_counts(docs: DataFrame, tokenizer: str, cache: str | None = None, limit: int = 512, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """For every row: doc_id, n_bytes, n_tokens, over_limit.

    cache: folder of the cache table, kept and appended to; None: a new one. Null counts as empty (0 tokens); equal texts are
    encoded once. Repeated rows and null identifiers give a row each. Other columns are ignored, whatever their names. An empty
    table gives no rows and leaves the cache as it was.
    """
    spark = docs.sparkSession
    work = workdir(spark, "token-counts")
    cache = cache or f"{work}/cache"
    version = file_digest(tokenizer)

    rows = docs.select(F.col(id_col).alias("doc_id"), body(text_col).alias("_text"))
    digest = F.unhex(F.sha2("_text", 256))
    narrow = staged(rows.select("doc_id", digest.alias("_digest"), F.octet_length("_text").cast("long").alias("n_bytes")), f"{work}/digests")

    known = cached(spark, cache).where(F.col("tokenizer") == version).select(F.col("digest").alias("_digest"))
    misses = narrow.groupBy("_digest").agg(F.min(row_key("doc_id", F.col("_digest"))).alias("_key")).join(known, "_digest", "left_anti")
    texts = rows.select("_text", row_key("doc_id", digest).alias("_key"))
    # one text per miss: its row's key moves it, its digest confirms it
    found = texts.join(misses, "_key").where(digest == F.col("_digest")).select("_digest", "_text")

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, seen = encoder(tokenizer), {}
        for b in batches:
            digests, counts = [], []
            for d, t in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                if d not in seen:
                    if len(seen) >= 100_000:
                        seen.clear()
                    seen[d] = True
                    digests.append(d)
                    counts.append(len(enc.ids(t.as_py())))
            yield pa.RecordBatch.from_arrays([pa.array(digests, pa.binary()), pa.array(counts, pa.int64())], ["_digest", "n_tokens"])

    fresh = found.mapInArrow(encode, "_digest binary, n_tokens long")
    fresh.select(F.lit(version).alias("tokenizer"), F.col("_digest").alias("digest"), "n_tokens").write.mode("append").parquet(cache)
    # a text may have been encoded twice (two rows of one identifier, or two runs that append at a time)
    counts = cached(spark, cache).where(F.col("tokenizer") == version).groupBy(F.col("digest").alias("_digest")).agg(F.max("n_tokens").alias("n_tokens"))
    # written, so that a digest of very many rows has an exchange on both sides of the join, which adaptive execution splits
    out = narrow.join(staged(counts, f"{work}/counts"), "_digest")
    return out.select("doc_id", "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))
