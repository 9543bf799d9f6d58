"""Exact deduplication by a tree merge of sorted digest runs, in DataFrame functions only.

Each input partition belongs to one of `runs` leaf runs: entries sorted by digest, one for each text in it, with the smallest
identifier and the number of rows. Leaf runs are written. Then come binomial rounds: in round r the runs whose numbers differ in
bit r alone exchange their entries, which are sorted by digest and merged, equal digests keeping the smallest identifier and the sum of
their rows. Because an entry's place follows from run and digest together, even the last round, with one run, is spread over all
tasks. A text with very many copies sends one entry per run and round, never its rows.

An entry's key is the SHA-256 of its text, the MD5 as a second, independently built digest, and the length in bytes. At every level
an identifier is only retained among entries that agree in all three: equal texts always do, and for different ones that would take a
collision of both digests at one length. No text moves for this.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from eqdict.llm.common import staged, workdir

KEY = ["_digest", "_check", "_bytes"]
RUNS = 64


def normalised(text):
    """Null counts as empty; each run of ASCII white space becomes one space."""
    return F.regexp_replace(F.coalesce(text, F.lit("")), r"[\x20\x09-\x0D]+", " ")


def with_digest(docs: DataFrame, id_col: str, text_col: str, *keep: str) -> DataFrame:
    t = docs.select(F.col(id_col).alias("_id"), *keep, normalised(F.col(text_col)).alias("_text"))
    return t.select("_id", *keep, F.unhex(F.sha2("_text", 256)).alias("_digest"), F.unhex(F.md5("_text")).alias("_check"), F.octet_length("_text").alias("_bytes"))


def leaf_runs(rows: DataFrame, runs: int, path: str) -> DataFrame:
    """Written runs (_run, KEY, smallest, size) of rows(_id, KEY), each partition's rows in the run of its number modulo `runs`."""
    first = F.struct(F.col("_id").isNull().alias("none"), F.col("_id").alias("id"))
    run = rows.select((F.spark_partition_id() % runs).alias("_run"), *KEY, first.alias("smallest"), F.lit(1).cast("long").alias("size"))
    return staged(merged(run.groupBy("_run", *KEY)).sortWithinPartitions("_run", *KEY), path)


def merged(groups) -> DataFrame:
    return groups.agg(F.min("smallest").alias("smallest"), F.sum("size").alias("size"))


def merged_runs(rows: DataFrame, path: str, runs: int = RUNS) -> DataFrame:
    """One entry (KEY, keep_id, group_size) per distinct text of rows(_id, KEY). Written leaf runs lie at path."""
    run = leaf_runs(rows, runs, path)
    for _ in range((runs - 1).bit_length()):
        paired = run.withColumn("_run", F.shiftright("_run", 1))
        run = merged(paired.repartition("_run", *KEY).sortWithinPartitions("_run", *KEY).groupBy("_run", *KEY))
    return run.select(*KEY, F.col("smallest.id").alias("keep_id"), F.col("size").alias("group_size"))


def exact_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", runs: int = RUNS) -> DataFrame:
    """For every row: doc_id, keep_id, group_size, kept, text_sha256.

    Null and empty texts are equal to each other, and a text of white space is one space. Repeated rows with one identifier all
    count in group_size and are all `kept` if theirs is the smallest. A null identifier is larger than any other; a group of such
    rows alone has keep_id null and all are kept. Other columns are ignored, whatever their names. An empty table gives no rows.
    """
    work = workdir(docs.sparkSession, "exact")
    rows = staged(with_digest(docs, id_col, text_col), f"{work}/digests")
    joined = rows.join(merged_runs(rows, f"{work}/runs", runs), KEY)
    return joined.select(F.col("_id").alias("doc_id"), "keep_id", "group_size", F.col("_id").eqNullSafe(F.col("keep_id")).alias("kept"), F.lower(F.hex("_digest")).alias("text_sha256"))


def exact_distinct(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", runs: int = RUNS) -> DataFrame:
    """docs with one row for each distinct normalised text: the one with the smallest identifier.

    Of rows that share text and identifier one stays. Columns and their names are those of docs.
    """
    work = workdir(docs.sparkSession, "exact")
    rows = staged(with_digest(docs, id_col, text_col), f"{work}/digests")
    keep = merged_runs(rows, f"{work}/runs", runs).select(F.xxhash64("keep_id").alias("_k"), *KEY)
    whole = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("_row"))
    tagged = with_digest(whole, f"_row.{id_col}", f"_row.{text_col}", "_row").withColumn("_k", F.xxhash64("_id"))
    return tagged.join(keep, ["_k", *KEY], "left_semi").dropDuplicates(["_k", *KEY]).select("_row.*")
