"""Applications: word lists, differential files, cache summaries, runs of a structured store, filtered joins, known texts.

Each has a verified form, whose result is exact, and a count of what the filter's errors cost.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from eqdict.functions.hashing import affine31, seed_of
from eqdict.operators.membership import build_filter, contains, contains_within1, where_contains
from eqdict.sources.store import Store

#: Proxies or runs that are written into a plan one by one.
MOST_LISTED = 1024


def words_of(text: Column, least: int = 1) -> Column:
    """Lower-case words of letters, as an array."""
    return F.filter(F.split(F.lower(text), r"[^\p{L}]+"), lambda w: F.length(w) >= least)


def word_list(docs: DataFrame, text: str = "text", least: int = 1) -> DataFrame:
    return docs.select(F.explode(words_of(F.col(text), least)).alias("word")).distinct()


def misspelled(words: Store, text: DataFrame, word: str = "word") -> DataFrame:
    """Words that the list's filter rejects: all of them are wrong, and 2^-k of the wrong ones are not among them."""
    return contains(words, text, word, "_known").where("_known is not null and not _known").drop("_known")


def misspelled_verified(dictionary: DataFrame, text: DataFrame, k: int = 8, word: str = "word") -> DataFrame:
    """Exactly the words that the list lacks: hits of the filter are compared with the list."""
    tested = contains(build_filter(dictionary, word, k), text, word, "_known")
    sure = tested.where("not _known").drop("_known")
    return sure.unionByName(tested.where("_known").drop("_known").join(dictionary.select(word), word, "left_anti"))


def unsuitable(passwords: Store, candidates: DataFrame, word: str = "word") -> DataFrame:
    """Candidates with whether they, or a word one edit away, are in the list. No bad one passes."""
    return contains_within1(passwords, candidates, word, "unsuitable")


def without_one(word: Column) -> Column:
    """(variant, place) of a word itself, at place 0, and of the word without each of its letters."""
    itself = F.struct(word.alias("variant"), F.lit(0).alias("place"))
    at = F.filter(F.sequence(F.lit(0), F.length(word)), lambda i: i > 0)
    return F.concat(F.array(itself), F.transform(at, lambda i: F.struct(F.concat(F.substring(word, F.lit(1), i - 1), F.substring(word, i + 1, F.length(word))).alias("variant"), i.alias("place"))))


def unsuitable_verified(dictionary: DataFrame, candidates: DataFrame, k: int = 8, word: str = "word") -> DataFrame:
    """Exactly which candidates are in the list or one edit away from it, whatever their letters.

    The filter holds the list's words and these without one letter, and a candidate asks for as many variants of its own as it has
    letters, not for all words around it. Two words are at most one edit apart if they are equal, if one is the other without a letter, or if
    they agree without the letter at one place; that is what the filter's hits are compared by.
    """
    of = lambda df, name: df.select(F.col(word).alias(name)).where(F.col(name).isNotNull()).distinct()
    # a word is short but stands for many variants, so the number of tasks is not left to adaptive coalescing
    tasks = int(candidates.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    spread = lambda df, name, place: of(df, name).repartition(tasks, name).select(name, F.inline(without_one(F.col(name)))).withColumnRenamed("place", place)
    listed, tried = spread(dictionary, "_l", "_lp"), spread(candidates, "_w", "_wp")
    claimed = where_contains(build_filter(listed.select("variant").distinct(), "variant", k), tried, "variant")
    near = claimed.join(listed, "variant").where("_lp = _wp or _lp = 0 or _wp = 0")
    sure = near.select("_w").distinct().withColumn("_is", F.lit(True))
    return candidates.join(sure, F.col(word) == F.col("_w"), "left").select(*candidates.columns, F.coalesce("_is", F.lit(False)).alias("unsuitable"))


def differential_reads(changed: DataFrame, reads: DataFrame, key: str, k: int = 8) -> DataFrame:
    """reads with `routed`: those that must look into the differential file. Every read of a changed record is among them."""
    return contains(build_filter(changed, key, k), reads, key, "routed")


def differential_report(changed: DataFrame, reads: DataFrame, key: str, k: int = 8) -> DataFrame:
    """(reads, needed, routed, missed, wasted)."""
    routed = differential_reads(changed, reads, key, k)
    truth = routed.join(changed.select(key).distinct().withColumn("_c", F.lit(True)), key, "left")
    need = F.col("_c").isNotNull()
    return truth.agg(F.count("*").alias("reads"), F.count_if(need).alias("needed"), F.count_if(F.col("routed")).alias("routed"), F.count_if(need & ~F.col("routed")).alias("missed"), F.count_if(~need & F.col("routed")).alias("wasted"))


def for_each(rows: DataFrame, few: DataFrame) -> DataFrame:
    """rows once for each row of the one-column table few: every proxy, or run, has its own filter to ask.

    While few is at most MOST_LISTED rows they are a list in the plan; a longer one stays a table.
    """
    name, listed = few.columns[0], few.limit(MOST_LISTED + 1).collect()
    if len(listed) > MOST_LISTED:
        return rows.crossJoin(few)
    kind = few.schema[name].dataType.simpleString()
    return rows.withColumn(name, F.explode(F.array(*(F.lit(r[0]) for r in listed)).cast(f"array<{kind}>")))


def proxy_of(url: Column, proxies: int) -> Column:
    """A proxy by the host of a URL, with a hash that SQL engines share."""
    host = F.regexp_extract(url, r"^[^:]*://([^/?#]*)", 1)
    return affine31(F.conv(F.substring(F.md5(host), 1, 7), 16, 10).cast("long"), seed_of("proxy"), proxies)


def summaries(caches: DataFrame, proxy: str, url: str, k: int = 8) -> Store:
    """One store for the filters of all proxies: its keys are pairs of proxy and URL."""
    return build_filter(caches, [proxy, url], k)


def ask_proxies(store: Store, requests: DataFrame, proxies: DataFrame, proxy: str, url: str) -> DataFrame:
    """requests with each proxy whose summary claims the URL."""
    asked = for_each(requests.select(F.col(url)), proxies.select(proxy))
    return contains(store, asked, [proxy, url], "_claims").where("_claims").drop("_claims")


def run_filters(runs: DataFrame, run: str, key: str, k: int = 8) -> Store:
    return build_filter(runs, [run, key], k)


def runs_to_read(store: Store, queries: DataFrame, runs: DataFrame, run: str, key: str) -> DataFrame:
    """(key, run) pairs that the runs' filters do not rule out. Every run that holds a key is among its pairs."""
    pairs = for_each(queries.select(key), runs.select(run).distinct())
    return contains(store, pairs, [run, key], "_may").where("_may").drop("_may")


def known_texts(docs: DataFrame, probe: DataFrame, text: str = "text", k: int = 16) -> DataFrame:
    """probe with whether its text is among docs', by a filter whose size does not depend on the texts'."""
    return contains(build_filter(docs, text, k, on_null="drop"), probe, text, "known")
