"""Language identification by rank-order profiles.

A profile is a list of the most frequent letter n-grams (1 to 3 letters, with word ends) in order. A document's own list is compared
with each language's by the out-of-place distance: the sum of how far each of its n-grams stands from its place in the profile, with
a fixed distance for those that the profile lacks. The nearest language wins; of equal ones the first in the alphabet.

Letters of all scripts keep their identity: a code holds the whole n-gram. Profiles are fitted on a sample of labelled documents of
about SAMPLE a language (all, if there are fewer), chosen by a hash of the identifier; every document is judged by its whole text.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

SAMPLE = 1500
TOP = 300
#: Up to so many languages their sample shares are broadcast; beyond, they are joined.
MOST_BROADCAST_LANGUAGES = 10_000
UNKNOWN = "und"
#: Letters that come first, in this order; all other letters of Unicode follow by code point. The first 63 fit six bits.
FIRST = "abcdefghijklmnopqrstuvwxyzßàáâãäåæçèéêëìíîïñòóôõöøùúûüœ"
_BITS = 18  # a letter's number; three letters and the length of the n-gram fit 56 bits
_MASK = (1 << _BITS) - 1


@lru_cache(maxsize=1)
def _letters() -> np.ndarray:
    """Number of each character: 0 for what is not a letter, every letter has its own."""
    table = np.zeros(0x110000, np.int32)
    letters = np.fromiter((chr(i).isalpha() for i in range(0x110000)), bool, 0x110000)
    first = [ord(c) for c in FIRST]
    letters[first] = False
    rest = np.flatnonzero(letters)
    table[first] = np.arange(1, len(first) + 1)
    table[rest] = np.arange(len(first) + 1, len(first) + 1 + len(rest))
    return table


def _grams(c: np.ndarray, bits: int) -> np.ndarray:
    """Codes of the 1-, 2- and 3-grams of letter numbers with 0 between words: length first, then the letters."""
    one, two = c[c != 0], (c[:-1] << bits) | c[1:]
    three = ((c[:-2] << 2 * bits) | (c[1:-1] << bits) | c[2:])[c[1:-1] != 0]
    return np.concatenate([one, two | 1 << 3 * bits, three | 2 << 3 * bits])


def ngrams(text: str) -> tuple[np.ndarray, np.ndarray]:
    """(codes, numbers) of the distinct letter n-grams of a text, in order of code; none if it has no letters."""
    c = _letters()[np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32)]
    c = np.concatenate([[0], c, [0]]).astype(np.int64)
    c = c[np.concatenate([[True], (c[1:] != 0) | (c[:-1] != 0)])]  # one 0 between words
    if len(c) < 3:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    if c.max() >= 64:
        return np.unique(_grams(c, _BITS), return_counts=True)
    # the common letters alone: narrow codes, which are counted faster and have the same order
    narrow = _grams(c.astype(np.int32), 6)
    if len(narrow) > 100_000:
        n = np.bincount(narrow)
        codes = np.flatnonzero(n)
        n = n[codes]
    else:
        codes, n = np.unique(narrow, return_counts=True)
        codes = codes.astype(np.int64)
    return sum((codes >> 6 * i & (63 if i < 3 else 3)) << _BITS * i for i in range(4)), n


def gram(code: int) -> tuple[int, tuple[int, ...]]:
    """(length, letter numbers) of a code."""
    size = (code >> 3 * _BITS) + 1
    return size, tuple(code >> _BITS * i & _MASK for i in range(size - 1, -1, -1))


def ranked(codes: np.ndarray, n: np.ndarray, top: int = TOP) -> np.ndarray:
    """The most frequent of distinct codes in order; of equally frequent ones the smaller code first."""
    if len(codes) > top:  # all that may be among the first, ties included
        keep = n >= np.partition(n, len(n) - top)[len(n) - top]
        codes, n = codes[keep], n[keep]
    return codes[np.lexsort((codes, -n))][:top]


class Profiles:
    """Ranked n-grams of each language, kept by code: for each code its languages and its places in their lists."""

    def __init__(self, names: list[str], lists: list[np.ndarray], top: int = TOP):
        order = sorted(range(len(names)), key=lambda i: names[i])
        self.names, self.top = [names[i] for i in order], top
        self.lists = [np.asarray(lists[i], np.int64) for i in order]
        code = np.concatenate([np.zeros(0, np.int64), *self.lists])
        by = np.argsort(code, kind="stable")
        self.codes, first = np.unique(code[by], return_index=True)
        self.starts = np.append(first, len(code))
        self.lang = np.repeat(np.arange(len(self.lists)), [len(x) for x in self.lists])[by]
        self.place = np.concatenate([np.zeros(0, np.int64), *(np.arange(len(x)) for x in self.lists)])[by]

    def judge(self, text: str | None) -> tuple[str, float]:
        """(language, score): the score is 1 less the distance over the largest possible one."""
        mine = ranked(*ngrams(text), self.top) if text else np.zeros(0, np.int64)
        if not len(mine) or not self.names:
            return UNKNOWN, 0.0
        at = np.minimum(np.searchsorted(self.codes, mine), len(self.codes) - 1)
        rank = np.flatnonzero(self.codes[at] == mine)
        first, size = self.starts[at[rank]], np.diff(self.starts)[at[rank]]
        entry = np.repeat(first - np.concatenate([[0], np.cumsum(size)[:-1]]), size) + np.arange(size.sum()) if len(rank) else rank
        # what an n-gram is nearer than the fixed distance of a missing one
        nearer = self.top - np.abs(self.place[entry] - np.repeat(rank, size) if len(rank) else entry)
        far = self.top * len(mine) - np.bincount(self.lang[entry], weights=nearer, minlength=len(self.names))
        best = int(far.argmin())
        return self.names[best], float(1 - far[best] / (self.top * len(mine)))


def has_letters(text: str | None) -> bool:
    return bool(text) and bool(_letters()[np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32)].any())


def fit(labelled: DataFrame, sample: int = SAMPLE, top: int = TOP) -> Profiles:
    """Profiles from labelled(_id, _text, _lang), rows without text or language left out. Only the ranked lists reach the driver."""
    spark = labelled.sparkSession
    rows = labelled.where("_text is not null and _lang is not null")
    sizes = rows.groupBy(F.col("_lang").alias("_of")).agg(F.least(F.lit(1.0), F.lit(float(sample)) / F.count("*")).alias("_share"))
    few = sizes.limit(MOST_BROADCAST_LANGUAGES + 1).collect()
    if not few:
        return Profiles([], [], top)
    if len(few) <= MOST_BROADCAST_LANGUAGES:
        sizes = F.broadcast(spark.createDataFrame(few, sizes.schema))
    draw = F.pmod(F.xxhash64(F.lit("language-sample"), "_id"), F.lit(1 << 30)) / F.lit(float(1 << 30))
    chosen = rows.withColumn("_draw", draw).join(sizes, (F.col("_lang") == F.col("_of")) & (F.col("_draw") < F.col("_share"))).select("_lang", "_text")

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:  # a batch's counts; they are summed before and after the exchange
            total: dict[str, list[tuple[np.ndarray, np.ndarray]]] = {}
            for lang, text in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                total.setdefault(lang, []).append(ngrams(text.as_py()))
            for lang, parts in total.items():
                codes, inverse = np.unique(np.concatenate([x for x, _ in parts]), return_inverse=True)
                n = np.bincount(inverse, weights=np.concatenate([x for _, x in parts]), minlength=len(codes)).astype(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(codes), pa.string()), pa.array(codes, pa.int64()), pa.array(n, pa.int64())], ["_lang", "code", "n"])

    found = chosen.mapInArrow(count, "_lang string, code long, n long").groupBy("_lang", "code").agg(F.sum("n").alias("n"))
    place = F.row_number().over(Window.partitionBy("_lang").orderBy(F.desc("n"), "code"))
    lists: dict[str, list[int]] = {}
    for r in found.withColumn("_place", place).where(F.col("_place") <= top).select("_lang", "_place", "code").collect():
        lists.setdefault(r["_lang"], []).append((r["_place"], r["code"]))
    return Profiles(list(lists), [np.array([c for _, c in sorted(x)], np.int64) for x in lists.values()], top)


def judged(docs: DataFrame, profiles: Profiles, id_col: str, text_col: str) -> DataFrame:
    """_id, _pred, _score for every row."""

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = [profiles.judge(t.as_py()) for t in b.column("_text")]
            yield pa.RecordBatch.from_arrays([b.column("_id"), pa.array([x[0] for x in out], pa.string()), pa.array([x[1] for x in out], pa.float64())], ["_id", "_pred", "_score"])

    rows = docs.select(F.col(id_col).alias("_id"), F.col(text_col).alias("_text"))
    return rows.mapInArrow(judge, rows.drop("_text").schema.add("_pred", "string").add("_score", "double"))


def held_out(c) -> Column:
    """Whether a document's label is kept for testing, by its identifier as text."""
    return F.coalesce(F.crc32(F.col(c).cast("string")) % 4, F.lit(0)) == 2


def training_rows(docs: DataFrame, id_col: str, text_col: str, lang_col: str) -> DataFrame:
    return docs.where(~held_out(id_col)).select(F.col(id_col).alias("_id"), F.col(text_col).alias("_text"), F.col(lang_col).alias("_lang"))


def languages(docs: DataFrame, sample: int = SAMPLE, top: int = TOP, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """For every row: doc_id, held_out, lang_pred, score.

    Null and empty texts and those without letters are `und` with score 0, and so is all if no row is labelled. Null identifiers
    count as not held out. Repeated rows give a row each. Other columns are ignored, whatever their names. An empty table gives
    no rows.
    """
    found = judged(docs, fit(training_rows(docs, id_col, text_col, lang_col), sample, top), id_col, text_col)
    return found.select(F.col("_id").alias("doc_id"), held_out("_id").alias("held_out"), F.col("_pred").alias("lang_pred"), F.col("_score").alias("score"))


def of_known_language(docs: DataFrame, least: float = 0.0, sample: int = SAMPLE, top: int = TOP, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """docs without the rows that have no language (`und`) or a score under `least`; columns and names as they are.

    If no row is labelled there is nothing to judge by: then all rows with a letter stay.
    """
    profiles = fit(training_rows(docs, id_col, text_col, lang_col), sample, top)
    place = docs.columns.index(text_col)

    def stays(text: str | None) -> bool:
        if not profiles.names:
            return has_letters(text)
        lang, score = profiles.judge(text)
        return lang != UNKNOWN and score >= least

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield b.filter(pa.array([stays(t.as_py()) for t in b.column(place)], pa.bool_()))

    return docs.mapInArrow(keep, docs.schema)
