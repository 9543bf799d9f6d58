"""Membership filters: a dictionary from keys to fingerprints. Stored keys always hit; others with probability 2^-k."""

from __future__ import annotations

from dataclasses import replace as with_

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from eqdict.functions.hashing import digest, gf2_affine, seed_of
from eqdict.operators.build import build, key_columns
from eqdict.operators.probe import looked_up
from eqdict.sources.store import Store
from eqdict.spec import DictSpec


def fingerprint(df: DataFrame, keys: list[str] | str, spec: DictSpec) -> Column:
    """k bits of a pairwise independent hash whose seed no other use shares."""
    hi, lo = digest(key_columns(df, keys), spec.digest)
    return gf2_affine(hi, lo, seed_of("fingerprint", spec.seed), spec.k)


def build_filter(df: DataFrame, keys: list[str] | str, k: int = 8, path: str | None = None, n_rows: int | None = None, **how) -> Store:
    """A filter of the keys of df. Repeated keys are one; null keys follow on_null."""
    spec = DictSpec(k=k, **how)
    spec = with_(spec, membership=True)
    names = [keys] if isinstance(keys, str) else list(keys)
    only = df.select(*names)
    value = fingerprint(only, names, spec)
    if spec.on_null == "error":  # the build reports a null key by that name
        value = F.coalesce(value, F.lit(0).cast("long"))
    return build(only, names, value, spec, path, n_rows)


def contains(store: Store, df: DataFrame, keys: list[str] | str, out: str = "hit") -> DataFrame:
    """df with a boolean: false is certain, true is certain but for 2^-k of the keys that are not stored. Null keys give null."""
    if not store.spec.membership:
        raise ValueError("the store is a dictionary, not a filter")
    got = looked_up(store, df.withColumn("_fp", fingerprint(df, keys, store.spec)), keys, "_got", filled="_filled")
    hit = F.col("_got") == F.col("_fp")
    if store.spec.strict_empty:  # nothing is stored in an empty cell
        hit = hit & F.col("_filled")
    return got.select(*df.columns, F.when(F.col("_got").isNotNull(), hit).alias(out))


def where_contains(store: Store, df: DataFrame, keys: list[str] | str) -> DataFrame:
    return contains(store, df, keys, "_hit").where("_hit").drop("_hit")


def prefiltered_join(left: DataFrame, right: DataFrame, on: list[str] | str, k: int = 8, how: str = "inner", **build_how) -> DataFrame:
    """left joined with right, exactly; rows of left that a filter of right's keys rules out never reach the shuffle."""
    if how not in ("inner", "left_semi"):
        raise ValueError("only inner and left_semi joins may lose rows of the left side early")
    names = [on] if isinstance(on, str) else list(on)
    store = build_filter(right.dropna(subset=names), names, k, **({"on_null": "drop"} | build_how))
    return where_contains(store, left, names).join(right, names, how)


def verified_anti(left: DataFrame, right: DataFrame, on: list[str] | str, k: int = 8) -> DataFrame:
    """Rows of left whose key right lacks. What the filter rejects is certain; only its hits are compared exactly."""
    names = [on] if isinstance(on, str) else list(on)
    store = build_filter(right.dropna(subset=names), names, k, on_null="drop")
    tested = contains(store, left, names, "_hit")
    sure = tested.where("_hit is null or not _hit").drop("_hit")
    return sure.unionByName(tested.where("_hit").drop("_hit").join(right.select(*names).distinct(), names, "left_anti"))


def checked_lookup(df: DataFrame, keys: list[str] | str, value: str, k: int, check_bits: int, **how):
    """(store, probe function): a dictionary of k + check_bits bits that also says, but for 2^-check_bits, whether a key is stored."""
    spec = DictSpec(k=k + check_bits, **how)
    fp = gf2_affine(*digest(key_columns(df, keys), spec.digest), seed_of("check", spec.seed), check_bits)
    store = build(df, keys, F.shiftleft(fp, k).bitwiseOR(F.col(value).cast("long")), spec)

    def probe(other: DataFrame, out: str = "value") -> DataFrame:
        mine = gf2_affine(*digest(key_columns(other, keys), spec.digest), seed_of("check", spec.seed), check_bits)
        got = looked_up(store, other.withColumn("_fp", mine), keys, "_got")
        return got.select(*other.columns, F.when(F.shiftrightunsigned("_got", k) == F.col("_fp"), F.col("_got").bitwiseAND(F.lit((1 << k) - 1).cast("long"))).alias(out))

    return store, probe


# --- edit distance 1 ------------------------------------------------------------------------------------------------------------

ALPHABET = "abcdefghijklmnopqrstuvwxyz0123456789"


def edit1_variants(word: Column, alphabet: str = ALPHABET) -> Column:
    """All words within one insertion, deletion or substitution of a word, itself included."""
    letters = F.array(*map(F.lit, alphabet))
    at = F.sequence(F.lit(0), F.length(word))
    head = lambda i: F.substring(word, F.lit(1), i)
    tail = lambda i: F.substring(word, i + 1, F.greatest(F.length(word) - i, F.lit(0)))
    inserted = F.flatten(F.transform(at, lambda i: F.transform(letters, lambda c: F.concat(head(i), c, tail(i)))))
    inner = F.filter(at, lambda i: i < F.length(word))
    deleted = F.transform(inner, lambda i: F.concat(head(i), tail(i + 1)))
    changed = F.flatten(F.transform(inner, lambda i: F.transform(letters, lambda c: F.concat(head(i), c, tail(i + 1)))))
    return F.array_distinct(F.concat(F.array(word), inserted, deleted, changed))


def contains_within1(store: Store, df: DataFrame, word: str, out: str = "hit", alphabet: str = ALPHABET) -> DataFrame:
    """df with whether any variant of its word is in the filter. A row's variants stay with the row's word; equal words are tried once."""
    words = df.select(F.col(word).alias("_w")).where("_w is not null").distinct()
    tried = words.select("_w", F.explode(edit1_variants(F.col("_w"), alphabet)).alias(word))
    hits = contains(store, tried, word, "_hit").groupBy("_w").agg(F.max(F.col("_hit").cast("int")).alias("_any"))
    return df.join(hits, df[word] == hits["_w"], "left").select(*(df[c] for c in df.columns), (F.col("_any") == 1).alias(out))
