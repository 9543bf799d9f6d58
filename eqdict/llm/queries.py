"""The registered queries opN_<name> and, where SQL can express them, the same in DuckDB's SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from eqdict.llm import exact_dedup, language, media, mixing, near_dedup, packing, pii, substring_dedup, token_counts, url_filter

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def byte_bpe() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def query(f: Callable[[SparkSession, str], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    QUERIES[f.__name__] = f
    return f


@query
def op1_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.personal_data(documents(spark, sf_dir))


@query
def op2_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """With a cache of its own, which starts empty."""
    return token_counts.token_counts(documents(spark, sf_dir), byte_bpe())


@query
def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language.languages(documents(spark, sf_dir))


@query
def op4_poisson_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The whole mixture, copies and their global order: doc_id, text, lang, source, n_chars, copy_no, order_key."""
    return mixing.mixed(documents(spark, sf_dir), extra=True)


ORACLES["op4_poisson_mixing"] = f"""
WITH size AS (SELECT source, sum(length(coalesce(text, '')))::DOUBLE AS s FROM documents GROUP BY source),
want AS (SELECT source, s, CASE WHEN s > 0 THEN pow(s, {mixing.SMOOTHING}) ELSE 0 END AS w FROM size),
rate AS (SELECT source, CASE WHEN s > 0 THEN w / (SELECT sum(w) FROM want) * (SELECT sum(s) FROM size) / s ELSE 1 END AS r FROM want),
term AS (SELECT source, r, k::BIGINT AS k, CASE WHEN k = 0 THEN exp(-r) ELSE exp(k * ln(r) - r - lgamma(k + 1)) END AS p
         FROM rate, LATERAL (SELECT unnest(generate_series(0, ceil(r + 12 * sqrt(r) + 30)::BIGINT)) AS k)),
cdf AS (SELECT source, k, sum(p) OVER (PARTITION BY source ORDER BY k) AS c FROM term),
u AS (SELECT *, ('0x' || substr(md5('{mixing.SEED}:' || coalesce(doc_id::VARCHAR, 'null')), 1, 13))::BIGINT / {1 << 52}.0::DOUBLE AS u FROM documents),
n AS (SELECT u.doc_id, u.text, u.lang, u.source, u.n_chars, (SELECT count(*) FROM cdf WHERE cdf.source IS NOT DISTINCT FROM u.source AND cdf.c <= u.u) AS n FROM u)
SELECT doc_id, text, lang, source, n_chars, copy_no::INTEGER AS copy_no,
       md5('{mixing.SEED}:order:' || coalesce(doc_id::VARCHAR, 'null') || ':' || copy_no) AS order_key
FROM n, LATERAL (SELECT unnest(generate_series(0, n.n - 1)) AS copy_no)
"""


@query
def op5_media_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media.media_columns(documents(spark, sf_dir))


@query
def op6_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.without_repeats(documents(spark, sf_dir))


@query
def op7_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge(spark.read.parquet(f"{sf_dir}/pages.parquet"), url_filter.rule_table(spark))


def _url_sql() -> str:
    quoted = lambda s: "'" + s.replace("'", "''") + "'"
    rules = ", ".join(f"({quoted(h + p)}, {quoted(v)}, {quoted(h)}, {quoted(p)})" for v, h, p in url_filter.SITE_RULES)
    general = " + ".join(f"CASE WHEN regexp_matches(lower(host || path), {quoted(p)}) THEN 1 ELSE 0 END" for p, _ in url_filter.GENERAL_RULES)
    return f"""
WITH parts AS (
  SELECT page_id,
    CASE WHEN contains(coalesce(url, ''), '://') THEN translate(regexp_extract(url, '^.*?://([^/?#]*)', 1, 's'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') ELSE '' END AS host,
    CASE WHEN contains(coalesce(url, ''), '://') THEN regexp_extract(url, '^.*?://[^/?#]*([^?#]*)', 1, 's') ELSE '' END AS path
  FROM pages),
rules(rule, verdict, h, p) AS (VALUES {rules}),
best AS (
  SELECT x.host, x.path, arg_max(rule, length(h) + length(p)) AS rule, arg_max(verdict, length(h) + length(p)) AS verdict
  FROM (SELECT DISTINCT host, path FROM parts) x JOIN rules ON (x.host = h OR ends_with(x.host, '.' || h)) AND starts_with(x.path, p) GROUP BY ALL)
SELECT page_id, parts.host, parts.path, best.rule, ({general.replace("host", "parts.host").replace("path", "parts.path")})::BIGINT AS general,
  coalesce(best.verdict, CASE WHEN ({general.replace("host", "parts.host").replace("path", "parts.path")}) > 0 THEN 'block' ELSE 'allow' END) AS verdict
FROM parts LEFT JOIN best ON parts.host = best.host AND parts.path = best.path
"""


ORACLES["op7_url_filter"] = _url_sql()


@query
def op8_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.near_groups(documents(spark, sf_dir), words=3, percent=85)


@query
def op9_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_groups(documents(spark, sf_dir))


ORACLES["op9_exact_dedup"] = r"""
WITH t AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS body FROM documents),
d AS (SELECT doc_id, sha256(body) AS text_sha256 FROM t)
SELECT doc_id, min(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size, doc_id = min(doc_id) OVER w AS kept, text_sha256
FROM d WINDOW w AS (PARTITION BY text_sha256)
"""


@query
def op10_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.packed(documents(spark, sf_dir), byte_bpe())
