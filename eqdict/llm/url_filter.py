"""URL filtering by pattern rules that are looked up by their rarest literal token, in DataFrame functions only.

A rule is a regular expression with literal tokens, each of which every URL that matches must contain as a whole token. The corpus
is read once to count the URLs that hold each rule token; a rule is filed under its rarest one. Then every URL's tokens fetch the
rules filed under them, and only those expressions run. A token that is in a large share of the URLs is chosen only by a rule that
has no other. A rule whose matches have no token in common (None instead of a list) runs on every URL.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

# The site rules of the contract (verdict, host, path).
SITE_RULES = [
    ("block", "net", "/"),
    ("allow", "example.net", "/en/"),
    ("block", "example.com", "/de/"),
    ("allow", "org", "/fr/"),
]
# General patterns that block where no site rule fits (pattern on host + path in lower case, literal tokens that
# are whole in every match, or None).
GENERAL_RULES = [
    (r"(^|[./-])spam[.-]?farm\d*\.", None),  # spamfarm.x, spam-farm12.x
    (r"(^|\.)ads\.", ["ads"]),
    (r"(^|\.)tracker\.", ["tracker"]),
    (r"/login(/|$)", ["login"]),
    (r"/cart(/|$)", ["cart"]),
    (r"/wp-admin(/|$)", ["wp", "admin"]),
    (r"/cgi-bin/", ["cgi", "bin"]),
]
#: Up to so many rules the index is a literal that goes to every task; beyond, tokens fetch rules by a join.
MOST_INLINE_RULES = 1000
TOKEN_SPLIT = r"[^a-z0-9]+"


def lowered(c: Column) -> Column:
    """A-Z only, as `lower` would change other letters too."""
    return F.translate(c, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def host_of(url: Column) -> Column:
    return F.when(F.locate("://", url) > 0, lowered(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1))).otherwise(F.lit(""))


def path_of(url: Column) -> Column:
    return F.when(F.locate("://", url) > 0, F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1)).otherwise(F.lit(""))


def site_rule(verdict: str, host: str, path: str) -> dict:
    """A rule for a host with its subdomains and a path prefix. Its expression runs on host, line feed, path."""
    words = [w for w in re.split(TOKEN_SPLIT, f"{host} {path.lower() if path.endswith('/') else path.lower().rpartition('/')[0]}") if w]
    return {"rule": f"{host}{path}", "verdict": verdict, "pattern": rf"^(?:[^\n]*\.)?{re.escape(host)}\n{re.escape(path)}", "tokens": words, "site": True, "weight": len(host) + len(path)}


def general_rule(pattern: str, tokens: list[str] | None) -> dict:
    return {"rule": pattern, "verdict": "block", "pattern": pattern, "tokens": tokens, "site": False, "weight": 0}


def rule_table(spark: SparkSession, site=SITE_RULES, general=GENERAL_RULES) -> DataFrame:
    rules = [site_rule(*r) for r in site] + [general_rule(*r) for r in general]
    rules = [r | {"rule_id": i} for i, r in enumerate(rules)]
    if not rules or any(r["tokens"] is not None and not r["tokens"] for r in rules):
        raise ValueError("there must be rules, and each needs a literal token, or None to run on every URL")
    listed = lambda tokens: F.lit(None).cast("array<string>") if tokens is None else F.array(*map(F.lit, tokens))
    fields = [F.struct(*((listed(r[k]) if k == "tokens" else F.lit(r[k])).alias(k) for k in rules[0])) for r in rules]
    return spark.range(1, numPartitions=1).select(F.inline(F.array(*fields)))


def indexed(rules: DataFrame, tokens: DataFrame) -> DataFrame:
    """rules with `token`, the rarest of theirs among tokens(token, n); ties go to the first in the alphabet. Rules without tokens are left out."""
    each = rules.select("rule_id", F.explode("tokens").alias("token"))
    rare = each.join(tokens, "token", "left").groupBy("rule_id").agg(F.min(F.struct(F.coalesce("n", F.lit(0)).alias("n"), "token")).alias("r"))
    return rules.join(rare, "rule_id").select("rule_id", "rule", "verdict", "pattern", "site", "weight", F.col("r.token").alias("token"))


def judge(pages: DataFrame, rules: DataFrame, id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """page_id, host, path, rule, verdict and general (the number of general rules met) for every row of pages.

    The longest site rule that fits decides, of equal length the first by name; else a URL is blocked if a general rule matches and
    allowed if none does. A null or malformed URL has an empty host and path, so no rule fits and it is allowed. Repeated rows give
    repeated rows, as the candidates are gathered inside each row's own URL. Other columns are ignored. An empty table gives none.
    """
    urls = pages.select(F.col(id_col).alias("page_id"), host_of(F.col(url_col)).alias("host"), path_of(F.col(url_col)).alias("path"))
    urls = urls.withColumn("_tokens", F.array_distinct(F.filter(F.split(F.lower(F.concat_ws(" ", "host", "path")), TOKEN_SPLIT), lambda t: t != "")))
    n_rules = rules.count()
    small = n_rules <= MOST_INLINE_RULES
    wanted = rules.select(F.explode("tokens").alias("token")).distinct()
    each = urls.select(F.explode("_tokens").alias("token"))
    counts = each.join(F.broadcast(wanted) if small else wanted, "token", "left_semi").groupBy("token").agg(F.count("*").alias("n"))
    index = indexed(rules, counts)
    always = rules.where("tokens is null").select("rule", "verdict", "pattern", "site", "weight")
    subject = F.concat("host", F.lit("\n"), "path")
    whole = F.lower(F.concat("host", "path"))

    def verdicts(found: Column) -> list[Column]:
        """found: the rules that matched, as an array of structs."""
        site = F.filter(found, lambda r: r["site"])
        best = F.try_element_at(F.array_sort(F.transform(site, lambda r: F.struct((-r["weight"]).alias("w"), r["rule"].alias("rule"), r["verdict"].alias("verdict")))), F.lit(1))
        general = F.size(F.filter(found, lambda r: ~r["site"]))
        return [best["rule"].alias("rule"), F.coalesce(best["verdict"], F.when(general > 0, "block").otherwise("allow")).alias("verdict"), general.cast("long").alias("general")]

    if small:
        # one lookup table of few rules goes to every task; candidates never leave their row
        entry = F.struct("rule", "verdict", "pattern", "site", "weight")
        filed = index.groupBy("token").agg(F.collect_list(entry).alias("rules")).agg(F.map_from_entries(F.collect_list(F.struct("token", "rules"))).alias("_index"))
        table = filed.first()["_index"]
        literal = lambda r: F.struct(F.lit(r["rule"]).alias("rule"), F.lit(r["verdict"]).alias("verdict"), F.lit(r["pattern"]).alias("pattern"), F.lit(r["site"]).alias("site"), F.lit(r["weight"]).alias("weight"))
        nothing = F.array().cast("array<struct<rule:string,verdict:string,pattern:string,site:boolean,weight:int>>")
        found = nothing
        if table:
            lookup = F.create_map(*(x for token, own in table.items() for x in (F.lit(token), F.array(*map(literal, own)))))
            candidates = F.flatten(F.transform("_tokens", lambda t: F.coalesce(F.try_element_at(lookup, t), nothing)))
            found = F.filter(candidates, lambda r: F.when(r["site"], F.rlike(subject, r["pattern"])).otherwise(F.rlike(whole, r["pattern"])))
        met = [F.when(F.rlike(subject if r["site"] else whole, F.lit(r["pattern"])), literal(r)) for r in always.collect()]
        if met:
            found = F.concat(found, F.array_compact(F.array(*met)))
        return urls.withColumn("_found", found).select("page_id", "host", "path", *verdicts(F.col("_found")))
    # a large rule set: tokens fetch rules by a join; rows are found again by host and path, which decide everything
    places = urls.select("host", "path", "_tokens").distinct()
    hits = places.select("host", "path", F.explode("_tokens").alias("token")).join(index, "token").select("host", "path", *always.columns)
    hits = hits.unionByName(places.select("host", "path").crossJoin(F.broadcast(always)))
    hits = hits.where(F.when(F.col("site"), F.rlike(subject, F.col("pattern"))).otherwise(F.rlike(whole, F.col("pattern"))))
    by_place = hits.groupBy("host", "path").agg(
        F.min(F.when(F.col("site"), F.struct((-F.col("weight")).alias("w"), "rule", "verdict"))).alias("best"),
        F.count(F.when(~F.col("site"), 1)).alias("general"),
    )
    out = urls.select("page_id", "host", "path").join(by_place, ["host", "path"], "left")
    return out.select("page_id", "host", "path", F.col("best.rule").alias("rule"), F.coalesce("best.verdict", F.when(F.col("general") > 0, "block").otherwise("allow")).alias("verdict"), F.coalesce("general", F.lit(0)).cast("long").alias("general"))
