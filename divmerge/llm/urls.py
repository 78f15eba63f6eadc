"""URL filters by host-suffix and path-prefix expressions, with DataFrame functions only.

A rule is (host, path, action). It fits its host and all subdomains of it, where the path of the URL starts with the
path of the rule. Of the rules that fit, the longest (host and path together) wins, then the longer host, then block.

Each distinct URL is expanded into its host suffixes times its directory prefixes, no deeper than any rule reaches (so
the expansion is bounded by the rules, and nothing that could match is left out). A rule stands under the directory part of its
path. Expressions meet rules by an equi-join on the first 32 bits of their digests; then the full digests must agree,
and the path must start with the whole path of the rule. Rules are sent whole only if they are counted to be few;
of the URLs with a rule, those that very many pages share are broadcast too, so no page of theirs moves.

Defined results: null URLs and those without ``://`` have an empty host and path; repeated rows stay; repeated rules count once;
no rules at all leave every URL to the default; other columns of the pages do not matter.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .joins import join_counted

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: So many rules at most are broadcast.
BROADCAST_RULES = 100_000
PREFIX_CHARS = 8  # hexadecimal digits of the digest


def host_of(url: Column) -> Column:
    rest = F.when(F.contains(url, F.lit("://")), F.substring_index(url, "://", 1)).otherwise(None)
    rest = F.substring(url, F.length(rest) + 4, F.length(url))
    return F.translate(F.coalesce(F.regexp_extract(rest, r"^[^/?#]*", 0), F.lit("")), UPPER, LOWER)


def path_of(url: Column) -> Column:
    rest = F.when(F.contains(url, F.lit("://")), F.substring_index(url, "://", 1)).otherwise(None)
    rest = F.substring(url, F.length(rest) + 4, F.length(url))
    return F.coalesce(F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1), F.lit(""))


def _key(host: Column, directory: Column) -> Column:
    return F.sha2(F.concat(host, F.lit("\n"), directory), 256)


def expressions(host: Column, path: Column, labels: int, depth: int) -> Column:
    """Digests of all host suffixes of at most ``labels`` labels with all directory prefixes of at most ``depth`` slashes."""
    parts = F.split(host, r"\.", -1)
    n = F.least(F.size(parts), F.lit(labels))
    slashes = F.least(F.length(path) - F.length(F.replace(path, F.lit("/"))), F.lit(depth))
    suffixes = F.transform(F.sequence(F.lit(1), n), lambda k: F.array_join(F.slice(parts, F.size(parts) - k + 1, k), "."))
    prefixes = F.transform(F.sequence(F.lit(0), slashes), lambda k: F.when(k == 0, "").otherwise(F.concat(F.array_join(F.slice(F.split(path, "/", -1), 1, k), "/"), F.lit("/"))))
    return F.flatten(F.transform(suffixes, lambda s: F.transform(prefixes, lambda p: _key(s, p))))


def filter_urls(pages: DataFrame, rules: DataFrame, key: str = "page_id", url: str = "url", default: str = "allow") -> DataFrame:
    """``pages(key, url)`` and ``rules(host, path, action)`` to (key, host, path, rule, verdict), one row for each page."""
    rules = rules.select(F.translate("host", UPPER, LOWER).alias("r_host"), F.coalesce("path", F.lit("")).alias("r_path"), F.col("action").alias("r_action")).where("r_host is not null and r_action is not null").distinct()
    rules = rules.withColumn("r_dir", F.regexp_extract("r_path", r"(?s)^(.*/)?", 0))
    size = rules.agg(F.count("*"), F.max(F.size(F.split("r_host", r"\.", -1))), F.max(F.length("r_path") - F.length(F.replace("r_path", F.lit("/"))))).first()
    n_rules, labels, depth = size[0], size[1] or 0, size[2] or 0
    rows = pages.select(F.col(key), F.col(url).alias("url"))
    if not n_rules:
        return rows.select(key, host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"), F.lit(None).cast("string").alias("rule"), F.lit(default).alias("verdict"))
    rules = rules.withColumn("r_digest", _key(F.col("r_host"), F.col("r_dir"))).withColumn("short", F.substring("r_digest", 1, PREFIX_CHARS))
    own = rows.where("url is not null").groupBy("url").agg(F.count("*").alias("n")).select("url", "n", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"))
    each = own.select("url", "n", "path", F.explode(expressions(F.col("host"), F.col("path"), labels, depth)).alias("digest")).withColumn("short", F.substring("digest", 1, PREFIX_CHARS))
    met = each.join(F.broadcast(rules) if n_rules <= BROADCAST_RULES else rules, "short")
    met = met.where((F.col("digest") == F.col("r_digest")) & F.startswith("path", "r_path"))
    order = F.struct(F.length("r_host") + F.length("r_path"), F.length("r_host"), (F.col("r_action") == "block").cast("int"), "r_host", "r_path")
    best = met.groupBy("url", "n").agg(F.max_by(F.struct(F.concat("r_host", "r_path").alias("rule"), "r_action"), order).alias("best"))
    found = join_counted(rows, best, ["url"])
    return found.select(key, host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"), F.col("best.rule").alias("rule"), F.coalesce("best.r_action", F.lit(default)).alias("verdict"))
