"""The registered queries of the subpackage, thin wrappers that derive the result columns from the operators, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import table
from . import langid, quality, toxicity
from .media import read_media, write_media
from .minhash import near_duplicates
from .mixing import mix
from .segment import sample_segmentations
from .substring import remove_repeats
from .tokenids import token_files
from .urls import filter_urls


def tokenizer_file(name: str) -> str:
    """Where a public tokenizer's file is; a parameter of the operators that read one."""
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_gumbel_segmentation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sample_segmentations(table(spark, sf_dir, "documents"), tokenizer_file("piece_bpe_32k.model"), check=True)


def op2_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))


def op3_png_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    media = read_media(write_media(table(spark, sf_dir, "documents")))
    return media.select("doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "phash")


def op4_quality_trees(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return quality.judge(docs, quality.train(docs, table(spark, sf_dir, "labels")))


def _remainder(by: int):
    return F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(by))


def op5_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    held = F.coalesce(_remainder(5) == 0, F.lit(False))
    return langid.train_and_predict(docs, _remainder(5) != 0).select("doc_id", held.alias("held_out"), "lang_pred", "score", "cross_entropy", "rejected")


#: Target weights of the mixture; a node that is not named weighs 1.
WEIGHTS = {"domain": {"web": 5, "books": 3, "code": 2}, "lang": {"en": 4, "de": 2, "fr": 2, "es": 2}, "source": {"src0": 2}}


def with_domain(docs: DataFrame) -> DataFrame:
    """The tables have no domain, so the number of the source picks one."""
    return docs.selectExpr("*", "coalesce(element_at(array('web', 'books', 'code'), cast(try_cast(regexp_extract(source, '([0-9]+)', 1) as int) % 3 as int) + 1), 'other') as domain")


def op6_hierarchical_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source")
    return mix(with_domain(docs), WEIGHTS, share=0.6, max_epochs=2)


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    held = F.coalesce(_remainder(4) == 2, F.lit(False))
    model = toxicity.train(docs, table(spark, sf_dir, "labels"), keep=_remainder(4) != 2)
    return toxicity.score(docs, model).select("doc_id", held.alias("held_out"), "score", "predicted")


URL_RULES = "VALUES ('net', '/', 'block'), ('example.net', '/en/', 'allow'), ('example.com', '/de/', 'block'), ('org', '/fr/', 'allow') AS rules(host, path, action)"


def op8_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return filter_urls(table(spark, sf_dir, "pages"), spark.sql(URL_RULES))


def op9_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_files(table(spark, sf_dir, "documents"), tokenizer_file("word_bpe_49k.json"), end_id=2)


def op10_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(table(spark, sf_dir, "documents").select("doc_id", "text"), window=20)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_gumbel_segmentation": op1_gumbel_segmentation,
    "op2_minhash_near_dedup": op2_minhash_near_dedup,
    "op3_png_media": op3_png_media,
    "op4_quality_trees": op4_quality_trees,
    "op5_language_id": op5_language_id,
    "op6_hierarchical_mixing": op6_hierarchical_mixing,
    "op7_toxicity": op7_toxicity,
    "op8_url_filter": op8_url_filter,
    "op9_token_files": op9_token_files,
    "op10_substring_dedup": op10_substring_dedup,
}

def _level_sql(parent: str, node: str, source: str, given: str, out: str) -> str:
    """One level of the budgets: the same shares, in plain windows."""
    p = parent or "1"
    keys = ", ".join(x for x in (parent, node) if x)
    return f"""
{out}_a AS (SELECT {keys}, cap, weight, {given} AS given, row_number() OVER w AS rk, sum(cap) OVER (PARTITION BY {p} ORDER BY cap / weight, {node} ROWS UNBOUNDED PRECEDING) - cap AS spent,
  sum(weight) OVER (PARTITION BY {p} ORDER BY cap / weight, {node} ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS rest FROM {source} WINDOW w AS (PARTITION BY {p} ORDER BY cap / weight, {node})),
{out}_b AS (SELECT *, CAST(given - spent AS DOUBLE) / rest AS level FROM {out}_a),
{out}_c AS (SELECT *, min(CASE WHEN cap > level * weight THEN rk END) OVER (PARTITION BY {p}) AS at_rank FROM {out}_b),
{out}_d AS (SELECT *, max(CASE WHEN rk = at_rank THEN level END) OVER (PARTITION BY {p}) AS at_level FROM {out}_c),
{out} AS (SELECT {keys}, CAST(CASE WHEN at_rank IS NULL OR rk < at_rank THEN cap ELSE floor(at_level * weight) END AS BIGINT) AS budget FROM {out}_d)"""


def _case(level: str) -> str:
    return f"CAST(CASE {level} " + " ".join(f"WHEN '{k}' THEN {v}" for k, v in WEIGHTS[level].items()) + " ELSE 1 END AS BIGINT)"


MIX_SQL = rf"""
WITH rows_ AS (SELECT doc_id, coalesce(CASE CAST(nullif(regexp_extract(source, '([0-9]+)', 1), '') AS INT) % 3 WHEN 0 THEN 'web' WHEN 1 THEN 'books' WHEN 2 THEN 'code' END, 'other') AS domain,
  coalesce(lang, '(none)') AS lang, coalesce(source, '(none)') AS source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS n_tokens FROM documents),
leaves AS (SELECT domain, lang, source, CAST(sum(n_tokens) AS BIGINT) AS tokens, CAST(sum(n_tokens) * 2 AS BIGINT) AS cap, {_case("source")} AS weight FROM rows_ GROUP BY ALL),
l1 AS (SELECT domain, CAST(sum(cap) AS BIGINT) AS cap, {_case("domain")} AS weight FROM leaves GROUP BY domain),
total AS (SELECT CAST(floor(sum(n_tokens) * CAST(0.6 AS DOUBLE)) AS BIGINT) AS b FROM rows_),
{_level_sql("", "domain", "l1", "(SELECT b FROM total)", "b1")},
l2 AS (SELECT domain, lang, sum(cap) AS cap, {_case("lang")} AS weight, any_value(b1.budget) AS given FROM leaves JOIN b1 USING (domain) GROUP BY domain, lang),
{_level_sql("domain", "lang", "l2", "given", "b2")},
l3 AS (SELECT leaves.*, b2.budget AS given FROM leaves JOIN b2 USING (domain, lang)),
{_level_sql("domain, lang", "source", "l3", "given", "b3")},
leaf AS (SELECT domain, lang, source, tokens, budget, CASE WHEN tokens > 0 THEN budget // tokens ELSE 0 END AS epochs FROM leaves JOIN b3 USING (domain, lang, source)),
drawn AS (SELECT *, ('0x' || substr(md5('17:' || epochs || ':' || doc_id), 1, 15))::BIGINT AS draw FROM rows_ JOIN leaf USING (domain, lang, source)),
run AS (SELECT *, sum(n_tokens) OVER (PARTITION BY domain, lang, source ORDER BY draw, doc_id ROWS UNBOUNDED PRECEDING) AS reach FROM drawn)
SELECT doc_id, domain, lang, source, n_tokens, tokens AS leaf_tokens, budget AS leaf_budget, CAST(epochs + CASE WHEN reach <= budget - epochs * tokens THEN 1 ELSE 0 END AS BIGINT) AS repeats FROM run
"""


ORACLE_SQL: dict[str, str] = {
    "op6_hierarchical_mixing": MIX_SQL,
    "op8_url_filter": r"""
WITH rules(r_host, r_path, action) AS (VALUES ('net', '/', 'block'), ('example.net', '/en/', 'allow'), ('example.com', '/de/', 'block'), ('org', '/fr/', 'allow')),
cut AS (SELECT page_id, CASE WHEN contains(url, '://') THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages),
own AS (SELECT page_id, translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM cut),
fit AS (SELECT page_id, r_host || r_path AS rule, action, row_number() OVER (PARTITION BY page_id ORDER BY length(r_host || r_path) DESC, length(r_host) DESC, action DESC) AS n
  FROM own JOIN rules ON (host = r_host OR ends_with(host, '.' || r_host)) AND starts_with(path, r_path))
SELECT own.page_id, host, path, rule, coalesce(action, 'allow') AS verdict FROM own LEFT JOIN fit ON own.page_id = fit.page_id AND n = 1
""",
    "op10_substring_dedup": r"""
WITH w AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents),
win AS (SELECT doc_id, s, array_to_string(ws[s:s + 19], ' ') AS k FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 18)) AS s FROM w)),
dup AS (SELECT doc_id, s FROM (SELECT doc_id, s, row_number() OVER (PARTITION BY k ORDER BY doc_id, s) AS n FROM win) WHERE n > 1),
gone AS (SELECT DISTINCT doc_id, s + i AS p FROM (SELECT doc_id, s, unnest(range(0, 20)) AS i FROM dup)),
words AS (SELECT doc_id, unnest(ws) AS word, generate_subscripts(ws, 1) AS p FROM w),
kept AS (SELECT doc_id, string_agg(word, ' ' ORDER BY p) AS t, count(*) AS n FROM words ANTI JOIN gone USING (doc_id, p) GROUP BY doc_id)
SELECT w.doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(len(ws) - coalesce(n, 0) AS BIGINT) AS n_removed, sha256(coalesce(t, '')) AS kept_sha256
FROM w LEFT JOIN kept USING (doc_id)
""",
}
