"""Sentence corpora from the given tables and from users' own files. Readers pin their schemas, so only named columns are read."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.corpus import number_documents, rows_to_sentences, split_sentences, strip_html
from ..session import once, spread

DOCUMENTS = "doc_id long, text string, lang string"


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.schema(DOCUMENTS).parquet(f"{sf_dir}/documents.parquet")


def document_sentences(spark: SparkSession, sf_dir: str, unit: str = "sentence") -> DataFrame:
    """(doc_id, lang, pos, tokens): the smaller corpus, for counts that need no order."""
    return split_sentences(spread(documents(spark, sf_dir)), keep=("doc_id", "lang"), unit=unit)


def numbered_sentences(spark: SparkSession, sf_dir: str, order: str = "lang") -> DataFrame:
    """(lang, doc_id, pos, tokens, sent_id) in language order (a corpus with drift) or document order; written once in an application."""
    keys = ["lang", "doc_id"] if order == "lang" else ["doc_id"]
    return once(spark, f"{sf_dir}/documents.parquet", f"sentences-{order}", lambda: number_documents(documents(spark, sf_dir), keys))


def all_texts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(src, doc_id, text) of documents, pages without markup, and conversations: the larger corpus."""
    d = documents(spark, sf_dir).select(F.lit("documents").alias("src"), "doc_id", "text")
    p = spark.read.schema("page_id long, html string").parquet(f"{sf_dir}/pages.parquet").select(F.lit("pages").alias("src"), F.col("page_id").alias("doc_id"), strip_html(F.col("html")).alias("text"))
    c = spark.read.schema("conv_id long, turn long, text string").parquet(f"{sf_dir}/conversations.parquet")
    return d.unionByName(p).unionByName(c.select(F.lit("conversations").alias("src"), (F.col("conv_id") * 1000 + F.col("turn")).alias("doc_id"), "text"))


def all_sentences(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(src, doc_id, pos, tokens) of the larger corpus."""
    return split_sentences(all_texts(spark, sf_dir), keep=("src", "doc_id"))


def numbered_larger(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(src, doc_id, pos, tokens, sent_id) of the larger corpus; written once in an application."""
    return once(spark, f"{sf_dir}/documents.parquet", "sentences-larger", lambda: number_documents(all_texts(spark, sf_dir), ["src", "doc_id"]))


def nation_sentences(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(o_orderkey, tokens): each order as [nation, region, segment, priority, status]."""
    read = lambda t, s: spark.read.schema(s).parquet(f"{sf_dir}/{t}.parquet")
    o = read("orders", "o_orderkey long, o_custkey long, o_orderstatus string, o_orderpriority string")
    c = read("customer", "c_custkey long, c_nationkey int, c_mktsegment string")
    n, r = read("nation", "n_nationkey int, n_name string, n_regionkey int"), read("region", "r_regionkey int, r_name string")
    who = c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).join(F.broadcast(r), n.n_regionkey == r.r_regionkey)
    return rows_to_sentences(o.join(who, o.o_custkey == who.c_custkey), ["n_name", "r_name", "c_mktsegment", "o_orderpriority", "o_orderstatus"], ["o_orderkey"])


def supply_sentences(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(l_orderkey, l_linenumber, tokens): each delivery as [supplier, the supplier's nation, return flag]."""
    read = lambda t, s: spark.read.schema(s).parquet(f"{sf_dir}/{t}.parquet")
    li = spread(read("lineitem", "l_orderkey long, l_linenumber int, l_suppkey long, l_returnflag string"))
    s, n = read("supplier", "s_suppkey long, s_name string, s_nationkey int"), read("nation", "n_nationkey int, n_name string")
    who = s.join(F.broadcast(n), s.s_nationkey == n.n_nationkey)
    return rows_to_sentences(li.join(who, li.l_suppkey == who.s_suppkey), ["s_name", "n_name", "l_returnflag"], ["l_orderkey", "l_linenumber"])


def baskets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(l_orderkey, tokens): the parts of an order as words of their names, brand and type, in line order."""
    li = spark.read.schema("l_orderkey long, l_partkey long, l_linenumber int").parquet(f"{sf_dir}/lineitem.parquet")
    p = spark.read.schema("p_partkey long, p_name string, p_brand string, p_type string").parquet(f"{sf_dir}/part.parquet")
    each = li.join(p, li.l_partkey == p.p_partkey).select("l_orderkey", "l_linenumber", F.concat(F.split("p_name", " "), F.array("p_brand", "p_type")).alias("t"))
    lines = F.array_sort(F.collect_list(F.struct("l_linenumber", "t")))
    return each.groupBy("l_orderkey").agg(F.flatten(F.transform(lines, lambda s: s["t"])).alias("tokens"))


def text_lines(spark: SparkSession, path: str) -> DataFrame:
    """(line, text) of plain text files; ``line`` is unique but not dense."""
    return spark.read.text(path).select(F.monotonically_increasing_id().alias("line"), F.col("value").alias("text"))


def json_lines(spark: SparkSession, path: str, schema: str = "id string, text string") -> DataFrame:
    return spark.read.schema(schema).json(path)


def table_text(spark: SparkSession, path: str, kind: str, schema: str) -> DataFrame:
    """Text columns from csv, orc or parquet with a pinned schema."""
    reader = spark.read.schema(schema)
    return reader.option("header", True).csv(path) if kind == "csv" else getattr(reader, kind)(path)
