"""A corpus pipeline of five stages, each an operator of ``divmerge.llm`` over all that the stage before has kept.

``STAGES`` lists (name, function); a function takes (spark, docs, sf_dir) and returns a DataFrame, which is written and
read again as the docs of the next. All but the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from divmerge.llm import quality
from divmerge.llm.joins import without
from divmerge.llm.minhash import one_of_each
from divmerge.llm.mixing import mix
from divmerge.llm.queries import WEIGHTS, tokenizer_file, with_domain
from divmerge.llm.segment import sample_segmentations
from divmerge.llm.substring import remove_repeats
from divmerge.session import materialize, table


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that fail the base rule or the trees go; nulls and empty texts have no words and fail. Null ids and repeated rows are judged like all others."""
    return quality.keep(docs, quality.train(docs, table(spark, sf_dir, "labels")))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each near-duplicate class one row stays, that with the least id.

    Rows are told apart by id and text: of rows that share an id each is judged by its own text, of equal rows one stays, and
    a row without an id stays only where its class has none with one. Rows without a word (null, empty) all stay.
    """
    return one_of_each(docs)


def substring_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages of 20 words or more that stand earlier are cut out; every document stays, the length column follows."""
    out = remove_repeats(docs, window=20, what="rows")
    return out.withColumn("n_chars", F.coalesce(F.length("text"), F.lit(0)).cast("long")).select(*docs.columns) if "n_chars" in docs.columns else out


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Four fifths of the tokens, shared out by weight; a document is in its leaf's prefix of the first epoch, or goes.

    Rows are told apart by id, text, language and source; rows equal in all of these go together unless the prefix holds
    them all. Null and empty texts have no tokens and stay where the prefix reaches them.
    """
    chosen = mix(with_domain(docs.select("doc_id", "text", "lang", "source")), WEIGHTS, share=0.8, max_epochs=1, with_key=True)
    gone = materialize(chosen.where("repeats = 0").select(*[F.col(c).alias(f"_{c}") for c in ("doc_id", "key", "lang", "source")]).distinct(), "not-chosen")
    leaf = lambda c: F.coalesce(F.col(c).cast("string"), F.lit("(none)")) == F.col(f"_{c}")
    same = F.col("doc_id").cast("long").eqNullSafe(F.col("_doc_id")) & (F.xxhash64("text") == F.col("_key")) & leaf("lang") & leaf("source")
    return without(docs, gone, same).select(*docs.columns)


def encode_pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sampled segmentations of every document, checked by decoding them; null and empty texts have the empty one."""
    return sample_segmentations(docs, tokenizer_file("piece_bpe_32k.model"), check=True)


STAGES = [
    ("quality rules", quality_rules),
    ("near dedup", near_dedup),
    ("substring dedup", substring_dedup),
    ("mix sources", mix_sources),
    ("encode pieces", encode_pieces),
]

#: The trees and the sampled segmentations are not SQL; ``tests/llm`` hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``."""
    docs = table(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = materialize(docs, name.replace(" ", "-"))
    return docs
