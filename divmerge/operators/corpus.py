"""From tables to sentences: cleaning, splitting, tokens, dense numbers, pairs and bigrams."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, IntegerType, StructField, StructType

from ..session import cores, materialize, ship

SENTENCE_END = r"[.!?]+\s+|\n+"
TOKEN = r"\p{L}+"
NOT_TEXT = r"(?is)<script.*?</script>|<style.*?</style>|<!--.*?-->|<[^>]*>|&[#a-z0-9]+;"


def strip_html(html: Column) -> Column:
    """Text of a page: scripts, styles, comments, tags and entities become spaces."""
    return F.trim(F.regexp_replace(F.regexp_replace(html, NOT_TEXT, " "), r"\s+", " "))


def tokenize(text: Column) -> Column:
    return F.regexp_extract_all(text, F.lit(TOKEN), 0)


def split_sentences(df: DataFrame, text: str = "text", keep: Sequence[str] = ("doc_id",), unit: str = "sentence") -> DataFrame:
    """(keep..., pos, tokens): one row for each sentence (or text) with a token."""
    low = F.lower(F.col(text))
    parts = F.split(low, SENTENCE_END) if unit == "sentence" else F.array(low)
    out = df.where(F.col(text).isNotNull()).select(*keep, F.posexplode(parts).alias("pos", "s"))
    return out.select(*keep, "pos", tokenize(F.col("s")).alias("tokens")).where(F.size("tokens") > 0)


def _numbered(rows: DataFrame) -> DataFrame:
    """Dense ``sent_id`` in the order of partitions and of the rows in them: written once, plus the sizes of the partitions before.

    No window over the whole corpus; only one count a partition reaches the driver.
    """
    rows = materialize(rows.withColumn("_at", F.monotonically_increasing_id()), "numbered")
    part, local = F.shiftright("_at", 33), F.col("_at").bitwiseAND(F.lit((1 << 33) - 1))
    sizes = rows.groupBy(part.alias("part")).agg(F.count("*").alias("n")).orderBy("part").collect()
    total, before = 0, []
    for r in sizes:
        before.append((int(r["part"]), total))
        total += r["n"]
    offsets = rows.sparkSession.createDataFrame(before or [(0, 0)], "part long, before long")
    return rows.withColumn("part", part).join(F.broadcast(offsets), "part").withColumn("sent_id", F.col("before") + local).drop("_at", "part", "before")


def number_sentences(sent: DataFrame, order_by: Sequence[str]) -> DataFrame:
    """Add dense ``sent_id`` 0..N-1 in ``order_by``: one exchange by ranges, sorted inside."""
    return _numbered(sent.repartitionByRange(cores(sent.sparkSession), *order_by).sortWithinPartitions(*order_by))


def number_documents(docs: DataFrame, order_by: Sequence[str], text: str = "text", unit: str = "sentence") -> DataFrame:
    """(order_by..., pos, tokens, sent_id) of ``docs(order_by..., text)``, in the order of documents and of sentences in them.

    The exchange moves whole texts and the split comes after it: once, in all tasks, whatever the number of input files.
    """
    rows = docs.select(*order_by, text).repartitionByRange(cores(docs.sparkSession), *order_by).sortWithinPartitions(*order_by)
    return _numbered(split_sentences(rows, text, order_by, unit))


def rows_to_sentences(df: DataFrame, cols: Sequence[str], keep: Sequence[str]) -> DataFrame:
    """Rows of a table as sentences: the values of ``cols`` are the tokens."""
    return df.select(*keep, F.array(*[F.col(c).cast("string") for c in cols]).alias("tokens"))


def dedup_texts(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """The first document (least key) of each distinct text, by a 128-bit digest."""
    return docs.groupBy(F.md5(F.coalesce(F.col(text), F.lit(""))).alias("digest")).agg(F.min(key).alias(key), F.count("*").alias("copies")).drop("digest")


def token_counts(sent: DataFrame, *by: str) -> DataFrame:
    return sent.select(*by, F.explode("tokens").alias("word")).groupBy(*by, "word").agg(F.count("*").alias("cnt"))


def bigrams(sent: DataFrame, *by: str) -> DataFrame:
    """Counts of adjacent words: (by..., w1, w2, cnt)."""
    t = F.col("tokens")
    pairs = F.arrays_zip(F.slice(t, F.lit(1), F.size(t) - 1).alias("w1"), F.slice(t, F.lit(2), F.size(t) - 1).alias("w2"))
    return sent.where(F.size(t) > 1).select(*by, F.inline(pairs).alias("w1", "w2")).groupBy(*by, "w1", "w2").agg(F.count("*").alias("cnt"))


def window_pairs(sent: DataFrame, win: int, *by: str) -> DataFrame:
    """Counts of (word, ctx) with ctx at most ``win`` positions away on either side: (by..., word, ctx, cnt).

    A sentence's pairs are made in its row, to the right only, and counted both ways after the first count.
    """
    t, n = F.col("tokens"), F.size("tokens")
    ahead = F.transform(t, lambda w, i: F.transform(F.slice(t, i + 2, F.lit(win)), lambda c: F.struct(w.alias("word"), c.alias("ctx"))))
    once = sent.where(n > 1).select(*by, F.inline(F.flatten(ahead)).alias("word", "ctx")).groupBy(*by, "word", "ctx").agg(F.count("*").alias("k"))
    both = F.explode(F.array(F.struct("word", "ctx"), F.struct(F.col("ctx").alias("word"), F.col("word").alias("ctx"))))
    return once.select(*by, "k", both.alias("p")).groupBy(*by, F.col("p.word").alias("word"), F.col("p.ctx").alias("ctx")).agg(F.sum("k").alias("cnt"))


#: The largest vocabulary that goes along with every task.
MAX_VOCABULARY = 1_000_000


def vocabulary_of(vocab: DataFrame) -> tuple[pa.Array, np.ndarray]:
    """Words and counts of ``vocab(word, word_id, cnt)`` in the order of their dense ids; raises beyond ``MAX_VOCABULARY``."""
    rows = vocab.select("word", F.col("word_id").cast("int").alias("word_id"), F.col("cnt").cast("long").alias("cnt")).limit(MAX_VOCABULARY + 1).toArrow().sort_by("word_id")
    if rows.num_rows > MAX_VOCABULARY:
        raise ValueError(f"a vocabulary for all tasks holds at most {MAX_VOCABULARY} words")
    return rows["word"].combine_chunks().cast(pa.string()), rows["cnt"].to_numpy().astype(np.float64)


def ids_of(tokens: pa.Array, words: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """For a list column of words: the ids of the known ones in a row, and how many each list has."""
    flat, offs = tokens.flatten(), tokens.offsets.to_numpy() if isinstance(tokens, pa.ListArray) else np.asarray(tokens.offsets)
    got = pc.fill_null(pc.index_in(flat.cast(pa.string()), value_set=words), -1).to_numpy(zero_copy_only=False)
    known = got >= 0
    upto = np.concatenate([[0], np.cumsum(known)])[offs - offs[0]]
    return got[known].astype(np.int32), np.diff(upto)


def encode(sent: DataFrame, vocab: DataFrame | pa.Array) -> DataFrame:
    """Replace ``tokens`` by ``ids`` of ``vocab(word, word_id, cnt)`` (or of its words in order), dropping unknown words and empty sentences."""
    words = vocab if isinstance(vocab, pa.Array) else vocabulary_of(vocab)[0]
    ship(sent.sparkSession)
    kept = [c for c in sent.columns if c != "tokens"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids, size = ids_of(b.column("tokens"), words)
            lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(size)]).astype(np.int32)), pa.array(ids))
            out = pa.RecordBatch.from_arrays([*(b.column(c) for c in kept), lists], names=[*kept, "ids"])
            yield out.filter(pa.array(size > 0))

    schema = StructType([sent.schema[c] for c in kept] + [StructField("ids", ArrayType(IntegerType()))])
    return sent.select(*kept, "tokens").mapInArrow(run, schema)
