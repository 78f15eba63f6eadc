"""Mixing sources to target weights by hierarchical budgets, with DataFrame functions only.

The sources are leaves of a tree (domain, language, source). A token budget goes down from the root: the children of a
node share its budget by their weights, none above what it can give (its tokens times ``max_epochs``, summed over its
leaves). What a child cannot give goes to its siblings by weight; because a node never receives more than its leaves
hold, a shortage reaches the ancestors' siblings only where all siblings are full. Shares are whole tokens, so less than
one token for each child of a node stays unspent.

A leaf spends its budget in epochs: all its documents once for each full epoch, then the documents that come first in
the seeded order of the next epoch, as long as their tokens fit (a token prefix). The prefix of a leaf is found
without bringing the leaf together: documents fall into ranges of the order, ``RANGE_DOCS`` in each on average whatever the leaf's
size, the ranges are summed, and only inside a range are documents ordered (by narrow rows; this bounds the largest window).

Defined results: null in a level is the node ``(none)``; null or empty text has no tokens and comes along where the prefix
reaches it; weights that are missing are 1 and negative ones 0; a null id is drawn by a hash of the text, and rows with equal draws
are ordered by id, length and hash; repeated rows count each; extra columns do not matter; no rows give no rows.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..session import materialize

LEVELS = ("domain", "lang", "source")
RANGE_DOCS = 8192
WORD = r"[^\x20\x09-\x0D]+"


def draw(seed: int, *key: Column) -> Column:
    """60 random bits of a key."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), *[k.cast("string") for k in key])), 1, 15), 16, 10).cast("long")


def share_out(children: DataFrame, parent: Sequence[str], node: str) -> DataFrame:
    """Add ``budget`` to children(parent..., node, cap, weight, given): shares of ``given`` by weight, none above ``cap``.

    In order of cap / weight, a child is full if its cap is at most its share of what is left; the first that is not full
    sets the level for all after it.
    """
    w = Window.partitionBy(*parent).orderBy(F.col("cap") / F.col("weight"), node)
    full = Window.partitionBy(*parent)
    out = children.withColumn("rank", F.row_number().over(w))
    out = out.withColumn("spent", F.sum("cap").over(w.rowsBetween(Window.unboundedPreceding, 0)) - F.col("cap"))
    out = out.withColumn("rest", F.sum("weight").over(w.rowsBetween(0, Window.unboundedFollowing)))
    out = out.withColumn("level", (F.col("given") - F.col("spent")).cast("double") / F.col("rest"))
    short = F.when(F.col("cap") > F.col("level") * F.col("weight"), F.struct("rank", "level"))
    out = out.withColumn("at", F.min(short).over(full))
    budget = F.when(F.col("at").isNull() | (F.col("rank") < F.col("at.rank")), F.col("cap")).otherwise(F.floor(F.col("at.level") * F.col("weight")))
    return out.withColumn("budget", budget.cast("long")).drop("rank", "spent", "rest", "level", "at", "given")


def budgets(leaves: DataFrame, weights: dict[str, dict[str, int]], total: int, max_epochs: int, levels: Sequence[str] = LEVELS) -> DataFrame:
    """``leaves(levels..., tokens, docs)`` with the ``budget`` of each leaf."""
    leaves = leaves.withColumn("cap", F.col("tokens") * max_epochs)
    given = None
    for k, level in enumerate(levels):
        path = list(levels[: k + 1])
        known = {n: max(0, int(w)) for n, w in weights.get(level, {}).items()}
        weight = F.coalesce(F.create_map(*[F.lit(x) for kv in known.items() for x in kv])[F.col(level)], F.lit(1)) if known else F.lit(1)
        nodes = (leaves.groupBy(*path).agg(F.sum("cap").alias("cap")) if k + 1 < len(levels) else leaves).withColumn("weight", weight.cast("long"))
        nodes = nodes.withColumn("cap", F.when(F.col("weight") > 0, F.col("cap")).otherwise(F.lit(0))).withColumn("weight", F.greatest("weight", F.lit(1)))
        nodes = nodes.withColumn("given", F.lit(total).cast("long")) if given is None else nodes.join(given, path[:-1])
        done = share_out(nodes, path[:-1] or [F.lit(0)], level)
        given = done.select(*path, F.col("budget").alias("given"))
    return done.select(*levels, "tokens", "docs", "budget")


def mix(docs: DataFrame, weights: dict[str, dict[str, int]], share: float = 0.6, max_epochs: int = 2, seed: int = 17, levels: Sequence[str] = LEVELS, with_key: bool = False) -> DataFrame:
    """``docs(doc_id, text, levels...)`` to (doc_id, levels..., n_tokens, leaf_tokens, leaf_budget, repeats[, key]), a row for each document.

    ``share`` of all tokens is the budget of the root; ``repeats`` says how often the document is to be read; ``key`` is a hash of the text.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), *[F.coalesce(F.col(x).cast("string"), F.lit("(none)")).alias(x) for x in levels], F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long").alias("n_tokens"), F.xxhash64("text").alias("key"))
    rows = materialize(rows, "mix-rows")
    leaves = rows.groupBy(*levels).agg(F.sum("n_tokens").alias("tokens"), F.count("*").alias("docs"))
    total = int((rows.agg(F.sum("n_tokens")).first()[0] or 0) * share)
    leaf = budgets(leaves, weights, total, max_epochs, levels)
    leaf = leaf.withColumn("epochs", F.when(F.col("tokens") > 0, F.floor(F.col("budget") / F.col("tokens"))).otherwise(0).cast("long"))
    leaf = leaf.withColumn("left_over", F.col("budget") - F.col("epochs") * F.col("tokens")).withColumn("ranges", (F.col("docs") / RANGE_DOCS).cast("long") + 1)
    leaf = materialize(leaf, "mix-leaves")
    own = rows.join(leaf, list(levels)).withColumn("draw", draw(seed, F.col("epochs"), F.coalesce("doc_id", "key")))
    own = own.withColumn("range", F.shiftright(F.shiftright("draw", 20) * F.col("ranges"), 40))
    key = [*levels, "range"]
    sums = own.groupBy(*key).agg(F.sum("n_tokens").alias("in_range"))
    sums = sums.withColumn("before", F.sum("in_range").over(Window.partitionBy(*levels).orderBy("range").rowsBetween(Window.unboundedPreceding, 0)) - F.col("in_range")).drop("in_range")
    inner = Window.partitionBy(*key).orderBy("draw", "doc_id", "n_tokens", "key").rowsBetween(Window.unboundedPreceding, 0)
    own = own.join(sums, key).withColumn("reach", F.col("before") + F.sum("n_tokens").over(inner))
    return own.select("doc_id", *levels, "n_tokens", F.col("tokens").alias("leaf_tokens"), F.col("budget").alias("leaf_budget"), (F.col("epochs") + (F.col("reach") <= F.col("left_over")).cast("long")).alias("repeats"), *["key"] * with_key)
