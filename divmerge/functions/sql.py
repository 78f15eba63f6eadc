"""Functions for SQL users, all of them SQL bodies, so that their plans are native: vector functions, and table functions of word pairs and neighbours."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

_DOT = "aggregate(zip_with(a, b, (x, y) -> cast(x as double) * cast(y as double)), cast(0 as double), (s, x) -> s + x)"
_NORM = "sqrt(aggregate(a, cast(0 as double), (s, x) -> s + cast(x as double) * cast(x as double)))"
FUNCTIONS = {
    "vec_dot": ("a ARRAY<FLOAT>, b ARRAY<FLOAT>", "DOUBLE", _DOT),
    "vec_norm": ("a ARRAY<FLOAT>", "DOUBLE", _NORM),
    "vec_cosine": ("a ARRAY<FLOAT>, b ARRAY<FLOAT>", "DOUBLE", f"nullif({_DOT} / nullif({_NORM} * {_NORM.replace('aggregate(a,', 'aggregate(b,')}, 0), double('nan'))"),
    "miss_threshold": ("u DOUBLE, ell DOUBLE", "DOUBLE", "1 - power(1 - u, (1 - u) / (ell * u))"),
}
#: Pairs of an array of tokens, ``win`` positions to either side.
PAIRS = """SELECT p.word, p.ctx FROM (SELECT explode(flatten(transform(tokens, (w, i) -> transform(
    concat(slice(tokens, greatest(1, i + 1 - win), least(win, i)), slice(tokens, i + 2, win)), c -> named_struct('word', w, 'ctx', c))))) AS p)"""


def register(spark: SparkSession) -> None:
    """Make ``vec_dot``, ``vec_norm``, ``vec_cosine``, ``miss_threshold`` and the table function ``window_pairs(tokens, win)`` known to SQL."""
    for name, (args, kind, body) in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {kind} RETURN {body}")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION window_pairs(tokens ARRAY<STRING>, win INT) RETURNS TABLE (word STRING, ctx STRING) RETURN {PAIRS}")


def register_neighbours(emb: DataFrame, name: str = "neighbours", k: int = 10) -> None:
    """The table function ``name(q)``: rows (word, score) of the ``k`` words of ``emb(word, vec)`` nearest to a vector, for lateral joins with a few queries."""
    spark = emb.sparkSession
    register(spark)
    emb.createOrReplaceTempView(f"_{name}_vectors")
    body = f"SELECT word, score FROM (SELECT word, vec_cosine(vec, q) AS score FROM _{name}_vectors) ORDER BY score DESC, word LIMIT {int(k)}"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(q ARRAY<FLOAT>) RETURNS TABLE (word STRING, score DOUBLE) RETURN {body}")
