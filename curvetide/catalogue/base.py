"""Registration, fixed test weights, and pieces of oracle SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.columns import r6


class Registry(dict):
    def add(self, sql: str | None = None, name: str | None = None):
        def take(f):
            self[name or f.__name__] = (lambda spark, sf_dir, f=f: widened(f(spark, sf_dir)), sql)
            return f

        return take


def widened(df: DataFrame) -> DataFrame:
    """Integers as BIGINT, other numbers as DOUBLE, as the oracles have them."""
    cast = {"int": "long", "smallint": "long", "tinyint": "long", "float": "double"}
    return df.select(*[F.col(f"`{n}`").cast(cast[t]).alias(n) if t in cast else F.col(f"`{n}`") for n, t in df.dtypes])


def w_fix(d: int) -> list[float]:
    """Fixed weights for tests of single evaluations."""
    return [((i * 7 + 3) % 11 - 5) / 10.0 for i in range(d)]


W_SQL = "(((i * 7 + 3) % 11 - 5) / 10.0)"


def rounded(df: DataFrame, *columns: str) -> DataFrame:
    for c in columns:
        df = df.withColumn(c, r6(F.col(c)))
    return df


def emb(q: int = 64) -> str:
    """CTEs e (row_id, y, label, x) and a (row_id, y, label, i, v) of the embeddings."""
    return f"""WITH e AS (SELECT vec_id AS row_id, CASE WHEN label < 5 THEN 1.0 ELSE -1.0 END::DOUBLE AS y, label::BIGINT AS label, embedding::DOUBLE[] AS x FROM embeddings),
a AS (SELECT row_id, y, label, r.i, x[r.i + 1] AS v FROM e, (SELECT unnest(range(0, {q})) AS i) r)"""


def margin(q: int = 64) -> str:
    return f"{emb(q)},\nm AS (SELECT row_id, y, sum(v * {W_SQL}) AS t FROM a GROUP BY row_id, y)"


SIG = "(1 / (1 + exp(-(t))))"
