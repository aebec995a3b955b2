"""The SQL surface: sketch functions, table functions, and a vectorised prediction."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Row, SparkSession
from pyspark.sql import functions as F

from .hashing import P


def register_sketch(spark: SparkSession, sketch) -> None:
    """sketch_bucket(id, blk) and sketch_sign(id, blk), for ids below the hash's prime;
    plain SQL expressions that Catalyst inlines."""
    case = []
    for k in range(sketch.blocks):
        h = str(sketch.coef(k)[0])
        for c in sketch.coef(k)[1:4]:
            h = f"(({h}) * (id % {P}) + {c}) % {P}"
        case.append(f"WHEN {k} THEN {h}")
    body = f"CASE blk {' '.join(case)} END"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION sketch_hash(id BIGINT, blk INT) RETURNS BIGINT RETURN {body}")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION sketch_bucket(id BIGINT, blk INT) RETURNS BIGINT RETURN (sketch_hash(id, blk) DIV 2) % {sketch.width}")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sketch_sign(id BIGINT, blk INT) RETURNS BIGINT RETURN 1 - 2 * (sketch_hash(id, blk) % 2)")


def register_tables(spark: SparkSession) -> None:
    """Table functions: peel('r,c;r,c', g) gives the decoding order of lost blocks,
    gradient_code(workers, s) the cyclic code's entries, and sketch_rows(TABLE(t), n, spare,
    width, seed) partial rows of the sketch of a table (row_id, x)."""

    @F.udtf(returnType="step int, r int, c int, line string")
    class Peel:
        def eval(self, erased: str, g: int):
            from ..operators.coding import peel

            cells = {tuple(map(int, x.split(","))) for x in erased.split(";") if x}
            for k, ((r, c), line) in enumerate(peel(cells, g) or []):
                yield k, r, c, line

    @F.udtf(returnType="worker int, shard int, coef double")
    class Code:
        def eval(self, workers: int, s: int):
            from ..operators.coding import cyclic_code

            code = cyclic_code(workers, s)
            for w, p in np.argwhere(code != 0):
                yield int(w), int(p), float(code[w, p])

    @F.udtf(returnType="block int, bucket int, v array<double>")
    class SketchRows:
        """Sums its partition's rows (row_id, x) into the buckets of n + spare blocks.  Each
        partition gives its own partial rows; sum them by (block, bucket)."""

        def __init__(self):
            self.sketch, self.into = None, {}

        def eval(self, row: Row, n: int, spare: int, width: int, seed: int):
            from ..operators.sketch import BlockSketch

            if self.sketch is None:
                self.sketch = BlockSketch(n, spare, width, seed)
            x = np.asarray(row["x"], float)
            for k in range(self.sketch.blocks):
                bucket, sign = self.sketch.place_np(np.array([row["row_id"]]), k)
                key = k, int(bucket[0])
                self.into[key] = self.into.get(key, 0.0) + sign[0] * x

        def terminate(self):
            for (k, b), v in self.into.items():
                yield k, b, v.tolist()

    spark.udtf.register("sketch_rows", SketchRows)
    spark.udtf.register("peel", Peel)
    spark.udtf.register("gradient_code", Code)


def predict_margin(w):
    """A vectorised column function: x -> x . w."""
    weights = np.asarray(w, float)

    @F.pandas_udf("double")
    def margin(x: pd.Series) -> pd.Series:
        return pd.Series(np.stack(x.to_numpy()) @ weights if len(x) else [], dtype=float)

    return margin
