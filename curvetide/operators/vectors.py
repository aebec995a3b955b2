"""Sums of packed vectors: partial sums inside partitions, then by key."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def pack(v: np.ndarray) -> bytes:
    return np.ascontiguousarray(v, np.float64).tobytes()


def unpack(raw: bytes) -> np.ndarray:
    return np.frombuffer(raw, np.float64)


def matrix(column, d: int) -> np.ndarray:
    """An Arrow list<double> column as (rows, d)."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    flat = column.flatten().to_numpy(zero_copy_only=False)
    if len(flat) != len(column) * d:
        raise ValueError("ragged rows")
    return flat.reshape(len(column), d)


BLOCK = 1 << 20  # bytes of a packed block of rows


def _narrow(x: np.ndarray) -> bytes:
    """The entries as doubles, or as bytes where all are whole numbers that fit."""
    with np.errstate(invalid="ignore"):
        small = x.astype(np.int8)
    same = small.astype(np.float64).view(np.int64) == np.ascontiguousarray(x, np.float64).view(np.int64)  # tells -0.0 and NaN
    return small.tobytes() if same.all() else np.ascontiguousarray(x, np.float64).tobytes()


def packed(df: DataFrame, d: int, flag: str | None = None) -> DataFrame:
    """(ids, ys, xs) of (row_id, y, x): rows in their order, packed in blocks of about a
    megabyte, which pass to Python without a conversion of each entry.

    With ``flag``, a truth column, rows of either value have blocks of their own, which have
    the column too."""
    step = max(1, BLOCK // (8 * d))

    def run(batches):
        for batch in batches:
            x, y, ids = matrix(batch.column("x"), d), batch.column("y").to_numpy(), batch.column("row_id").to_numpy()
            of = batch.column(flag).to_numpy(zero_copy_only=False) if flag else np.zeros(len(y), bool)
            for side in (False, True) if flag else (False,):
                at = of == side
                i, v, u = (ids, y, x) if at.all() else (ids[at], y[at], x[at])
                cut = range(0, len(v), step)
                cols = [pa.array([f(w[lo : lo + step]) for lo in cut], pa.binary()) for f, w in ((lambda w: np.ascontiguousarray(w).tobytes(), i), (lambda w: np.ascontiguousarray(w).tobytes(), v), (_narrow, u))]
                yield pa.record_batch([*cols, *([pa.array([side] * len(cut), pa.bool_())] if flag else [])], names=["ids", "ys", "xs", *([flag] if flag else [])])

    more = [flag] if flag else []
    return df.select("row_id", F.col("y").cast("double").alias("y"), "x", *more).mapInArrow(run, "ids binary, ys binary, xs binary" + "".join(f", {c} boolean" for c in more))


def rows_of(batches, d: int, drawn=None):
    """(row ids, y, x) of Arrow batches of rows, of packed blocks, or of ids whose rows are
    ``drawn``, about a megabyte at a time."""
    step = max(1, BLOCK // (8 * d))
    for batch in batches:
        if drawn is not None:
            ids = batch.column("row_id").to_numpy()
            for lo in range(0, len(ids), step):
                yield ids[lo : lo + step], *drawn(ids[lo : lo + step])
        elif "xs" in batch.schema.names:
            for ids, ys, xs in zip(*(batch.column(c) for c in ("ids", "ys", "xs"))):
                y, raw = np.frombuffer(ys.as_buffer(), np.float64), xs.as_buffer()
                x = np.frombuffer(raw, np.int8).astype(np.float64) if raw.size == len(y) * d else np.frombuffer(raw, np.float64)
                yield np.frombuffer(ids.as_buffer(), np.int64), y, x.reshape(len(y), d)
        else:
            yield batch.column("row_id").to_numpy(), batch.column("y").to_numpy(), matrix(batch.column("x"), d)


def sum_packed(parts: DataFrame, keys: list[str], value: str = "v", fan: int = 0) -> DataFrame:
    """Sum the packed vectors of each key.  With ``fan`` the sums go through that many
    groups for each key first, so that no task reads the partials of all tasks."""
    spec = ", ".join(f"{k} {t}" for k, t in parts.select(*keys).dtypes)

    def add(table: pa.Table) -> pa.Table:
        col = table.column(value)
        total = unpack(col[0].as_py()).copy()
        for i in range(1, len(col)):
            total += unpack(col[i].as_py())
        return pa.table({**{k: table.column(k).slice(0, 1) for k in names}, value: pa.array([pack(total)], pa.binary())})

    if fan:
        names = [*keys, "_fan"]
        spread = parts.withColumn("_fan", F.pmod(F.spark_partition_id(), F.lit(fan)))
        parts = spread.groupBy(*names).applyInArrow(add, f"{spec}, _fan int, {value} binary").drop("_fan")
        return sum_packed(parts, keys, value)
    names = list(keys)
    return parts.groupBy(*keys).applyInArrow(add, f"{spec}, {value} binary")


def sum_arrays(df: DataFrame, key: str, column: str) -> DataFrame:
    """(key, i, s): sums of array columns by place, in JVM operators."""
    long = df.select(key, F.posexplode(column).alias("i", "v"))
    return long.groupBy(key, "i").agg(F.sum("v").alias("s"))


LIGHT = 32 << 20  # bytes of partial sums that may reach the driver at once


def collected(parts: DataFrame, keys: list[str], nbytes: int, value: str = "v", fan: int = 0):
    """Keys and summed vectors at the driver.  ``nbytes`` is a bound for all partials: few
    are summed at the driver, without an exchange; 0 means that it isn't known."""
    summed = not 0 < nbytes <= LIGHT
    table = (sum_packed(parts, keys, value, fan) if summed else parts).select(*keys, value).toArrow()  # rows of Python objects would take several times their bytes
    total = {}
    for batch in table.to_batches():
        for *k, v in zip(*(batch.column(c).to_pylist() for c in keys), batch.column(value)):
            k, v = tuple(k), np.frombuffer(v.as_buffer(), np.float64)
            total[k] = total[k] + v if k in total else v
    yield from total.items() if summed else sorted(total.items(), key=lambda r: r[0])
