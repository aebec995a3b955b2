"""Readers and writers: tables, examples in several formats, models, traces, streams."""

from __future__ import annotations

import json

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_examples(spark: SparkSession, path: str, fmt: str, schema: T.StructType | str, **options) -> DataFrame:
    """CSV, JSON, ORC or Parquet rows with an explicit schema; malformed rows fail."""
    reader = spark.read.schema(schema).options(**options)
    if fmt in ("csv", "json"):
        reader = reader.option("mode", "FAILFAST")
    return reader.format(fmt).load(path)


def parse_sparse(lines: DataFrame, column: str = "value") -> DataFrame:
    """(y, idx, val) from lines ``label index:value ...`` with indices from 1."""
    parts = F.split(F.trim(F.regexp_replace(column, r"\s+", " ")), " ")
    pairs = F.filter(F.slice(parts, 2, F.size(parts)), lambda p: F.length(p) > 0)
    half = lambda k: F.transform(pairs, lambda p: F.element_at(F.split(p, ":"), k))
    return lines.select("*", F.element_at(parts, 1).cast("double").alias("y"), half(1).cast("array<int>").alias("idx"), half(2).cast("array<double>").alias("val"))


def read_sparse_text(spark: SparkSession, path: str) -> DataFrame:
    return parse_sparse(spark.read.text(path)).drop("value")


def save_vector(spark: SparkSession, w: np.ndarray, path: str) -> None:
    rows = [(int(i), float(v)) for i, v in enumerate(np.ravel(w))]
    spark.createDataFrame(rows, "i int, w double").coalesce(1).write.mode("overwrite").parquet(path)


def load_vector(spark: SparkSession, path: str) -> np.ndarray:
    return np.array([r["w"] for r in spark.read.parquet(path).orderBy("i").collect()])


TRACE = "workload string, scheme string, it int, loss double, grad_norm double, step double, sim_s double, wall_s double, note string, test_loss double, test_error double"


def trace_frame(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    """Rows of a trace; losses and errors on held-out rows may be left out."""
    return spark.createDataFrame([(*r, None, None)[:11] for r in rows], TRACE)


def save_trace(df: DataFrame, path: str) -> None:
    df.write.mode("append").partitionBy("workload").parquet(path)


def stream(spark: SparkSession, sf_dir: str, name: str = "events", time_column: str = "ts") -> DataFrame:
    """A file stream of one table; times become TIMESTAMP, as watermarks need."""
    schema = spark.read.parquet(f"{sf_dir}/{name}.parquet").schema
    rows = spark.readStream.schema(schema).option("pathGlobFilter", f"{name}.parquet*").parquet(sf_dir)
    return rows.withColumn(time_column, F.col(time_column).cast("timestamp"))


def settings(df: DataFrame) -> str:
    """The formatted plan, for inspection in tests."""
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def to_json_line(**values) -> str:
    return json.dumps(values, sort_keys=True)
