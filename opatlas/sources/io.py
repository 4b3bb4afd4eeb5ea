"""Readers and writers; schemas are explicit where a format has none."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

#: JSON sources get their types from here, never by inference.
REPLY = "overall STRING, steps ARRAY<STRUCT<pos: INT, name: STRING, description: STRING>>, _corrupt_record STRING"
AST_NODE = (
    "script_id STRING, node_id INT, parent_id INT, pos INT, depth INT, kind STRING, op STRING, "
    "call_path ARRAY<STRING>, next_call STRING"
)


def read(spark: SparkSession, sf_dir: str, name: str, columns: Sequence[str] | None = None) -> DataFrame:
    """A given table, with only the columns that are asked for."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_json(spark: SparkSession, path: str, schema: str | T.StructType, mode: str = "PERMISSIVE") -> DataFrame:
    return spark.read.schema(schema).option("mode", mode).json(path)


def read_csv(spark: SparkSession, path: str, schema: str | T.StructType, header: bool = True) -> DataFrame:
    return spark.read.schema(schema).option("header", header).csv(path)


def read_text(spark: SparkSession, path: str, whole: bool = False) -> DataFrame:
    """Lines, or whole files, for scripts."""
    return spark.read.option("wholetext", whole).text(path)


def read_files(spark: SparkSession, path: str, pattern: str = "*") -> DataFrame:
    """Whole files with path, size, time and bytes."""
    return spark.read.format("binaryFile").option("pathGlobFilter", pattern).option("recursiveFileLookup", True).load(path)


def read_stream(spark: SparkSession, path: str, schema: str | T.StructType, fmt: str = "parquet", **options: str) -> DataFrame:
    return spark.readStream.format(fmt).schema(schema).options(**options).load(path)


def write(df: DataFrame, path: str, fmt: str = "parquet", partition_by: Sequence[str] | None = None, mode: str = "overwrite") -> None:
    """Writes any built-in format; partition columns are given where readers filter on them."""
    out = df.write.format(fmt).mode(mode)
    if fmt == "csv":
        out = out.option("header", True)
    (out.partitionBy(*partition_by) if partition_by else out).save(path)


def write_bucketed(df: DataFrame, table: str, n: int, cols: Sequence[str], mode: str = "overwrite") -> None:
    """A table whose joins and groupings on ``cols`` need no exchange."""
    df.write.mode(mode).bucketBy(n, *cols).sortBy(*cols).saveAsTable(table)
