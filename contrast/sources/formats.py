"""Reading rows from files of several kinds, and keeping results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

KINDS = ("parquet", "csv", "json", "orc", "text")


def read(spark: SparkSession, kind: str, path: str, schema: str | None = None, **options) -> DataFrame:
    """Files of a kind; csv and json infer their schema where none is given, csv with a header."""
    if kind not in KINDS:
        raise ValueError(f"unknown kind: {kind}")
    reader = spark.read.format(kind)
    if kind == "csv":
        options = {"header": True, "inferSchema": schema is None} | options
    return (reader.schema(schema) if schema else reader).options(**options).load(path)


def write_patterns(patterns: DataFrame, path: str) -> None:
    """Patterns by class, in Parquet; a class that is written again replaces its own files only."""
    patterns.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("cls").parquet(path)


def write_rules(patterns: DataFrame, path: str) -> None:
    patterns.write.mode("overwrite").json(path)


def save_rows(tx: DataFrame, name: str, buckets: int = 64) -> None:
    """Encoded rows as a table bucketed by row, so that joins on tx_id need no shuffle."""
    tx.write.mode("overwrite").bucketBy(buckets, "tx_id").sortBy("tx_id").saveAsTable(name)
