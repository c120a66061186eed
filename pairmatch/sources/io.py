"""Record tables in and results out."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def read_records(spark: SparkSession, path: str, fmt: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """parquet, orc, json (lines), csv or text, with a given schema where one is known."""
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write_split(df: DataFrame, path: str, by: tuple[str, ...] = ("split",), mode: str = "overwrite") -> None:
    """Parquet partitioned for pruning; rows of a partition value are spread over tasks as they come."""
    df.write.mode(mode).partitionBy(*by).parquet(path)


def write_metrics(df: DataFrame, path: str) -> None:
    df.write.mode("overwrite").json(path)


def write_bucketed(df: DataFrame, table: str, key: str, buckets: int = 64) -> None:
    """A table whose joins and groupings on key need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)
