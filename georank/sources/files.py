"""Reading and writing of files in Spark's formats, always with a schema, and a bucketed table for the rank index."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

FORMATS = {"parquet": {}, "orc": {}, "json": {}, "csv": {"header": "true"}}


def read(spark: SparkSession, path: str, fmt: str, schema: T.StructType) -> DataFrame:
    """Rows that don't fit the schema raise an error instead of turning into nulls."""
    strict = {"mode": "FAILFAST"} if fmt in ("csv", "json") else {}
    return spark.read.format(fmt).options(**FORMATS[fmt], **strict).schema(schema).load(path)


def write(df: DataFrame, path: str, fmt: str) -> None:
    df.write.format(fmt).options(**FORMATS[fmt]).save(path)


def scratch(spark: SparkSession, name: str) -> str:
    """A new path that all executors reach: in the checkpoint folder if the session has one, else in its warehouse."""
    at = spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.sql.warehouse.dir")
    return f"{at}/{name}-{uuid.uuid4().hex}"


def round_trip(df: DataFrame, fmt: str) -> DataFrame:
    path = scratch(df.sparkSession, fmt)
    write(df, path, fmt)
    return read(df.sparkSession, path, fmt, df.schema)


def write_bucketed(df: DataFrame, table: str, by: list[str], buckets: int) -> DataFrame:
    """A table bucketed and sorted by its join key: joins on that key with another such table need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, *by).sortBy(*by).format("parquet").saveAsTable(table)
    return df.sparkSession.table(table)
