"""Reading and writing in Spark's formats, always with a declared schema."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from pantry.session import shared_dir

FORMATS = ("parquet", "csv", "json", "orc", "text")


def read(spark: SparkSession, path: str, kind: str, schema) -> DataFrame:
    """``path`` in one of FORMATS; no inference, malformed rows fail."""
    reader = spark.read.schema(schema)
    if kind in ("csv", "json"):
        reader = reader.option("mode", "FAILFAST")
    return reader.format(kind).load(path)


def write(df: DataFrame, path: str, kind: str = "parquet", by: tuple[str, ...] = (), order: tuple[str, ...] = (), mode: str = "errorifexists") -> None:
    """Partitioned by ``by``, sorted inside each file by ``order``."""
    out = df.sortWithinPartitions(*order) if order else df
    writer = out.write.mode(mode).format(kind)
    (writer.partitionBy(*by) if by else writer).save(path)


def write_bucketed(df: DataFrame, name: str, buckets: int, key: str, mode: str = "overwrite") -> None:
    """A table whose files are dealt by ``key``: later joins and aggregations on it need no exchange."""
    df.write.mode(mode).bucketBy(buckets, key).sortBy(key).saveAsTable(name)


def round_trip(df: DataFrame, kind: str) -> DataFrame:
    """``df`` written to the shared folder and read again."""
    path = f"{shared_dir(df.sparkSession)}/pantry-{kind}-{uuid.uuid4().hex}"
    write(df, path, kind)
    return read(df.sparkSession, path, kind, df.schema)
