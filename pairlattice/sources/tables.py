"""Readers with declared schemas and writers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def read(spark: SparkSession, path: str, kind: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """A table from parquet, ORC, CSV, JSON or text; CSV and JSON need a schema, so nothing is inferred by a scan."""
    if kind in ("csv", "json") and schema is None:
        raise ValueError(f"{kind} needs a schema")
    reader = spark.read.options(**{k: str(v) for k, v in options.items()})
    return (reader.schema(schema) if schema else reader).format(kind).load(path)


def stream(spark: SparkSession, path: str, schema, kind: str = "parquet", files_per_trigger: int | None = None) -> DataFrame:
    """A file stream; the schema is given, as a stream needs it."""
    reader = spark.readStream.schema(schema)
    return (reader.option("maxFilesPerTrigger", files_per_trigger) if files_per_trigger else reader).format(kind).load(path)


def write(df: DataFrame, path: str, kind: str = "parquet", by: tuple[str, ...] = (), mode: str = "overwrite") -> None:
    (df.write.mode(mode).partitionBy(*by) if by else df.write.mode(mode)).format(kind).save(path)
