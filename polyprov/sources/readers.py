"""Sources and sinks: thin, typed fronts over ``spark.read`` and ``df.write``."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.types import StructType

FORMATS = ("parquet", "csv", "json", "orc", "text", "jdbc", "table")


def read(spark: SparkSession, kind: str, location: str | None = None, schema: StructType | str | None = None, **options) -> DataFrame:
    """Read a base relation.  CSV and JSON need a schema (inference would scan twice)."""
    if kind not in FORMATS:
        raise ValueError(f"unknown source {kind}")
    if kind == "table":
        return spark.table(location)
    reader = spark.read.options(**options)
    if kind in ("csv", "json"):
        if schema is None:
            raise ValueError(f"{kind} needs a schema")
        reader = reader.schema(schema)
    elif schema is not None:
        reader = reader.schema(schema)
    return reader.format("jdbc").load() if kind == "jdbc" else getattr(reader, kind)(location)


def write(df: DataFrame, kind: str, location: str, mode: str = "errorifexists", partition_by: list[str] | None = None, bucket_by: tuple[int, list[str]] | None = None) -> None:
    """Write a result, annotation columns included, as files or as a (bucketed) table."""
    if kind not in ("parquet", "csv", "json", "orc", "table", "noop"):
        raise ValueError(f"unknown sink {kind}")
    writer = df.write.mode(mode)
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    if bucket_by:
        if kind != "table":
            raise ValueError("only tables can be bucketed")
        writer = writer.bucketBy(bucket_by[0], *bucket_by[1]).sortBy(*bucket_by[1])
    if kind == "table":
        writer.saveAsTable(location)
    elif kind == "noop":
        df.write.format("noop").mode("overwrite").save()
    else:
        getattr(writer, kind)(location)
