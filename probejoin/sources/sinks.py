"""Mappings written to files and read again."""

from __future__ import annotations

from pyspark.sql import DataFrame

from probejoin.sources.storage import shared_folder


def write(df: DataFrame, path: str, fmt: str = "parquet") -> None:
    writer = df.write.format(fmt)
    if fmt == "csv":
        writer = writer.option("header", True).option("escape", '"')
    writer.save(path)


def read(spark, path: str, fmt: str, schema) -> DataFrame:
    reader = spark.read.format(fmt).schema(schema)
    if fmt == "csv":
        reader = reader.option("header", True).option("escape", '"')
    return reader.load(path)


def roundtrip(df: DataFrame, fmt: str) -> DataFrame:
    path = shared_folder(df.sparkSession, f"sink-{fmt}")
    write(df, path, fmt)
    return read(df.sparkSession, path, fmt, df.schema)
