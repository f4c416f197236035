"""Readers and writers of the tables that the engine uses."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read_table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A Parquet table; only ``columns`` reach the scan if they are given."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_examples(spark: SparkSession, path: str, fmt: str, schema: str) -> DataFrame:
    """Examples from csv, json, orc or parquet; vectors of csv are JSON arrays in text columns."""
    if fmt == "csv":
        flat = schema.replace("ARRAY<DOUBLE>", "STRING").replace("array<double>", "string")
        df = spark.read.schema(flat).option("header", True).option("escape", '"').csv(path)
        for field in df.schema.fields:
            if f"{field.name} ARRAY<DOUBLE>".lower() in schema.lower():
                df = df.withColumn(field.name, F.from_json(field.name, "array<double>"))
        return df
    return spark.read.schema(schema).format(fmt).load(path)


def write_by_device(df: DataFrame, path: str, max_records: int = 0) -> None:
    """One folder for each device, so that a list of devices prunes the scan."""
    df.write.mode("overwrite").option("maxRecordsPerFile", max_records).partitionBy("device").parquet(path)


def arrivals_stream(spark: SparkSession, path: str, schema: str) -> DataFrame:
    """New Parquet files of a folder as a stream."""
    return spark.readStream.schema(schema).parquet(path)
