"""Payload rows from files and live sources."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def binary_files(spark: SparkSession, path: str, pattern: str = "*") -> DataFrame:
    """A payload per file; its path is its source."""
    rows = spark.read.format("binaryFile").option("pathGlobFilter", pattern).load(path)
    return rows.select(F.col("path").alias("source_id"), F.xxhash64("path").alias("packet_id"), F.col("content").alias("payload"))


def text_lines(spark: SparkSession, path: str) -> DataFrame:
    """A payload per line; the file is the source. Equal lines of a file share a packet number, which is a hash."""
    rows = spark.read.text(path)
    return rows.select(F.input_file_name().alias("source_id"), F.xxhash64(F.input_file_name(), "value").alias("packet_id"), F.encode("value", "UTF-8").alias("payload"))


def csv_records(spark: SparkSession, path: str, schema: str, source: str, packet: str, field: str) -> DataFrame:
    rows = spark.read.schema(schema).option("header", True).csv(path)
    return rows.select(F.col(source).cast("string").alias("source_id"), F.col(packet).cast("long").alias("packet_id"), F.encode(F.col(field).cast("string"), "UTF-8").alias("payload"))


def rate_stream(spark: SparkSession, rows_per_second: int = 100, sources: int = 16) -> DataFrame:
    """Synthetic load: eight-byte counters that change in their last bits only, with times."""
    rows = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    payload = F.unhex(F.lpad(F.hex(F.col("value") % 1024), 16, "0"))
    return rows.select((F.col("value") % sources).cast("string").alias("source_id"), F.col("value").alias("packet_id"), F.col("timestamp").alias("ts"), payload.alias("payload"))
