"""Payload rows (source_id, packet_id, payload) from the given tables.

Numbers are packed big-endian. Prices and shares are multiplied by 100 and rounded
before they become integers, as they are binary floats.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import BinaryType

from basisflow.operators import ordered

NODES = 16


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def dealt(rows: DataFrame, *by: str) -> DataFrame:
    """The rows dealt by hash over at least four tasks a core, for work that takes far longer than moving them; a file may be one row group, which one task reads."""
    spark = rows.sparkSession
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 4 * spark.sparkContext.defaultParallelism)
    return rows.repartition(tasks, F.xxhash64(*by))


def pack_uint(value: Column, width: int) -> Column:
    """Big-endian unsigned integer of ``width`` bytes; higher bytes are cut off."""
    return F.unhex(F.lpad(F.right(F.hex(value.cast("long")), F.lit(2 * width)), 2 * width, "0"))


def pack_i64(value: Column) -> Column:
    """Two's complement in eight bytes."""
    return pack_uint(value, 8)


@F.pandas_udf(BinaryType())
def pack_f64(value: pd.Series) -> pd.Series:
    """Eight bytes of a double; no built-in function reinterprets its bits."""
    raw = value.to_numpy(">f8").tobytes()
    return pd.Series([None if null else raw[i : i + 8] for i, null in zip(range(0, len(raw), 8), value.isna(), strict=True)], dtype=object)


def hundredths(value: Column) -> Column:
    return F.round(value * 100).cast("long")


def pack_text(value: Column) -> Column:
    return F.encode(value, "UTF-8")


def pack_days(value: Column) -> Column:
    return pack_uint(F.datediff(value.cast("date"), F.lit("1970-01-01").cast("date")), 2)


def documents(spark, sf_dir) -> DataFrame:
    return table(spark, sf_dir, "documents").select(F.col("source").alias("source_id"), F.col("doc_id").alias("packet_id"), pack_text(F.col("text")).alias("payload"))


def pages(spark, sf_dir) -> DataFrame:
    return table(spark, sf_dir, "pages").select(F.regexp_extract("url", "//([^/:?#]*)", 1).alias("source_id"), F.col("page_id").alias("packet_id"), pack_text(F.col("html")).alias("payload"))


def conversations(spark, sf_dir) -> DataFrame:
    return table(spark, sf_dir, "conversations").select(F.col("conv_id").cast("string").alias("source_id"), (F.col("conv_id") * 10_000 + F.col("turn")).alias("packet_id"), pack_text(F.col("text")).alias("payload"))


def _line_rows(spark, sf_dir, payload: Column) -> DataFrame:
    node = (F.col("l_suppkey") % NODES).cast("string").alias("source_id")
    return table(spark, sf_dir, "lineitem").select(node, F.xxhash64("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_shipdate").alias("packet_id"), payload.alias("payload"))


def records4(spark, sf_dir) -> DataFrame:
    """Discount, tax, line number and return flag, a byte each."""
    return _line_rows(spark, sf_dir, F.concat(pack_uint(hundredths(F.col("l_discount")), 1), pack_uint(hundredths(F.col("l_tax")), 1), pack_uint(F.col("l_linenumber"), 1), pack_uint(F.ascii("l_returnflag"), 1)))


def records8(spark, sf_dir) -> DataFrame:
    """Quantity, discount, tax, line number, flag, status and two zero bytes."""
    fields = [F.col("l_quantity").cast("long"), hundredths(F.col("l_discount")), hundredths(F.col("l_tax")), F.col("l_linenumber"), F.ascii("l_returnflag"), F.ascii("l_linestatus"), F.lit(0), F.lit(0)]
    return _line_rows(spark, sf_dir, F.concat(*(pack_uint(f, 1) for f in fields)))


def column_stream(rows: DataFrame, source: str, order: list[str], value: Column, samples: int) -> DataFrame:
    """A column as packets of ``samples`` values per source, in a total order within the source.

    A source may be as large as the table: places are counted across partitions.
    """
    by = [f"by{i}" for i in range(len(order))]
    plain = rows.select(F.col(source).cast("string").alias("source_id"), *(F.col(o).alias(b) for o, b in zip(order, by, strict=True)), value.alias("v"))
    numbered = ordered.numbered(plain, "source_id", by).select("source_id", "at", "v")
    groups = numbered.groupBy("source_id", F.floor(F.col("at") / samples).alias("packet_id")).agg(F.array_sort(F.collect_list(F.struct("at", "v"))).alias("parts"))
    return groups.select("source_id", "packet_id", F.unhex(F.array_join(F.transform("parts", lambda p: F.hex(p["v"])), "")).alias("payload"))


def ship_dates(spark, sf_dir, n_b: int) -> DataFrame:
    """Ship dates as 2-byte days, per supplier, in rising order: a slowly rising meter."""
    return column_stream(table(spark, sf_dir, "lineitem"), "l_suppkey", ["l_shipdate"], pack_days(F.col("l_shipdate")), n_b // 2)


def event_values(spark, sf_dir, n_b: int) -> DataFrame:
    """Event values in hundredths as 3-byte integers, per user, in time order; ``n_b`` must hold whole samples."""
    return column_stream(table(spark, sf_dir, "events"), "user_id", ["ts", "event_id"], pack_uint(hundredths(F.col("value")), 3), n_b // 3)


def embeddings(spark, sf_dir) -> DataFrame:
    """Vectors as 2-byte fixed-point numbers, a packet each."""
    parts = F.transform("embedding", lambda x: F.right(F.lpad(F.hex((F.floor(x.cast("double") * 1024 + 0.5) + 32768).cast("long")), 16, "0"), F.lit(4)))
    return table(spark, sf_dir, "embeddings").select(F.lit("0").alias("source_id"), F.col("vec_id").alias("packet_id"), F.unhex(F.array_join(parts, "")).alias("payload"))


def readings(spark, sf_dir) -> DataFrame:
    """User and value of every event as they are stored: eight bytes of an integer and eight of a double."""
    return table(spark, sf_dir, "events").select(F.col("user_id").cast("string").alias("source_id"), F.col("event_id").alias("packet_id"), F.concat(pack_i64(F.col("user_id")), pack_f64(F.col("value"))).alias("payload"))
