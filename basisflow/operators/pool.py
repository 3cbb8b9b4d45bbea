"""The sink's pool of bases, and lossless restoration from it."""

from __future__ import annotations

import tempfile
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from basisflow.config import DedupConfig
from basisflow.operators.encode import restore

#: Chunks of one basis from which its restoration is spread, most such bases, and over how many keys.
HOT_REFS, HOT_BASES, SALTS = 1_000_000, 10_000, 64


def shared_folder(spark) -> str:
    """The folder that all executors share: ``spark.checkpoint.dir``; on one machine a temporary one where it is unset."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if folder is None:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        folder = tempfile.mkdtemp(prefix="basisflow-")
    return folder.rstrip("/")


def kept(table: DataFrame, label: str) -> DataFrame:
    """The table, written to the shared folder and read again: several branches scan it, not what made it."""
    path = f"{shared_folder(table.sparkSession)}/basisflow/{label}-{uuid.uuid4().hex}"
    table.write.option("compression", "zstd").parquet(path)
    return table.sparkSession.read.schema(table.schema).parquet(path)


def build(encoded: DataFrame) -> DataFrame:
    """(basis_key, basis, refs): each basis once."""
    return encoded.groupBy("basis_key").agg(F.first("basis").alias("basis"), F.count("*").alias("refs"))


def missing(encoded: DataFrame, pool: DataFrame) -> DataFrame:
    """Bases of a new batch that the pool lacks: only distinct keys of the batch meet it."""
    return build(encoded).join(pool.select("basis_key"), "basis_key", "left_anti")


def extend(pool: DataFrame, encoded: DataFrame) -> DataFrame:
    """The pool after a batch. Repeated batches change nothing but ``refs`` of what is new."""
    return pool.unionByName(missing(encoded, pool))


def reconstruct(encoded: DataFrame, pool: DataFrame, cfg: DedupConfig) -> DataFrame:
    """(source_id, packet_id, payload) from keys, deviations and the pool; empty payloads have no chunks and no row."""

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            bases = np.frombuffer(b"".join(batch.column(3).to_pylist()), np.uint8).reshape(batch.num_rows, -1)
            chunks = restore(bases, batch.column(4).to_pylist(), cfg)
            parts = [c.tobytes()[:n] for c, n in zip(chunks, batch.column(5).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(2), pa.array(parts, pa.binary())], ["source_id", "packet_id", "chunk_seq", "part"])

    pool = kept(pool.select("basis_key", "basis", "refs"), "pool")
    chunks = encoded.select("source_id", "packet_id", "chunk_seq", "basis_key", "deviation", "valid_len")
    total = pool.agg(F.sum("refs")).first()[0] or 0
    hot = pool.where(F.col("refs") > max(HOT_REFS, total // HOT_BASES))  # fewer than HOT_BASES
    if hot.limit(1).count():  # their chunks are spread over SALTS keys, so no task gets all of one
        named = F.broadcast(hot.select("basis_key", F.lit(SALTS).alias("salts")))
        salt = F.pmod(F.xxhash64("source_id", "packet_id", "chunk_seq"), F.coalesce("salts", F.lit(1)))
        chunks = chunks.join(named, "basis_key", "left").withColumn("salt", salt).drop("salts")
        every = F.explode(F.sequence(F.lit(0).cast("long"), F.coalesce("salts", F.lit(1)).cast("long") - 1))
        joined = chunks.join(pool.join(named, "basis_key", "left").select("basis_key", "basis", every.alias("salt")), ["basis_key", "salt"])
    else:
        joined = chunks.join(pool.select("basis_key", "basis"), "basis_key")
    parts = joined.select("source_id", "packet_id", "chunk_seq", "basis", "deviation", "valid_len").mapInArrow(run, "source_id string, packet_id long, chunk_seq int, part binary")
    ordered = parts.groupBy("source_id", "packet_id").agg(F.array_sort(F.collect_list(F.struct("chunk_seq", "part"))).alias("p"))
    return ordered.select("source_id", "packet_id", F.unhex(F.array_join(F.transform("p", lambda x: F.hex(x["part"])), "")).alias("payload"))


def roundtrip_mismatches(payloads: DataFrame, restored: DataFrame) -> DataFrame:
    """Payloads that are not the same after restoration, missing or wrong; empty ones need none."""
    want = payloads.where(F.octet_length("payload") > 0).select(F.col("source_id").cast("string").alias("source_id"), "packet_id", F.sha2("payload", 256).alias("sha"))
    got = restored.select("source_id", "packet_id", F.sha2("payload", 256).alias("sha"))
    return want.join(got, ["source_id", "packet_id", "sha"], "left_anti")
