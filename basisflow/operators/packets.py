"""Several chunks in one packet, bodies held until acknowledged, and the check of the dual scheme."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from basisflow.config import DedupConfig
from basisflow.operators import ordered
from basisflow.operators.schemes import _uplink


def packed_traffic(found: DataFrame, cfg: DedupConfig, scheme: str, chunks_per_packet: int) -> DataFrame:
    """(source_id, messages, up_bytes, down_bytes) where fingerprints of several chunks share a message.

    The sink answers each vector with a bitmap; bodies it lacks follow in one message. Bytes sent are
    those of single chunks, messages are fewer. Vectors do not cross payloads.
    """
    extra = F.lit(0).cast("long")
    first = F.lit(0).cast("long")
    for outcome, messages in _uplink(cfg, scheme).items():
        here = F.when(F.col("outcome") == outcome, 1).otherwise(0)
        size = lambda m: F.lit(m[1]) + (F.col("dev_bytes") if m[2] else 0)
        first = first + here * size(messages[0])
        if len(messages) > 1:
            extra = extra + here * size(messages[1])
    rows = found.select("source_id", "packet_id", F.floor(F.col("chunk_seq") / chunks_per_packet).alias("vector"), first.alias("first"), extra.alias("extra"))
    vectors = rows.groupBy("source_id", "packet_id", "vector").agg(F.count("*").alias("n"), F.sum("first").alias("first"), F.sum("extra").alias("extra"))
    missing = F.col("extra") > 0
    return vectors.groupBy("source_id").agg(
        F.sum(F.when(missing, 4).otherwise(2)).cast("long").alias("messages"),
        F.sum(F.col("first") + F.col("extra")).alias("up_bytes"),
        F.sum(F.ceil(F.col("n") / 8) + F.when(missing, 1).otherwise(0)).cast("long").alias("down_bytes"),
    )


def source_buffer(encoded: DataFrame, latency: int) -> DataFrame:
    """(source_id, peak_bytes): most bytes of bodies that a source holds, if an acknowledgement takes ``latency`` more chunks."""
    placed = ordered.numbered(encoded.select("source_id", "packet_id", "chunk_seq", "valid_len"), "source_id", ["packet_id", "chunk_seq"])
    held = ordered.sums_before(placed, "source_id", "at", F.col("valid_len"), latency, "held")
    return held.groupBy("source_id").agg(F.max("held").cast("long").alias("peak_bytes"))


def verify_dual(rebuilt: Column, claimed_half: Column, algo: str, half: int) -> Column:
    """The sink's check: the chunk rebuilt from its own basis must have the half fingerprint that was sent."""
    from basisflow.functions.fingerprints import fingerprint

    return fingerprint(rebuilt, algo, half) == claimed_half


def uplink_variant(found: DataFrame, cfg: DedupConfig, miss_body: str = "basis", repeat_fp: bool = False) -> DataFrame:
    """(outcome, chunks, up_bytes) of the plain scheme where a miss sends the chunk, or the fingerprint goes along once more."""
    if miss_body not in ("basis", "chunk"):
        raise ValueError("a miss sends the basis or the chunk")
    body = (cfg.basis_bytes if miss_body == "basis" else cfg.n_b) + (cfg.fp_bytes if repeat_fp else 0)
    size = F.lit(cfg.fp_bytes) + F.col("dev_bytes") + F.when(F.col("outcome") == "new_basis", body).otherwise(0)
    return found.groupBy("outcome").agg(F.count("*").alias("chunks"), F.sum(size).cast("long").alias("up_bytes"))


def uplink_variants(totals: DataFrame, cfg: DedupConfig, variants) -> DataFrame:
    """(body, fp_again, outcome, chunks, up_bytes) of several such variants, from rows (outcome, chunks, dev_bytes)."""
    rows = []
    for miss_body, again in variants:
        body = (cfg.basis_bytes if miss_body == "basis" else cfg.n_b) + (cfg.fp_bytes if again else 0)
        size = F.col("chunks") * cfg.fp_bytes + F.col("dev_bytes") + F.when(F.col("outcome") == "new_basis", F.col("chunks") * body).otherwise(0)
        rows.append(F.struct(F.lit(miss_body).alias("body"), F.lit(again).alias("fp_again"), size.cast("long").alias("up_bytes")))
    return totals.select("outcome", "chunks", F.explode(F.array(*rows)).alias("r")).select("r.body", "r.fp_again", "outcome", "chunks", "r.up_bytes")
