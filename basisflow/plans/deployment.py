"""Packets of several chunks, held bodies, variants of a miss, stored pools, the SQL surface."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from basisflow import sqlapi
from basisflow.config import DedupConfig
from basisflow.functions.codecs import stream_totals
from basisflow.operators import costs, encode, packets, pool, schemes
from basisflow.operators.pool_store import PoolStore
from basisflow.plans import sql
from basisflow.plans.registry import register
from basisflow.sources import payloads as source

_C8 = DedupConfig(8)


@register("packed_traffic", sql.outcomes(sql.CONVERSATIONS, 8) + ", v AS (SELECT source_id, packet_id, chunk_seq // 32 AS vector, count(*) AS n, (count(*) * 7)::BIGINT AS first, (count(*) FILTER (outcome = 'new_basis') * 8)::BIGINT AS extra FROM o GROUP BY ALL) SELECT source_id, sum(CASE WHEN extra > 0 THEN 4 ELSE 2 END)::BIGINT AS messages, sum(first + extra)::BIGINT AS up_bytes, sum(ceil(n / 8) + CASE WHEN extra > 0 THEN 1 ELSE 0 END)::BIGINT AS down_bytes FROM v GROUP BY source_id")
def packed_traffic(spark, sf_dir):
    """Thirty-two chunks in a message: the same bytes up, far fewer messages."""
    return packets.packed_traffic(schemes.outcomes(encode.encode_payloads(source.conversations(spark, sf_dir), _C8)), _C8, "sim_plain", 32)


@register("source_buffer", f"WITH {sql.chunks(sql.CONVERSATIONS, 8)}, v AS (SELECT c.*, least(8, length(h) // 2 - chunk_seq * 8) AS n FROM c JOIN p USING (source_id, packet_id)), b AS (SELECT source_id, sum(n) OVER (PARTITION BY source_id ORDER BY packet_id, chunk_seq ROWS 16 PRECEDING) AS held FROM v) SELECT source_id, max(held)::BIGINT AS peak_bytes FROM b GROUP BY source_id")
def source_buffer(spark, sf_dir):
    """Bytes that each source keeps until they are acknowledged, sixteen chunks later."""
    return packets.source_buffer(encode.encode_payloads(source.conversations(spark, sf_dir), _C8), 16)


@register("miss_variants", sql.outcomes(sql.RECORDS8, 8) + " SELECT body, fp_again, outcome, count(*) AS chunks, sum(7 + CASE WHEN outcome = 'new_basis' THEN size ELSE 0 END)::BIGINT AS up_bytes FROM o CROSS JOIN (VALUES ('basis', false, 8), ('chunk', false, 8), ('chunk', true, 14)) t(body, fp_again, size) GROUP BY ALL")
def miss_variants(spark, sf_dir):
    """A miss that sends the basis, the chunk, or the chunk with its fingerprint once more: from counts alone."""
    counted = costs.counts(encode.unique_chunks(source.records8(spark, sf_dir), [_C8]))
    totals = schemes.outcome_totals(counted).withColumn("dev_bytes", F.col("chunks") * _C8.fixed_deviation)
    return packets.uplink_variants(totals, _C8, (("basis", False), ("chunk", False), ("chunk", True)))


@register("pool_store_batches", f"WITH {sql.chunks(sql.RECORDS4, 4)}, {sql.hamming(4)}, f AS (SELECT word, min(source_id::INT % 2) AS batch FROM w GROUP BY word) SELECT 0 AS batch, count(*) FILTER (batch = 0) AS new_bases FROM f UNION ALL SELECT 1, count(*) FILTER (batch = 1) FROM f UNION ALL SELECT 2, 0")
def pool_store_batches(spark, sf_dir):
    """A pool on disk takes two batches and one of them again: only what is new is added."""
    cfg = DedupConfig(4)
    encoded = encode.encode_payloads(source.records4(spark, sf_dir), cfg)
    store = PoolStore(spark, f"{pool.shared_folder(spark)}/pool-{uuid.uuid4().hex}", cfg)
    added = [store.append(encoded.where(F.col("source_id").cast("int") % 2 == side)) for side in (0, 1, 1)]
    return spark.createDataFrame(list(enumerate(added)), "batch int, new_bases long")


@register("sql_surface", f"WITH {sql.chunks(sql.CONVERSATIONS, 8)}, {sql.hamming(8)} SELECT syn AS syndrome, count(*) AS chunks, count(DISTINCT word) AS bases, 0::BIGINT AS wrong FROM w GROUP BY syn")
def sql_surface(spark, sf_dir):
    """Cut, split and restored in SQL alone."""
    sqlapi.register(spark)
    source.conversations(spark, sf_dir).createOrReplaceTempView("basisflow_payloads")
    return spark.sql("""
        WITH s AS (SELECT c.chunk, gd_syndrome(c.chunk) AS syndrome, gd_basis(c.chunk) AS basis, gd_deviation(c.chunk) AS deviation
                   FROM basisflow_payloads p, LATERAL gd_chunks(p.payload, 8) c)
        SELECT syndrome, count(*) AS chunks, count(DISTINCT basis) AS bases, count_if(gd_restore(basis, deviation, 8) <> chunk) AS wrong FROM s GROUP BY syndrome""")


@register("sql_reed_solomon", f"WITH {sql.chunks(sql.CONVERSATIONS, 16)}, {sql.rs2(16)} SELECT count(*) AS chunks, count(DISTINCT x) AS exact_bases, count(DISTINCT word) AS bases FROM w")
def sql_reed_solomon(spark, sf_dir):
    """The Reed-Solomon split in SQL alone."""
    sqlapi.register(spark)
    source.conversations(spark, sf_dir).createOrReplaceTempView("basisflow_payloads")
    return spark.sql("SELECT count(*) AS chunks, count(DISTINCT c.chunk) AS exact_bases, count(DISTINCT gd_rs_basis(c.chunk)) AS bases FROM basisflow_payloads p, LATERAL gd_chunks(p.payload, 16) c")


@register("stream_compression")
def stream_compression(spark, sf_dir):
    """Whole sources through DEFLATE, against each packet alone: small packets lose most of the gain."""
    from basisflow.functions.codecs import codec_totals

    data = source.conversations(spark, sf_dir)
    whole = stream_totals(data).agg(F.lit("source").alias("scope"), F.sum("original_bytes").alias("original_bytes"), F.sum("total_bytes").alias("total_bytes"))
    alone = codec_totals(data, ["deflate"], [64]).select(F.lit("packet of 64").alias("scope"), "original_bytes", "total_bytes")
    return whole.unionByName(alone).withColumn("ratio", F.col("original_bytes") / F.col("total_bytes"))
