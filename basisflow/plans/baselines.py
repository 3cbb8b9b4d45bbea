"""Compressors and other baselines beside the schemes: each chunk is compressed alone, as packets are."""

from __future__ import annotations

from pyspark.sql import functions as F

from basisflow.config import DedupConfig
from basisflow.functions.codecs import CODECS, codec_totals
from basisflow.operators import chunking, encode, schemes
from basisflow.plans import sql
from basisflow.plans.registry import register
from basisflow.sources import payloads as source


def _with_ratio(table):
    return table.withColumn("ratio", F.col("original_bytes") / F.col("total_bytes"))


@register("deflate_ratio")
def deflate_ratio(spark, sf_dir):
    return _with_ratio(codec_totals(source.conversations(spark, sf_dir), ["deflate"], [16, 64, 256]))


@register("lzw_ratio")
def lzw_ratio(spark, sf_dir):
    return _with_ratio(codec_totals(source.conversations(spark, sf_dir), ["lzw"], [16, 64, 256]))


@register("codec_matrix")
def codec_matrix(spark, sf_dir):
    """All codecs by chunk length on the rising date column: small packets hardly compress."""
    return _with_ratio(codec_totals(source.ship_dates(spark, sf_dir, 256), list(CODECS), [64, 128, 256]))


@register("content_defined_chunks")
def content_defined_chunks(spark, sf_dir):
    """Cuts that follow content: more chunks are shared between edited copies than with fixed cuts."""
    rows = chunking.content_defined(source.documents(spark, sf_dir), least=64, average=256, most=1024)
    unique = rows.groupBy("chunk_key").agg(F.count("*").alias("n"), F.first("size").alias("size"))
    return unique.agg(F.sum("n").alias("chunks"), F.count("*").alias("unique_chunks"), F.sum(F.col("n") * F.col("size")).alias("bytes"), F.sum("size").alias("unique_bytes"))


_HINTED = f"""WITH {sql.chunks(sql.DOCUMENTS, 64)}, u AS (SELECT x, count(*) AS n, bool_or(source_id = 'src0') AS held FROM c GROUP BY x)
SELECT sum(n)::BIGINT AS chunks, count(*) AS unique_chunks, count(*) FILTER (held) AS hinted_chunks, (count(*) FILTER (NOT held) * 64)::BIGINT AS body_bytes,
       (count(*) FILTER (held) * 6)::BIGINT AS manifest_bytes, (sum(n) * 6 + count(*) FILTER (NOT held) * 64)::BIGINT AS up_bytes, (2 * sum(n) + 2 * count(*) FILTER (NOT held) + 1)::BIGINT AS messages FROM u"""


@register("hinted_exact", _HINTED)
def hinted_exact(spark, sf_dir):
    """Exact deduplication where the sink has told sources, in one manifest, what it holds (all of the first source's chunks): those chunks need no body."""
    cfg = DedupConfig(64, "identity")
    unique = encode.unique_chunks(source.documents(spark, sf_dir).withColumn("source_id", F.when(F.col("source_id") == "src0", "held").otherwise("new")), [cfg], by_source=True)
    return schemes.hinted(unique.groupBy("chunk_key").agg(F.sum("n").alias("n"), F.max(F.col("source_id") == "held").alias("held")), cfg)
