"""Bytes that each scheme sends, from the table of distinct chunks, and what follows from them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from basisflow.config import DedupConfig


def counts(unique: DataFrame, group: tuple[str, ...] = ("cfg",)) -> DataFrame:
    """Per group: chunks, exact_bases, bases, dev_sum over all chunks, q_chunks and their q_dev.

    Q is the set of first arrivals of unseen chunks whose basis was known. Two aggregations,
    first by basis, so that a basis with very many chunks is combined before it moves.
    """
    by_basis = unique.groupBy(*group, "basis_key").agg(F.count("*").alias("u"), F.sum("n").alias("n"), F.sum(F.col("n") * F.col("dev_bytes")).alias("dev"), (F.sum("dev_bytes") - F.min_by("dev_bytes", "first")).alias("q_dev"))
    return by_basis.groupBy(*group).agg(F.sum("n").alias("chunks"), F.sum("u").alias("exact_bases"), F.count("*").alias("bases"), F.sum("dev").alias("dev_sum"), (F.sum("u") - F.count("*")).alias("q_chunks"), F.sum("q_dev").alias("q_dev"))


def scheme_bytes(h: int, n_b: int, k_b: int) -> dict[str, Column]:
    """What the source sends under each scheme, for fingerprints of ``h`` bytes in the full scheme.

    Short fingerprints fill what the deviation leaves of ``h``; both halves of the dual scheme make ``h``.
    """
    c = F.col
    return {
        "raw": c("chunks") * n_b,
        "exact": c("exact_bases") * n_b + c("chunks") * h,
        "sim_plain": c("bases") * k_b + c("chunks") * h + c("dev_sum"),
        "sim_short": c("bases") * k_b + c("chunks") * h,
        "sim_dual": c("bases") * n_b + c("q_dev") + c("chunks") * h,
    }


def scheme_table(counted: DataFrame, cfg: DedupConfig) -> DataFrame:
    """(scheme, chunks, bases, total_bytes, original_bytes, ratio): a row for each scheme."""
    totals = scheme_bytes(cfg.fp_bytes, cfg.n_b, cfg.basis_bytes)
    rows = F.explode(F.array(*(F.struct(F.lit(s).alias("scheme"), F.when(F.lit(s) == "exact", F.col("exact_bases")).when(F.lit(s) == "raw", F.col("chunks")).otherwise(F.col("bases")).alias("bodies"), t.cast("long").alias("total_bytes")) for s, t in totals.items())))
    out = counted.select("chunks", rows.alias("r")).select("chunks", "r.*")
    return out.select("scheme", "chunks", "bodies", "total_bytes", (F.col("chunks") * cfg.n_b).alias("original_bytes"), (F.col("chunks") * cfg.n_b / F.col("total_bytes")).alias("ratio"))


def study(counted: DataFrame, cfgs: list[DedupConfig]) -> DataFrame:
    """``scheme_table`` of many configurations at once, from one scan: (transform, preprocess, n_b, scheme, chunks, bodies, total_bytes, ratio)."""
    spark, c = counted.sparkSession, F.col
    names = spark.createDataFrame([(i, x.transform, x.preprocess, x.n_b, x.basis_bytes, x.fp_bytes) for i, x in enumerate(cfgs)], "cfg int, transform string, preprocess string, n_b long, k_b long, h long")
    totals = scheme_bytes(c("h"), c("n_b"), c("k_b"))
    bodies = {"raw": c("chunks"), "exact": c("exact_bases")}
    rows = F.explode(F.array(*(F.struct(F.lit(s).alias("scheme"), bodies.get(s, c("bases")).alias("bodies"), t.cast("long").alias("total_bytes")) for s, t in totals.items())))
    out = counted.join(F.broadcast(names), "cfg").select("transform", "preprocess", "n_b", "chunks", rows.alias("r"))  # a row for each configuration
    return out.select("transform", "preprocess", "n_b", "r.scheme", "chunks", "r.bodies", "r.total_bytes", (c("chunks") * c("n_b") / c("r.total_bytes")).alias("ratio"))


# --- conditions -------------------------------------------------------------


def exact_pays(bases, chunks, n_b: int, h: int):
    """Whether exact deduplication sends less than the chunks themselves."""
    return bases * n_b < chunks * (n_b - h)


def exact_pays_from(chunks: int, n_b: int, h: int) -> float:
    """Matches beyond which it does."""
    return chunks * h / n_b


def plain_beats_exact(bases, exact_bases, dev_sum, n_b: int, k_b: int):
    return bases * k_b < exact_bases * n_b - dev_sum


def min_matches_plain(chunks, exact_matches, dev_sum, n_b: int, k_b: int):
    """Matches beyond which the plain scheme beats exact deduplication with ``exact_matches``."""
    return (dev_sum + chunks * (k_b - n_b) + exact_matches * n_b) / k_b


def dominance(counted: DataFrame, cfg: DedupConfig) -> DataFrame:
    """One row of invariants that must hold: short and dual never send more than exact, bases never outnumber chunks."""
    t = scheme_bytes(cfg.fp_bytes, cfg.n_b, cfg.basis_bytes)
    return counted.select(
        (t["sim_short"] <= t["exact"]).alias("short_le_exact"),
        (t["sim_dual"] <= t["exact"]).alias("dual_le_exact"),
        (F.col("bases") <= F.col("exact_bases")).alias("bases_le_exact"),
        (F.col("exact_bases") <= F.col("chunks")).alias("exact_le_chunks"),
        (F.col("q_chunks") == F.col("exact_bases") - F.col("bases")).alias("q_is_difference"),
        (t["sim_short"] + F.col("dev_sum") == t["sim_plain"]).alias("plain_is_short_and_deviations"),
    )


def storage(counted: DataFrame, cfg: DedupConfig) -> DataFrame:
    """Bytes at rest: bodies once, and a fingerprint (with a deviation) for each chunk."""
    h = cfg.fp_bytes
    return counted.select("chunks", "exact_bases", "bases", (F.col("exact_bases") * cfg.n_b + F.col("chunks") * h).alias("exact_bytes"), (F.col("bases") * cfg.basis_bytes + F.col("chunks") * h + F.col("dev_sum")).alias("similar_bytes"))


def chunks_per_basis(unique: DataFrame) -> DataFrame:
    """(unique_chunks, bases): how many bases have so many distinct chunks."""
    return unique.groupBy("basis_key").agg(F.count("*").alias("unique_chunks")).groupBy("unique_chunks").agg(F.count("*").alias("bases"))


def throughput_mbps(n_bytes: float, seconds: float) -> float:
    return n_bytes * 8 / seconds / 1e6


def energy_per_bit(watts: float, seconds: float, bits: float) -> float:
    """A model (power by time by bit): nothing here measures energy."""
    return watts * seconds / bits
