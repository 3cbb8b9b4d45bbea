"""Fingerprint columns: a digest, cut to a prefix."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from basisflow.config import DIGEST_BYTES


def digest(body: Column, algo: str) -> Column:
    if algo == "crc32":
        return F.unhex(F.lpad(F.hex(F.crc32(body)), 8, "0"))
    return F.unhex({"sha1": F.sha1, "md5": F.md5, "sha256": lambda c: F.sha2(c, 256)}[algo](body))


def fingerprint(body: Column, algo: str = "md5", n_bytes: int | None = None) -> Column:
    n_bytes = n_bytes or DIGEST_BYTES[algo]
    if not 0 < n_bytes <= DIGEST_BYTES[algo]:
        raise ValueError("the fingerprint is longer than its digest")
    return F.substring(digest(body, algo), 1, n_bytes)


def collision_report(bodies: DataFrame, algo: str, n_bytes: int, body: str = "body", n: str = "n") -> DataFrame:
    """One row: distinct bodies and fingerprints, fingerprints of several bodies, chunks behind those.

    ``bodies`` has distinct bodies and how many chunks have each.
    """
    fps = bodies.select(fingerprint(F.col(body), algo, n_bytes).alias("fp"), F.col(n).alias("n")).groupBy("fp").agg(F.count("*").alias("bodies"), F.sum("n").alias("chunks"))
    several = F.col("bodies") > 1
    return fps.agg(
        F.lit(algo).alias("algo"),
        F.lit(n_bytes).cast("long").alias("fp_bytes"),
        F.coalesce(F.sum("bodies"), F.lit(0)).alias("bodies"),
        F.count("*").alias("fps"),
        F.count(F.when(several, 1)).alias("colliding_fps"),
        F.coalesce(F.sum(F.when(several, F.col("chunks"))), F.lit(0)).alias("affected_chunks"),
    )


def collision_reports(bodies: DataFrame, widths: list[tuple[str, int]], body: str = "body", n: str = "n") -> DataFrame:
    """``collision_report`` of several (algorithm, bytes) in one pass: every body is named in all of them at once."""
    names = F.explode(F.array(*(F.struct(F.lit(a).alias("algo"), F.lit(w).cast("long").alias("fp_bytes"), fingerprint(F.col(body), a, w).alias("fp")) for a, w in widths)))
    fps = bodies.select(names.alias("f"), F.col(n).alias("n")).groupBy("f.algo", "f.fp_bytes", "f.fp").agg(F.count("*").alias("bodies"), F.sum("n").alias("chunks"))
    several = F.col("bodies") > 1
    return fps.groupBy("algo", "fp_bytes").agg(
        F.sum("bodies").alias("bodies"),
        F.count("*").alias("fps"),
        F.count(F.when(several, 1)).alias("colliding_fps"),
        F.coalesce(F.sum(F.when(several, F.col("chunks"))), F.lit(0)).alias("affected_chunks"),
    )
