"""A pool of bases on disk: Parquet by key prefix, with the digest of its configuration."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from basisflow.config import DedupConfig
from basisflow.operators import pool


class PoolStore:
    """``append`` adds what a batch has and the pool lacks: only the batch's prefixes are read. Repeating a batch adds nothing."""

    def __init__(self, spark: SparkSession, path: str, cfg: DedupConfig):
        self.spark, self.path, self.digest = spark, path.rstrip("/"), cfg.digest()

    def load(self) -> DataFrame | None:
        """The pool, or None before the first batch."""
        fs = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/bases").getFileSystem(self.spark._jsc.hadoopConfiguration())
        if not fs.exists(self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/bases")):
            return None
        held = self.spark.read.parquet(f"{self.path}/config").first()["digest"]
        if held != self.digest:
            raise ValueError("the pool belongs to another configuration")
        return self.spark.read.parquet(f"{self.path}/bases")

    def append(self, encoded: DataFrame) -> int:
        """Returns how many bases were new."""
        known = self.load()
        fresh = pool.build(encoded).select("basis_key", "basis")
        if known is None:
            self.spark.createDataFrame([(self.digest,)], "digest string").write.mode("overwrite").parquet(f"{self.path}/config")
        else:
            fresh = fresh.join(known.select("basis_key"), "basis_key", "left_anti")
        before = 0 if known is None else known.count()
        fresh.withColumn("prefix", F.hex(F.substring("basis_key", 1, 1))).repartition("prefix").write.mode("append").partitionBy("prefix").parquet(f"{self.path}/bases")
        return self.load().count() - before

    def compact(self, target: str) -> "PoolStore":
        """Writes the pool anew elsewhere, a file for each prefix."""
        whole = self.load()
        whole.repartition("prefix").sortWithinPartitions("basis_key").write.partitionBy("prefix").parquet(f"{target}/bases")
        self.spark.createDataFrame([(self.digest,)], "digest string").write.parquet(f"{target}/config")
        out = object.__new__(PoolStore)
        out.spark, out.path, out.digest = self.spark, target.rstrip("/"), self.digest
        return out
