"""Shared helpers of the training-data operators."""

from __future__ import annotations

import atexit
import ctypes
import gc
import shutil
import tempfile
import uuid

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Caches that outlive a task in a Python worker, by name.
KEPT: dict[str, dict] = {}
#: Largest row count of a table of fixed-width rows that is sent to every executor.
BROADCAST_ROWS = 500_000
#: Rows and bytes of an Arrow batch that a worker turns into Python objects at once.
PORTION_ROWS, PORTION_BYTES = 2000, 8_000_000


def fresh(name: str) -> str:
    """A column name that no input has."""
    return f"{name}_{uuid.uuid4().hex}"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that the driver and all executors see, from the session.

    Where ``spark.checkpoint.dir`` is unset, a temporary folder is set on one machine;
    a cluster must name its folder.
    """
    folder = spark.conf.get("spark.checkpoint.dir", None) or _context_dir(spark)
    if folder is None:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        folder = tempfile.mkdtemp(prefix="basisflow-")
        atexit.register(shutil.rmtree, folder, ignore_errors=True)
        spark.sparkContext.setCheckpointDir(folder)
    elif _context_dir(spark) is None:
        spark.sparkContext.setCheckpointDir(folder)
    return folder.rstrip("/")


def _context_dir(spark: SparkSession) -> str | None:
    option = spark.sparkContext._jsc.sc().getCheckpointDir()
    return option.get() if option.isDefined() else None


def written(df: DataFrame, label: str) -> DataFrame:
    """Cuts lineage: writes ``df`` to the shared folder and reads it again."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/basisflow/{label}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def small_side(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """Hints a broadcast of a written table only if it is counted to be small."""
    return F.broadcast(df) if df.count() <= rows else df


def within(df: DataFrame, keys: DataFrame, key: str) -> DataFrame:
    """The rows of ``df`` whose ``key`` is in the written table ``keys``, without a shuffle of ``df``; where that has too many rows to be broadcast, also a few others."""
    if keys.count() <= BROADCAST_ROWS:
        return df.join(F.broadcast(keys), key, "left_semi")
    return _marked(df, keys, key, True)


def without(df: DataFrame, keys: DataFrame, key: str) -> DataFrame:
    """The rows of ``df`` whose ``key`` is not in the written table ``keys``; only those that may be in it are shuffled, and only where it is too large to be broadcast."""
    if keys.count() <= BROADCAST_ROWS:
        return df.join(F.broadcast(keys), key, "left_anti")
    return _marked(df, keys, key, False).unionByName(_marked(df, keys, key, True).join(keys, key, "left_anti"))


def _marked(df: DataFrame, keys: DataFrame, key: str, hit: bool) -> DataFrame:
    """The rows of ``df`` whose hashed ``key`` is marked by one of ``keys``, or those that none marks: one bit a hash, in at most ``BROADCAST_ROWS`` words of 64."""
    word, bits = fresh("word"), fresh("bits")
    hashed = F.pmod(F.xxhash64(F.col(key).cast("long")), F.lit(64 * BROADCAST_ROWS))
    place, bit = F.floor(hashed / 64), F.pmod(hashed, F.lit(64)).cast("int")
    one = F.call_function("shiftleft", F.lit(1).cast("long"), bit)
    marks = written(keys.groupBy(place.alias(word)).agg(F.bit_or(one).alias(bits)), "marks")
    found = df.withColumn(word, place).join(F.broadcast(marks), word, "left")
    return found.where(F.coalesce(F.getbit(bits, bit), F.lit(0)) == int(hit)).select(df.columns)


def free_but(keeps: str | None):
    """Empties this worker's caches of other names."""
    for name, cache in KEPT.items():
        if name != keeps:
            cache.clear()


def portions(batches):
    """The same rows in slices of the batches: what a task makes of its texts is held for one slice, not for the 10,000 rows that Spark sends at once."""
    for batch in batches:
        rows = max(1, min(PORTION_ROWS, PORTION_BYTES * batch.num_rows // max(1, batch.nbytes)))
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)


def tidied(run, keeps: str | None = None):
    """The same function of Arrow batches; when a task ends, free memory goes back to the machine, as workers live on for other stages.

    Caches of ``KEPT`` are for tasks that name them: a task of another kind frees them first, so that a worker holds no stage's cache through other stages.
    """

    def inner(batches):
        free_but(keeps)
        try:
            yield from run(batches)
        finally:
            gc.collect()
            pa.default_memory_pool().release_unused()
            try:
                ctypes.CDLL(None).malloc_trim(0)
            except (AttributeError, OSError):  # another C library
                pass

    return inner
