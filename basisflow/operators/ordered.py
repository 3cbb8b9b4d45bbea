"""Places of rows within their source, and sums over the rows before, where a source may be as large as the table."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from basisflow.operators.pool import shared_folder


def checkpointed(df: DataFrame) -> DataFrame:
    """The rows in the shared folder, in the partitions they have."""
    context = df.sparkSession.sparkContext
    if not context._jsc.sc().getCheckpointDir().isDefined():
        context.setCheckpointDir(shared_folder(df.sparkSession))
    return df.checkpoint()


def numbered(rows: DataFrame, source: str, order: list[str], name: str = "at") -> DataFrame:
    """Adds the place of each row within its source, from 0.

    Rows are range-sorted by source and order, so a source lies in neighbouring partitions, each of which
    counts on from those before. Only the first and the last source of every partition go through the driver.
    """
    ordered = checkpointed(rows.repartitionByRange(source, *order).sortWithinPartitions(source, *order))
    counts = ordered.groupBy(F.spark_partition_id().alias("p"), F.col(source).alias("s")).agg(F.count("*").alias("n"))
    edges = counts.groupBy("p").agg(F.min(F.struct("s", "n")).alias("first"), F.max(F.struct("s", "n")).alias("last")).collect()
    carry, open_, so_far = {}, None, 0
    for p, first, last in sorted((e["p"], tuple(e["first"]), tuple(e["last"])) for e in edges):
        carry[p] = so_far if open_ == (first[0],) else 0
        so_far = (carry[p] if first[0] == last[0] else 0) + last[1]
        open_ = (last[0],)
    at = ordered.columns.index(source)

    def run(batches):
        from pyspark import TaskContext

        current, n = None, carry.get(TaskContext.get().partitionId(), 0)
        for batch in batches:
            if not batch.num_rows:
                continue
            own = batch.column(at).to_pylist()
            codes = np.unique(np.array([str(x) for x in own]), return_inverse=True)[1]
            new = np.ones(len(own), bool)
            new[1:] = codes[1:] != codes[:-1]
            starts = np.nonzero(new)[0]
            places = np.arange(len(own)) - np.repeat(starts, np.diff(np.append(starts, len(own))))
            if current is None or current == (own[0],):  # the first source goes on
                until = starts[1] if len(starts) > 1 else len(own)
                places[:until] += n
            current, n = (own[-1],), int(places[-1]) + 1
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(places)], [*batch.schema.names, name])

    return ordered.mapInArrow(run, StructType([*ordered.schema.fields, StructField(name, LongType())]))


def sums_before(rows: DataFrame, source: str, at: str, value: Column, count: int, name: str) -> DataFrame:
    """(source, ``name``): the sum of ``value`` over each row and the ``count`` before it, in stretches that overlap by so many rows."""
    stretch = max(1024, 64 * count)
    number = F.floor(F.col(at) / stretch)
    # the last rows of a stretch are also the beginning of the next
    both = F.when(F.col(at) % stretch >= stretch - count, F.array(number, number + 1)).otherwise(F.array(number))
    spread = rows.select(source, at, value.alias("value"), F.explode(both).alias("stretch"))
    window = Window.partitionBy(source, "stretch").orderBy(at).rowsBetween(-count, 0)
    summed = spread.select(source, at, "stretch", F.sum("value").over(window).alias(name))
    return summed.where(F.col("stretch") == F.floor(F.col(at) / stretch)).select(source, name)
