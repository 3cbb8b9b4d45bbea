"""Exact histogram of encoded lengths, with suffix sums for every context limit.

One row per occurring length: documents and tokens of that length, documents and
tokens of at least that length, and the corpus total if each document were cut
to that many tokens. Any other limit falls between two rows and follows
from the row above it (``truncated_total``), as do quantiles (``quantile``).

Defined results: null and empty texts have length 0 and count; ids play no part, so
null ids and repeated rows count like others; an empty table gives no rows; further
columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import small_side, tidied, written
from .tokens import encoder

#: Lengths per block of the two-level suffix sums.
SPAN = 1024


def document_lengths(docs: DataFrame, text: str = "text", path: str | None = None) -> DataFrame:
    """(n_tokens, n_docs), counted within each batch; a length may come many times."""

    def run(batches):
        encode = encoder(path)
        width = int(encode.dtype[-1])
        for batch in batches:
            sizes = [len(ids) // width for ids in encode.packed(batch.column(0).cast(pa.binary()).to_pylist())]
            values, counts = np.unique(np.array(sizes, np.int64), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(values), pa.array(counts.astype(np.int64))], ["n_tokens", "n_docs"])

    return docs.select(text).mapInArrow(tidied(run, "encoders"), "n_tokens long, n_docs long")


def histogram(lengths: DataFrame) -> DataFrame:
    """The table described above, from rows (n_tokens, n_docs)."""
    counted = lengths.groupBy("n_tokens").agg(F.sum("n_docs").alias("n_docs"))
    counted = written(counted.withColumn("block", F.floor(F.col("n_tokens") / SPAN)).withColumn("tokens", F.col("n_tokens") * F.col("n_docs")), "lengths")
    blocks = counted.groupBy("block").agg(F.sum("n_docs").alias("d"), F.sum("tokens").alias("t"))
    # one row for each thousand of lengths that occurs, so one task sums them all
    above = Window.orderBy(F.desc("block")).rowsBetween(Window.unboundedPreceding, -1)
    after = small_side(written(blocks.select("block", F.sum("d").over(above).alias("d_after"), F.sum("t").over(above).alias("t_after")), "length-blocks"))
    within = Window.partitionBy("block").orderBy(F.desc("n_tokens")).rowsBetween(Window.unboundedPreceding, 0)
    summed = counted.join(after, "block", "left")
    docs_ge = F.sum("n_docs").over(within) + F.coalesce("d_after", F.lit(0))
    tokens_ge = F.sum("tokens").over(within) + F.coalesce("t_after", F.lit(0))
    out = summed.select("n_tokens", "n_docs", docs_ge.alias("docs_ge"), tokens_ge.alias("tokens_ge"))
    total = counted.agg(F.sum("tokens")).first()[0] or 0
    return out.withColumn("truncated_total", F.lit(int(total)) - F.col("tokens_ge") + F.col("docs_ge") * F.col("n_tokens"))


def truncated_total(table: DataFrame, limit: int) -> int:
    """Corpus tokens if each document kept at most ``limit``."""
    total = table.agg(F.sum(F.col("n_tokens") * F.col("n_docs"))).first()[0] or 0
    above = table.where(F.col("n_tokens") > limit).agg(F.min(F.struct("n_tokens", "docs_ge", "tokens_ge"))).first()[0]
    return total if above is None else total - above["tokens_ge"] + above["docs_ge"] * limit


def limits(table: DataFrame, sizes: list[int]) -> DataFrame:
    """(context_limit, documents_cut, tokens): what each limit cuts, and the corpus tokens it leaves, from the suffix sums."""
    whole = table.agg(F.sum(F.col("n_tokens") * F.col("n_docs"))).first()[0] or 0
    named = F.explode(F.array(*map(F.lit, sizes))).alias("context_limit")
    above = table.select("n_tokens", "docs_ge", "tokens_ge", named).where(F.col("n_tokens") > F.col("context_limit"))
    first = above.groupBy("context_limit").agg(F.min(F.struct("n_tokens", "docs_ge", "tokens_ge")).alias("x"))
    every = table.sparkSession.createDataFrame([(s,) for s in sizes], "context_limit int")
    cut, left = F.coalesce("x.docs_ge", F.lit(0)), F.lit(int(whole)) - F.coalesce("x.tokens_ge", F.lit(0))
    return every.join(first, "context_limit", "left").select(F.col("context_limit").cast("long").alias("context_limit"), cut.alias("documents_cut"), (left + cut * F.col("context_limit")).alias("tokens"))


def quantile(table: DataFrame, q: float) -> int | None:
    """Smallest length that at least a share ``q`` of the documents does not exceed."""
    documents = table.agg(F.sum("n_docs")).first()[0]
    if not documents:
        return None
    return table.where((F.lit(documents) - F.col("docs_ge") + F.col("n_docs")) >= F.lit(q) * documents).agg(F.min("n_tokens")).first()[0]
