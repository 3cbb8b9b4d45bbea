"""A corpus pipeline: five of the training-data operators, one after the other.

Each stage takes the documents that its predecessor kept. All but the last return the
columns of ``documents``; ``run`` writes every stage as Parquet and reads it again.
Texts are never cut short: language ID, near-dedup and decontamination drop whole
documents, the secret scan masks what it finds, packing returns pieces of sequences.

Defined results: documents whose text is null, empty or without a letter have no language and go in
the first stage; rows with null or repeated ids are documents like others, of equal texts one
stays (the smallest id, nulls last); null ``lang``, ``source`` and ``n_chars`` play no part; texts of any length are read
whole; further columns are kept, whatever their names, up to the last stage, which returns its own; an empty
table gives no rows. A stage's outcome does not depend on ties: they fall to the smaller id, or the first by hash.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from basisflow.llm import decontam, langid, packing, secrets, simhash
from basisflow.llm.common import fresh, table, written


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents in no known language (op 9)."""
    return langid.accepted(docs)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the smallest id of each group of texts whose 5-word shingles have a similarity of 0.8 or more (op 8)."""
    return simhash.keep_one(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that hold a copy of a benchmark item (op 4)."""
    return decontam.clean(docs, table(spark, sf_dir, "benchmark"))


def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Masks secrets; documents that held some get a new character count (op 1)."""
    before = fresh("before")
    masked = secrets.redact(docs.withColumn(before, F.col("text")))
    changed = ~F.col("text").eqNullSafe(F.col(before))
    return masked.withColumn("n_chars", F.when(changed, F.char_length("text").cast("long")).otherwise(F.col("n_chars"))).select(docs.columns)


def sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packs what is left into token sequences along a Hilbert curve (op 5)."""
    return packing.pack(docs, lean=True)


STAGES = [("language", language), ("near_dedup", near_dedup), ("decontamination", decontamination), ("secrets", mask_secrets), ("packing", sequences)]

#: SQL has no tokenizer, no trained model and no 64-bit XXH; ``tests/llm`` holds each stage against plain Python.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
