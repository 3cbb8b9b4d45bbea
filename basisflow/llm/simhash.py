"""SimHash near-duplicate groups over one-wildcard segment variants.

A 64-bit fingerprint is cut into two 32-bit segments. Of two fingerprints that
differ in at most two bits, at least one segment differs in at most one, so
the two share that segment with one bit masked out. Every distinct fingerprint is
indexed under its 64 masked segments; an equality join on them, verified by
``bit_count``, finds every link. Only the first common key of a pair emits it.
Copies collapse to one fingerprint before the join, so no group of copies is
ever expanded into pairs.

Defined results: null and empty texts have fingerprint zero and are linked like any
other; repeated rows share a component; fingerprints of rows with null id take part in
links (their component is null where no row of it has an id); an empty table
gives no rows; further columns are ignored by ``near_groups`` and kept by ``keep_one``.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import similar
from .common import fresh, tidied, without, written
from .components import components

#: Fixed values of the contract.
SEED, SHINGLE, BITS_APART = 42, 3, 2
SEGMENT = 32
#: Shingles counted at once.
BLOCK = 1 << 16


def fingerprint(text: bytes, width: int = SHINGLE) -> int:
    """Majority bits of the shingles' XXH64; zero for a text without words."""
    words = text.lower().split()  # of bytes: only A-Z, only ASCII white space
    if not words:
        return 0
    shingles = [b" ".join(words)] if len(words) < width else list(map(b" ".join, zip(*(words[i:] for i in range(width)), strict=False)))
    digest, counts = xxhash.xxh64_intdigest, np.zeros(64, np.int64)
    for at in range(0, len(shingles), BLOCK):
        part = shingles[at : at + BLOCK]
        hashes = np.fromiter((digest(s, SEED) for s in part), "<u8", len(part))
        counts += np.add.reduce(np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little"), axis=0, dtype=np.int32)
    return int(np.packbits(counts * 2 > len(shingles), bitorder="little").view("<u8")[0])


def signatures(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, fp) with the fingerprint as a signed 64-bit integer."""

    def run(batches):
        for batch in batches:
            texts = batch.column(1).cast(pa.binary())
            fps = np.array([fingerprint(t.as_py() or b"") for t in texts], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fps)], ["doc_id", "fp"])

    return docs.select(F.col(key).cast("long"), text).mapInArrow(tidied(run), "doc_id long, fp long")


def _part(fp: Column, segment: int) -> Column:
    return F.shiftrightunsigned(fp, SEGMENT * segment).bitwiseAND(F.lit(0xFFFFFFFF))


def variants(fps: DataFrame) -> DataFrame:
    """(variant, fp): the fingerprint's segments, each with one bit masked, and which bit of 64 that is."""
    keys = [F.struct(F.lit(SEGMENT * s + bit).alias("slot"), _part(F.col("fp"), s).bitwiseAND(F.lit(0xFFFFFFFF ^ (1 << bit))).alias("rest")) for s in (0, 1) for bit in range(SEGMENT)]
    return fps.select("fp", F.explode(F.array(*keys)).alias("v")).select((F.shiftleft(F.col("v.slot").cast("long"), 32).bitwiseOR(F.col("v.rest"))).alias("variant"), "fp")


def links(fps: DataFrame, apart: int = BITS_APART) -> DataFrame:
    """Pairs (x, y) of distinct fingerprints, x < y, that differ in ``apart`` (0 to 2) bits or fewer; each pair once."""
    if not 0 <= apart <= 2:
        raise ValueError("two segments with one wildcard find up to two differing bits")
    left, right = variants(fps), variants(fps)
    differ = F.col("l.fp").bitwiseXOR(F.col("r.fp"))
    low = _part(differ, 0)
    first = F.when(low == 0, 0).when(F.bit_count(low) == 1, F.bit_count(low - 1)).otherwise(SEGMENT)
    # the optimizer takes an explode to be as small as its input, so the join is told not to broadcast
    found = left.alias("l").hint("merge").join(right.alias("r"), (F.col("l.variant") == F.col("r.variant")) & (F.col("l.fp") < F.col("r.fp")) & (F.bit_count(differ) <= apart) & (F.shiftright(F.col("l.variant"), 32) == first))
    return found.select(F.col("l.fp").alias("x"), F.col("r.fp").alias("y"))


def near_groups(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, fingerprint, component_id) for every row."""
    signed = written(signatures(docs, key, text), "simhash")
    fps = written(signed.groupBy("fp").agg(F.min("doc_id").alias("rep")), "simhash-fps")
    roots = components(links(fps.select("fp")), "x", "y")
    rooted = written(fps.join(roots.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "rep", F.coalesce("root", "fp").alias("root")), "simhash-roots")
    least = rooted.groupBy("root").agg(F.min("rep").alias("component_id"))
    classes = written(rooted.select("fp", "root").join(least, "root").select(F.col("fp").alias("f"), "component_id"), "simhash-classes")
    return signed.join(classes, F.col("fp") == F.col("f")).select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One document of each near-duplicate group: the one with the smallest id (nulls last; of repeated rows one); columns as given.

    Groups are those of ``similar``: the links of ``near_groups`` are candidates there, held against the shingles, beside others, as most texts
    with a few replaced words are more than two bits apart. Where ids are null or repeated, the rows are numbered and written first.
    """
    ids = docs.groupBy(F.col(key).cast("long").alias("id")).count()
    name = fresh("row")
    if ids.where("id IS NULL OR count > 1").limit(1).count():
        rows = written(docs.withColumn(name, F.monotonically_increasing_id()), "simhash-rows")
        found = similar.groups(rows, key=name, text=text).withColumnsRenamed({"doc_id": name, "component_id": "group"})
        first = F.struct(F.col(key).isNull().alias("null"), F.col(key).cast("long").alias("id"), F.col(name).alias("row"))
        found = written(found.join(rows.select(name, first.alias("first")), name), "simhash-groups")
        least = found.groupBy("group").agg(F.min("first").alias("least"))
        gone = found.join(least, "group").where(F.col("first.row") != F.col("least.row")).select(name)
    else:
        rows = docs.withColumn(name, F.col(key).cast("long"))
        gone = similar.groups(docs, key=key, text=text).where("doc_id <> component_id").select(F.col("doc_id").alias(name))
    return without(rows, written(gone, "simhash-gone"), name).select(docs.columns)
