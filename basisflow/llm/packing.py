"""Packing of encoded documents along a Hilbert curve.

Token ids are hashed into a few signed dimensions; a document's mean vector is
quantised and gets its Hilbert index. Documents sorted by (index, row) lie end to
end on one line of tokens, cut into sequences: neighbours on the curve share
sequences, and only the end of the line needs care, where the rest is cut into
powers of two, which need no padding.

The heavy ids are written once and never sorted: only (index, row, tokens) is
range-sorted, which yields each document's place on the line.

Defined results: null and empty texts are the single closing id; rows with equal or
null ids are packed one by one; ties on the curve follow the row number; an empty
table gives no rows; further columns are ignored.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import portions, shared_dir, tidied, written
from .tokens import CACHE_PIECES, encoder

#: Fixed values of the contract.
SEQUENCE, CLOSING = 2048, 1
#: Dimensions and bits of each on the curve: 60 bits in all.
DIMENSIONS, BITS = 4, 15
LANES = np.arange(DIMENSIONS, dtype=np.uint64) * np.uint64(16)


def hilbert_index(points: np.ndarray, bits: int = BITS) -> np.ndarray:
    """Hilbert indices of rows of unsigned coordinates below ``2**bits``.

    The axes-to-transpose transform, published by J. Skilling in 2004, on all rows at once.
    """
    x = np.array(points, np.int64).T.copy()
    n = len(x)
    for level in range(bits - 1, 0, -1):
        q, low = 1 << level, (1 << level) - 1
        for i in range(n):
            set_ = (x[i] & q) != 0
            swap = np.where(set_, 0, (x[0] ^ x[i]) & low)
            x[0] ^= np.where(set_, low, swap)
            x[i] ^= swap
    for i in range(1, n):
        x[i] ^= x[i - 1]
    flip = np.zeros_like(x[0])
    for level in range(bits - 1, 0, -1):
        flip ^= np.where((x[n - 1] >> level) & 1, (1 << level) - 1, 0)
    x ^= flip
    index = np.zeros_like(x[0])
    for level in range(bits - 1, -1, -1):
        for i in range(n):
            index = (index << 1) | ((x[i] >> level) & 1)
    return index


def token_vectors(size: int = 1 << 16) -> np.ndarray:
    """A fixed pseudo-random number of four bytes for each id (ids beyond ``size`` wrap around), a byte in each 16 bits: one for each dimension."""
    ids = np.arange(size, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    ids ^= ids >> np.uint64(29)
    ids *= np.uint64(0xBF58476D1CE4E5B9)
    ids ^= ids >> np.uint64(32)
    lanes = [((ids >> np.uint64(8 * d)) & np.uint64(255)) << np.uint64(16 * d) for d in range(DIMENSIONS)]
    return np.bitwise_or.reduce(lanes)


def curve_key(ids: np.ndarray, table: np.ndarray) -> np.ndarray:
    """Quantised mean vector of one document; a byte v stands for v / 127.5 - 1."""
    found = table.take(ids & (len(table) - 1))
    # 256 bytes fit into the 16 bits of a lane
    parts = np.add.reduceat(found, np.arange(0, len(found), 256)) if len(found) else found
    sums = ((parts[:, None] >> LANES) & np.uint64(0xFFFF)).sum(0).astype(np.float64)
    mean = sums / 127.5 / max(1, len(ids)) - (len(ids) > 0)
    spread = np.clip(mean * 2 + 0.5, 0, 1)  # means are small; most of the cube is used
    return np.minimum((spread * (1 << BITS)).astype(np.int64), (1 << BITS) - 1)


def encoded(docs: DataFrame, key: str = "doc_id", text: str = "text", path: str | None = None, lean: bool = False) -> DataFrame:
    """(doc_id, curve, n_tokens, ids) with the closing id; ids are little-endian unsigned 16- or 32-bit.

    ``lean``: half the cache of words, of which only the younger generation outlives a task, where workers serve other stages too.
    """

    def run(batches):
        encode, table = encoder(path, CACHE_PIECES // 2 if lean else CACHE_PIECES), token_vectors()
        closing = np.array([CLOSING], encode.dtype).tobytes()
        for batch in portions(batches):
            points, sizes, packed = [], [], []
            for own in encode.packed(batch.column(1).cast(pa.binary()).to_pylist()):
                own += closing
                ids = np.frombuffer(own, encode.dtype)
                points.append(curve_key(ids, table))
                sizes.append(len(ids))
                packed.append(own)
            if sizes:
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(hilbert_index(np.array(points))), pa.array(sizes, pa.int64()), pa.array(packed, pa.binary())], ["doc_id", "curve", "n_tokens", "ids"])
        if lean:
            encode.forget_older()

    return docs.select(F.col(key).cast("long"), text).mapInArrow(tidied(run, "encoders"), "doc_id long, curve long, n_tokens long, ids binary")


def line_places(light: DataFrame) -> DataFrame:
    """(row, at): where each row's tokens start on the line; ``light`` has row, curve, n_tokens."""
    spark = light.sparkSession
    shared_dir(spark)
    ordered = light.repartitionByRange(F.col("curve"), F.col("row")).sortWithinPartitions("curve", "row").select("row", "n_tokens").checkpoint()
    sums = ordered.groupBy(F.spark_partition_id().alias("p")).agg(F.sum("n_tokens").alias("n")).collect()  # a number for each partition
    firsts, total = {}, 0
    for p, n in sorted(sums):
        firsts[p], total = total, total + n

    def run(batches):
        from pyspark import TaskContext

        at = firsts.get(TaskContext.get().partitionId(), 0)
        for batch in batches:
            sizes = batch.column(1).to_numpy()
            ends = at + np.cumsum(sizes)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(ends - sizes)], ["row", "at"])
            at = int(ends[-1]) if len(ends) else at

    return ordered.mapInArrow(tidied(run), "row long, at long").withColumn("total", F.lit(total).cast("long"))


def cut(start: int, length: int, total: int, size: int = SEQUENCE):
    """Pieces (offset in the document, length, sequence, offset there) of a stretch of the line."""
    whole, at, end = total // size * size, start, start + length
    while at < end:
        if at < whole:
            number, first, last = at // size, at // size * size, (at // size + 1) * size
        else:  # the rest: its binary digits, the largest first
            rest, first, number = total - whole, whole, whole // size
            width = 1 << (rest.bit_length() - 1)
            while at >= first + width:
                first, rest, number = first + width, rest - width, number + 1
                width = 1 << (rest.bit_length() - 1)
            last = first + width
        stop = min(end, last)
        yield at - start, stop - at, number, at - first
        at = stop


def pack(docs: DataFrame, key: str = "doc_id", text: str = "text", path: str | None = None, size: int = SEQUENCE, with_ids: bool = False, lean: bool = False) -> DataFrame:
    """One row per piece; ``with_ids`` adds the piece's ids as an array, ``lean`` is as in ``encoded``."""
    rows = written(encoded(docs, key, text, path, lean).withColumn("row", F.monotonically_increasing_id()), "encoded")
    places = written(line_places(rows.select("row", "curve", "n_tokens")), "places")
    # places looks small to the optimizer, as it compresses well, but grows with the rows: no broadcast
    placed = rows.select("row", "doc_id", "n_tokens", "ids").join(places.hint("merge"), "row").select("doc_id", "n_tokens", "ids", "at", "total")

    def run(batches):
        for batch in portions(batches):
            out = {n: [] for n in ("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")}
            pieces = []
            for doc, n, raw, at, total in zip(*(batch.column(i).to_pylist() for i in range(5)), strict=True):
                ids = np.frombuffer(raw, "<u2" if len(raw) == 2 * n else "<u4").astype("<u4")
                for start, length, number, offset in cut(at, n, total, size):
                    part = ids[start : start + length]
                    for name, value in zip(out, (doc, start, length, zlib.crc32(part.tobytes()), n, number, offset), strict=True):
                        out[name].append(value)
                    if with_ids:
                        pieces.append(part.astype(np.int32))
            arrays = [pa.array(v, pa.int64()) for v in out.values()] + ([pa.array(pieces, pa.list_(pa.int32()))] if with_ids else [])
            yield pa.RecordBatch.from_arrays(arrays, [*out, *(["ids"] if with_ids else [])])

    kinds = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
    return placed.mapInArrow(tidied(run), kinds + (", ids array<int>" if with_ids else ""))


def sequences(pieces: DataFrame) -> DataFrame:
    """(sequence_id, ids, doc_ids): the sequences themselves, from pieces with ids; padding is left to the reader."""
    parts = F.array_sort(F.collect_list(F.struct("offset", "ids", "doc_id")))
    return pieces.groupBy("sequence_id").agg(parts.alias("p")).select("sequence_id", F.flatten(F.transform("p", lambda x: x["ids"])).alias("ids"), F.transform("p", lambda x: x["doc_id"]).alias("doc_ids"))
