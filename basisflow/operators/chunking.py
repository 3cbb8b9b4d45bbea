"""Content-defined chunks, as a comparison to fixed ones."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame

WINDOW = 32


def boundaries(data: bytes, least: int, average: int, most: int) -> list[int]:
    """Ends of chunks: places where a rolling hash of the last bytes is 0 modulo ``average``, within the given sizes."""
    if len(data) <= least:
        return [len(data)] if data else []
    x = np.frombuffer(data, np.uint8).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    x ^= x >> np.uint64(29)
    summed = np.concatenate([np.zeros(1, np.uint64), np.cumsum(x)])
    rolling = summed[WINDOW:] - summed[:-WINDOW] if len(data) >= WINDOW else np.zeros(0, np.uint64)
    rolling = (rolling ^ (rolling >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)
    marks = (np.nonzero((rolling >> np.uint64(20)) % np.uint64(average) == 0)[0] + WINDOW).tolist()
    ends, start = [], 0
    for mark in [*marks, len(data)]:
        while mark - start > most:
            start += most
            ends.append(start)
        if mark - start >= least or mark == len(data) and mark > start:
            ends.append(mark)
            start = mark
    return ends


def content_defined(payloads: DataFrame, least: int = 64, average: int = 256, most: int = 1024) -> DataFrame:
    """(source_id, packet_id, chunk_seq, size, chunk_key) of content-defined chunks."""

    def run(batches):
        for batch in batches:
            rows = []
            for source, packet, data in zip(batch.column(0), batch.column(1), batch.column(2), strict=True):
                data, start = data.as_py() or b"", 0
                for i, end in enumerate(boundaries(data, least, average, most)):
                    rows.append((source.as_py(), packet.as_py(), i, end - start, xxhash.xxh3_128_digest(data[start:end])))
                    start = end
            kinds = (pa.string(), pa.int64(), pa.int32(), pa.int64(), pa.binary())
            columns = zip(*rows, strict=True) if rows else [[]] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], ["source_id", "packet_id", "chunk_seq", "size", "chunk_key"])

    return payloads.select("source_id", "packet_id", "payload").mapInArrow(run, "source_id string, packet_id long, chunk_seq int, size long, chunk_key binary")
