"""Baseline compressors, per packet: DEFLATE, LZW, and two more of the standard library."""

from __future__ import annotations

import bz2
import lzma
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame


def lzw_encode(data: bytes, max_bits: int = 16) -> tuple[list[int], int]:
    """(codes, bits): codes start at 9 bits and widen as the table grows; a full table stays as it is."""
    table = {bytes([i]): i for i in range(256)}
    codes, bits, width, word = [], 0, 9, b""
    for i in range(len(data)):
        longer = word + data[i : i + 1]
        if longer in table:
            word = longer
            continue
        codes.append(table[word])
        bits += width
        if len(table) < 1 << max_bits:
            table[longer] = len(table)
            width = max(width, (len(table)).bit_length())
        word = data[i : i + 1]
    if word:
        codes.append(table[word])
        bits += width
    return codes, bits


def lzw_decode(codes: list[int], max_bits: int = 16) -> bytes:
    table = [bytes([i]) for i in range(256)]
    out, last = [], b""
    for code in codes:
        word = table[code] if code < len(table) else last + last[:1]
        out.append(word)
        if last and len(table) < 1 << max_bits:
            table.append(last + word[:1])
        last = word
    return b"".join(out)


def lzw_size(data: bytes, max_bits: int = 16) -> int:
    """Bytes of ``lzw_encode``, without the codes: words are numbered, and the 256 of one byte need no table."""
    if not data:
        return 0
    table: dict[int, int] = {}
    rest = iter(data)
    word, size, bits, width, most = next(rest), 256, 0, 9, 1 << max_bits
    for byte in rest:
        longer = word << 8 | byte
        if longer in table:
            word = table[longer]
            continue
        bits += width
        if size < most:
            table[longer] = size
            size += 1
            if size >> width:
                width += 1
        word = byte
    return -(-(bits + width) // 8)


def _lzw_saved(data: bytes, repeats) -> int:
    """By how much the codes are fewer than the bytes; ``repeats`` are (place, first place of the same pair, pair as a number), in order.

    A pair is in the table when a code of one byte was written at its first place, or at a later one.
    """
    inner, late, longer, saved, end = set(), set(), {}, 0, 0  # inner: places within a code, late: pairs entered after their first place
    for at, first, word in repeats:
        if at < end:
            continue
        if first in inner and word not in late:
            late.add(word)
            continue
        end = at + 2
        while end < len(data):
            key = word << 8 | data[end]
            if key not in longer:
                longer[key] = (1 << 16) + len(longer)
                break
            word = longer[key]
            end += 1
        saved += end - at - 1
        inner.update(range(at + 1, end))
    return saved


#: Longest chunk that cannot fill a table of 16 bits, and the bits of so many codes.
LZW_LONGEST = (1 << 16) - 256
LZW_BITS = np.concatenate([[0], np.cumsum([max(9, size.bit_length()) for size in range(256, 1 << 16)])])


def lzw_sizes(chunks: list[bytes]) -> list[int]:
    """``lzw_size`` of chunks of one length, each alone.

    The size follows from the number of codes, and only a pair of bytes that the chunk had before can start a code of more than one: these
    are found by sorting the pairs of many chunks at once. A chunk where they are many takes ``lzw_size``.
    """
    length = len(chunks[0]) if chunks else 0
    if not 2 <= length <= LZW_LONGEST:
        return [lzw_size(c) for c in chunks]
    out, step = [], max(1, (1 << 16) // length)
    for start in range(0, len(chunks), step):
        some = chunks[start : start + step]
        data = np.frombuffer(b"".join(some), np.uint8).reshape(len(some), length).astype(np.uint32)
        keys = data[:, :-1] << 24 | data[:, 1:] << 16 | np.arange(length - 1, dtype=np.uint32)
        keys.sort(axis=1)
        again = np.zeros(keys.shape, bool)
        np.equal(keys[:, 1:] >> 16, keys[:, :-1] >> 16, out=again[:, 1:])
        many = again.sum(axis=1) > length // 4
        again[many] = False
        found, saved = np.flatnonzero(again), np.zeros(len(some), np.int64)
        if len(found):
            heads = np.diff(found, prepend=-1) != 1  # the first repeat of its pair; a row's first key never is one
            keys = keys.ravel()
            firsts = (keys[found[heads] - 1] & 0xFFFF)[np.cumsum(heads) - 1]
            rows, places, pairs = found // (length - 1), keys[found] & 0xFFFF, keys[found] >> 16
            order = np.lexsort((places, rows))
            repeats = list(zip(places[order].tolist(), firsts[order].tolist(), pairs[order].tolist(), strict=True))
            with_repeats, begins = np.unique(rows[order], return_index=True)
            for row, low, high in zip(with_repeats.tolist(), begins.tolist(), [*begins[1:].tolist(), len(repeats)], strict=True):
                saved[row] = _lzw_saved(some[row], repeats[low:high])
        sizes = (LZW_BITS[length - saved] + 7) // 8
        for row in np.flatnonzero(many).tolist():
            sizes[row] = lzw_size(some[row])
        out += sizes.tolist()
    return out


def deflate_size(data: bytes, level: int = 6, raw: bool = True) -> int:
    return len(zlib.compress(data, level, -15 if raw else 15))


CODECS = {"deflate": deflate_size, "lzw": lzw_size, "bz2": lambda d: len(bz2.compress(d)), "lzma": lambda d: len(lzma.compress(d, format=lzma.FORMAT_RAW, filters=[{"id": lzma.FILTER_LZMA2, "preset": 6}]))}


def codec_totals(payloads: DataFrame, codecs: list[str], n_bs: list[int], deal: bool = True) -> DataFrame:
    """(codec, n_b, chunks, original_bytes, total_bytes), each chunk compressed alone; summed in each task first.

    Payloads are dealt evenly first, unless they are already (``deal``): compressing takes far longer than moving them, and a file may be one row
    group, which one task reads. Of equal chunks of a batch, or of about 8 MB of it, one is compressed.
    """
    from collections import Counter

    from pyspark.sql import functions as F

    from basisflow.sources.payloads import dealt

    def step(column):
        return max(1, (len(column) << 23) // max(1, column.nbytes))

    def run(batches):
        sums: dict = {}
        columns = (batch.column(0) for batch in batches)
        for column, at in ((c, i) for c in columns for i in range(0, len(c), step(c))):
            texts = [data or b"" for data in column.slice(at, step(column)).to_pylist()]
            for n_b in n_bs:
                chunks = Counter(data[i : i + n_b].ljust(n_b, b"\0") for data in texts for i in range(0, len(data), n_b))
                if not chunks:
                    continue
                for codec in codecs:
                    total = sums.setdefault((codec, n_b), [0, 0])
                    total[0] += chunks.total()
                    sizes = lzw_sizes(list(chunks)) if codec == "lzw" else map(CODECS[codec], chunks)
                    total[1] += sum(map(int.__mul__, sizes, chunks.values()))
        if sums:
            keys, totals = list(sums), list(sums.values())
            yield pa.RecordBatch.from_arrays([pa.array([k[0] for k in keys]), pa.array([k[1] for k in keys], pa.int64()), pa.array([t[0] for t in totals], pa.int64()), pa.array([t[1] for t in totals], pa.int64())], ["codec", "n_b", "chunks", "bytes"])

    rows = dealt(payloads.select("packet_id", "payload"), "packet_id") if deal else payloads
    parts = rows.select("payload").mapInArrow(run, "codec string, n_b long, chunks long, bytes long")
    return parts.groupBy("codec", "n_b").agg(F.sum("chunks").alias("chunks"), (F.sum("chunks") * F.col("n_b")).alias("original_bytes"), F.sum("bytes").alias("total_bytes"))


def stream_totals(payloads: DataFrame, level: int = 6) -> DataFrame:
    """(source_id, original_bytes, total_bytes): each source's packets, in order, through one DEFLATE stream.

    Sources are sorted within partitions and read as a stream; a packet is flushed before the next, as it has to be sent.
    """
    from pyspark.sql import functions as F

    def run(batches):
        current, packer, sizes = None, None, [0, 0]

        def row():
            return pa.RecordBatch.from_arrays([pa.array([current]), pa.array([sizes[0]], pa.int64()), pa.array([sizes[1]], pa.int64())], ["source_id", "original_bytes", "total_bytes"])

        for batch in batches:
            for source, data in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                if packer is None or source != current:
                    if packer is not None:
                        yield row()
                    current, packer, sizes = source, zlib.compressobj(level, zlib.DEFLATED, -15), [0, 0]
                data = data.as_py() or b""
                sizes[0] += len(data)
                sizes[1] += len(packer.compress(data)) + len(packer.flush(zlib.Z_SYNC_FLUSH))
        if packer is not None:
            yield row()

    keyed = payloads.select(F.col("source_id").cast("string").alias("source_id"), "payload", "packet_id")
    ordered = keyed.repartition("source_id").sortWithinPartitions("source_id", "packet_id").select("source_id", "payload")
    return ordered.mapInArrow(run, "source_id string, original_bytes long, total_bytes long")
