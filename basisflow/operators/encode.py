"""Payloads to chunks, bases and deviations.

``encode_payloads`` keeps a row per chunk; ``unique_chunks`` never makes such rows:
each Arrow batch is cut, split and counted by one kernel, and only distinct
chunks of a batch leave it, so what is shuffled follows distinct chunks, not bytes.

Chunks and bases are named by identity keys: their own bytes up to 16, beyond that a
128-bit hash. These keys are the engine's; fingerprints that go over a wire are modelled
apart, in ``schemes``.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from basisflow.config import DedupConfig
from basisflow.functions import hamming, preprocess, reed_solomon

#: Bytes of chunks handled by the kernel at once.
BLOCK = 1 << 23


def chunk_payloads(payloads: DataFrame, n_b: int, pad: bool = True) -> DataFrame:
    """One row per chunk, in plain columns: chunk_seq, chunk (zero-padded), valid_len."""
    size = F.octet_length("payload")
    places = F.sequence(F.lit(0), F.ceil(size / n_b).cast("int") - 1)
    out = payloads.where(size > 0).select(*(c for c in payloads.columns if c != "payload"), "payload", F.explode(places).alias("chunk_seq"))
    piece = F.substring("payload", F.col("chunk_seq") * n_b + 1, F.lit(n_b))
    out = out.withColumn("chunk", piece).withColumn("valid_len", F.octet_length("chunk")).drop("payload")
    return out.withColumn("chunk", F.rpad("chunk", n_b, F.lit(b"\0"))) if pad else out


def cut(payloads: list[bytes], n_b: int):
    """(chunks as rows of bytes, payload number, number in the payload, valid bytes) of zero-padded payloads."""
    sizes = np.array([len(p) for p in payloads], np.int64)
    counts = -(-sizes // n_b)
    flat = np.frombuffer(b"".join(p.ljust(int(c) * n_b, b"\0") for p, c in zip(payloads, counts, strict=True)), np.uint8).reshape(-1, n_b)
    owner = np.repeat(np.arange(len(payloads)), counts)
    place = np.arange(len(owner)) - np.repeat(np.cumsum(counts) - counts, counts)
    return flat, owner, place, np.minimum(n_b, sizes[owner] - place * n_b)


def split(chunks: np.ndarray, cfg: DedupConfig, with_basis: bool = True):
    """(basis rows, deviations as rows of bytes, as a list of bytes where their lengths differ, or None, and their lengths).

    Without ``with_basis`` the error-free word stands for the basis: there is one for each.
    """
    body, side = preprocess.apply(chunks, cfg.preprocess, cfg.sample_width)
    n = len(body)
    if cfg.transform == "identity":
        basis, own = body, np.zeros((n, 0), np.uint8)
    elif cfg.transform == "hamming":
        words, syndrome, spare = hamming.codewords(body)
        basis = hamming.pack_basis(words) if with_basis else words
        width = cfg.fixed_deviation - cfg.side_bytes
        value = (syndrome << 1) | spare
        own = np.stack([(value >> (8 * (width - 1 - i))) & 0xFF for i in range(width)], 1).astype(np.uint8)
    else:
        basis, wrong = reed_solomon.split(body, cfg.basis_bytes)
        fixed = cfg.fixed_deviation
        lengths = np.full(n, fixed, np.int64) if fixed else 2 * (wrong != 0).sum(1) + cfg.side_bytes
        if not with_basis:
            return basis, None, lengths
        own = reed_solomon.pairs(wrong)
        return basis, [o + s.tobytes() for o, s in zip(own, side, strict=True)] if side is not None else own, lengths
    lengths = np.full(n, cfg.fixed_deviation, np.int64)
    if not with_basis:
        return basis, None, lengths
    whole = own if side is None else np.concatenate([own, side], axis=1)
    return basis, whole, lengths


def restore(bases: np.ndarray, deviations: list[bytes], cfg: DedupConfig) -> np.ndarray:
    """Chunks from bases and deviations."""
    side = None
    if cfg.side_bytes:
        side = np.frombuffer(b"".join(d[len(d) - cfg.side_bytes :] for d in deviations), np.uint8).reshape(-1, cfg.side_bytes)
        deviations = [d[: len(d) - cfg.side_bytes] for d in deviations]
    if cfg.transform == "identity":
        body = bases
    elif cfg.transform == "hamming":
        value = np.zeros(len(bases), np.int64)
        for part in np.frombuffer(b"".join(deviations), np.uint8).reshape(len(bases), -1).T:
            value = value << 8 | part
        body = hamming.join(bases, value >> 1, value & 1, hamming.m_for_chunk(cfg.n_b))
    else:
        body = reed_solomon.join(bases, deviations, cfg.body_bytes)
    return preprocess.undo(body, side, cfg.preprocess, cfg.sample_width)


def binary(rows: np.ndarray) -> pa.Array:
    """Rows of bytes as an Arrow column, without Python objects."""
    rows = np.ascontiguousarray(rows)
    offsets = np.arange(len(rows) + 1, dtype=np.int64) * rows.shape[1]
    if offsets[-1] >= 1 << 31:
        raise ValueError("a batch of bodies must stay under 2 GiB")
    return pa.BinaryArray.from_buffers(pa.binary(), len(rows), [None, pa.py_buffer(offsets.astype(np.int32)), pa.py_buffer(rows)])


def keys(rows: np.ndarray) -> pa.Array:
    """Identity keys of rows of bytes."""
    if rows.shape[1] <= 16:
        return binary(rows)
    digest, body, n = xxhash.xxh3_128_digest, memoryview(np.ascontiguousarray(rows)).cast("B"), rows.shape[1]
    return pa.array([digest(body[i : i + n]) for i in range(0, len(rows) * n, n)], pa.binary())


def _blocks(payloads: list[bytes], n_b: int):
    """Whole payloads of about ``BLOCK`` bytes; a longer one stays whole."""
    part, size = [], 0
    for p in payloads:
        part.append(p)
        size += len(p)
        if size >= BLOCK:
            yield part
            part, size = [], 0
    if part:
        yield part


def encode_payloads(payloads: DataFrame, cfg: DedupConfig) -> DataFrame:
    """A row per chunk: source_id, packet_id, chunk_seq, valid_len, chunk_key, basis_key, basis, deviation, dev_bytes."""

    def run(batches):
        for batch in batches:
            source, packet = batch.column(0), batch.column(1)
            data = [p or b"" for p in batch.column(2).to_pylist()]
            first = 0
            for part in _blocks(data, cfg.n_b):
                chunks, owner, place, valid = cut(part, cfg.n_b)
                if len(chunks):
                    basis, deviation, lengths = split(chunks, cfg)
                    rows = pa.array(owner + first)
                    yield pa.RecordBatch.from_arrays([source.take(rows), packet.take(rows), pa.array(place.astype(np.int32)), pa.array(valid.astype(np.int32)), keys(chunks), keys(basis), binary(basis), binary(deviation) if isinstance(deviation, np.ndarray) else pa.array(deviation, pa.binary()), pa.array(lengths)], ["source_id", "packet_id", "chunk_seq", "valid_len", "chunk_key", "basis_key", "basis", "deviation", "dev_bytes"])
                first += len(part)

    schema = "source_id string, packet_id long, chunk_seq int, valid_len int, chunk_key binary, basis_key binary, basis binary, deviation binary, dev_bytes long"
    return payloads.select(F.col("source_id").cast("string"), F.col("packet_id").cast("long"), "payload").mapInArrow(run, schema)


def unique_chunks(payloads: DataFrame, configs: list[DedupConfig], by_source: bool = False) -> DataFrame:
    """Distinct chunks for each configuration: cfg, chunk_key, basis_key, dev_bytes, n, first (packet_id, chunk_seq).

    One scan serves all configurations. ``by_source`` keeps the sources apart (private pools).
    """

    def run(batches):
        for batch in batches:
            names = np.array(batch.column(0).to_pylist(), object) if by_source else None
            packet = batch.column(1).fill_null(-1).to_numpy(zero_copy_only=False)
            data, first = [p or b"" for p in batch.column(2).to_pylist()], 0
            for part in _blocks(data, 1):
                for c, cfg in enumerate(configs):
                    chunks, owner, place, _ = cut(part, cfg.n_b)
                    if not len(chunks):
                        continue
                    origin = names[owner + first] if by_source else None
                    packets = packet[owner + first]
                    yield _counted(c, cfg, chunks, packets, place, origin)
                first += len(part)

    fields = "cfg int, source_id string, chunk_key binary, basis_key binary, dev_bytes long, n long, packet_id long, chunk_seq long"
    parts = payloads.select(F.col("source_id").cast("string"), F.col("packet_id").cast("long"), "payload").mapInArrow(run, fields)
    group = ["cfg", *(["source_id"] if by_source else []), "chunk_key"]
    return parts.groupBy(*group).agg(F.first("basis_key").alias("basis_key"), F.first("dev_bytes").alias("dev_bytes"), F.sum("n").alias("n"), F.min(F.struct("packet_id", "chunk_seq")).alias("first"))


def _counted(c, cfg, chunks, packets, place, origin):
    raw = np.ascontiguousarray(chunks).view({1: "u1", 2: "u2", 4: "u4", 8: "u8"}.get(cfg.n_b, f"V{cfg.n_b}")).ravel()
    order = np.lexsort((place, packets))
    if origin is None:
        _, at, back = np.unique(raw[order], return_index=True, return_inverse=True)
    else:
        source = np.unique(origin.astype(str), return_inverse=True)[1].astype(">u4")
        both = np.concatenate([source[:, None].view(np.uint8).reshape(len(source), 4), chunks], axis=1)
        _, at, back = np.unique(np.ascontiguousarray(both).view(f"V{cfg.n_b + 4}").ravel()[order], return_index=True, return_inverse=True)
    counts, rows = np.bincount(back), order[at]
    basis, _, lengths = split(chunks[rows], cfg, with_basis=False)
    sources = pa.array([None if origin is None else origin[i] for i in rows], pa.string())
    return pa.RecordBatch.from_arrays([pa.array(np.full(len(rows), c, np.int32)), sources, keys(chunks[rows]), keys(basis), pa.array(lengths), pa.array(counts.astype(np.int64)), pa.array(packets[rows]), pa.array(place[rows])], ["cfg", "source_id", "chunk_key", "basis_key", "dev_bytes", "n", "packet_id", "chunk_seq"])
