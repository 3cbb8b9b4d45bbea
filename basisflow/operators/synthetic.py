"""Best-case workloads: chunks within one bit of few random bases.

Bits come from digests of counters, so that any engine can make the same rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from basisflow.config import HammingParams
from basisflow.functions import hamming


def _random_bytes(name: str, count: int) -> np.ndarray:
    import hashlib

    raw = b"".join(hashlib.sha256(f"{name}:{i}".encode()).digest() for i in range(-(-count // 32)))
    return np.frombuffer(raw[:count], np.uint8)


def ball_chunks(names: list[str], flips: list[np.ndarray], m: int):
    """Rows of chunks: for each name an error-free word with spare bit 0, with one bit flipped for each given position."""
    params = HammingParams(m)
    bases = np.stack([_random_bytes(n, params.k_b) for n in names]).copy()
    pad = 8 * params.k_b - params.k
    bases[:, 0] &= 0xFF >> pad
    zero = np.zeros(len(names), np.int64)
    words = hamming.join(bases, zero, zero, m)
    words[:, -1] &= 0xFE
    rows = np.repeat(np.arange(len(names)), [len(f) for f in flips])
    return hamming.flip(words[rows], np.concatenate(flips)), rows


def ball(spark: SparkSession, m: int, n_bases: int, per_basis: int, mode: str = "random", seed: int = 1) -> DataFrame:
    """Payload rows (source_id, packet_id, payload), one chunk each.

    ``random`` draws ``per_basis`` positions with replacement, ``all`` takes each of the 2^m positions once.
    """
    count = 1 << m if mode == "all" else per_basis
    step = max(1, (1 << 22) // (HammingParams(m).n_b * count))

    def run(batches):
        for batch in batches:
            ids = batch.column(0).to_numpy()
            for at in range(0, len(ids), step):
                some = ids[at : at + step]
                names = [f"{seed}:{i}" for i in some]
                flips = []
                for name in names:
                    if mode == "all":
                        flips.append(np.arange(1 << m))
                    else:
                        drawn = _random_bytes(f"{name}:flips", 2 * count).view("<u2").astype(np.int64)
                        flips.append(drawn % (1 << m))
                chunks, rows = ball_chunks(names, flips, m)
                place = np.concatenate([np.arange(len(f)) for f in flips])
                packet = some[rows] * (1 << 20) + place
                yield pa.RecordBatch.from_arrays([pa.array([str(i % 16) for i in some[rows]]), pa.array(packet), pa.array([c.tobytes() for c in chunks], pa.binary())], ["source_id", "packet_id", "payload"])

    return spark.range(n_bases).mapInArrow(run, "source_id string, packet_id long, payload binary")


def ball_from_tables(parts: DataFrame, lines: DataFrame, m: int) -> DataFrame:
    """A ball around each part, a chunk for each of its line items (m up to 6), in plain columns.

    The error-free word has the leading bits of the part's md5 as its basis; the flipped
    position comes from a digest of the line.
    """
    if not 3 <= m <= 6:
        raise ValueError("plain columns hold words of up to 64 bits")
    params = HammingParams(m)
    top = F.conv(F.substring(F.md5(F.col("l_partkey").cast("string")), 1, 15), 16, 10).cast("long")
    basis = F.shiftright(top, 60 - params.k)
    positions = sorted((p for p in range(3, 1 << m) if p & (p - 1)), reverse=True)
    word = F.lit(0).cast("long")
    for i, p in enumerate(positions):
        word = word.bitwiseOR(F.shiftleft(F.shiftright(basis, params.k - 1 - i).bitwiseAND(F.lit(1)), p))
    used = lines.join(parts.select(F.col("p_partkey").alias("l_partkey")), "l_partkey")
    digest = F.sha2(F.concat_ws("|", F.col("l_orderkey"), F.col("l_linenumber"), F.col("l_partkey")), 256)
    out = used.select("l_partkey", word.alias("word"), (F.conv(F.substring(digest, 1, 8), 16, 10).cast("long") % (1 << m)).cast("int").alias("flip"))
    syndrome = hamming.word_syndrome([F.col("word")])
    out = out.withColumn("syndrome", syndrome)
    for t in range(m):
        bit = F.shiftright(F.col("syndrome"), t).bitwiseAND(F.lit(1)).cast("long")
        out = out.withColumn("word", F.col("word").bitwiseOR(F.shiftleft(bit, 1 << t)))
    flipped = F.col("word").bitwiseXOR(F.call_function("shiftleft", F.lit(1).cast("long"), F.col("flip")))
    return out.select("l_partkey", "flip", flipped.alias("chunk_word"))


def expected_unique(draws: int, positions: int) -> float:
    """Distinct positions among so many draws with replacement."""
    return positions * (1 - (1 - 1 / positions) ** draws)


def expected_ratio(m: int, h: int) -> dict[str, float]:
    """Ratios of plain and exact on balls of 2^m random flips, without sampling."""
    p = HammingParams(m)
    chunks = 1 << m
    unique = expected_unique(chunks, chunks)
    plain = p.k_b + chunks * (h + p.deviation_bytes)
    return {"sim_plain": chunks * p.n_b / plain, "exact": chunks * p.n_b / (unique * p.n_b + chunks * h)}


def repeats(spark: SparkSession, n_b: int, times: int) -> DataFrame:
    """Every chunk of ``n_b`` bytes (1 or 2), ``times`` times."""
    if n_b not in (1, 2):
        raise ValueError("1 or 2 bytes")
    chunk = F.unhex(F.lpad(F.hex("id"), 2 * n_b, "0"))
    return spark.range(1 << 8 * n_b).crossJoin(F.broadcast(spark.range(times).withColumnRenamed("id", "copy"))).select(F.lit("0").alias("source_id"), (F.col("copy") * (1 << 8 * n_b) + F.col("id")).alias("packet_id"), chunk.alias("payload"))


def drawn(ids: DataFrame, m: int, per_basis: int | None = None, seed: int = 1) -> DataFrame:
    """A chunk for each row's id (one long column): ids that share a multiple of ``per_basis`` (2^m where none is given) lie around one random basis.

    Without ``per_basis`` a digest of the id draws the flipped position, else it is the id's place: so many different chunks on each basis.
    Ids are dealt and sorted by basis and position, so that equal chunks follow each other in one task.
    """
    from basisflow.sources.payloads import dealt

    share = per_basis or 1 << m
    if share > 1 << m:
        raise ValueError("a basis has 2^m chunks")
    step = max(1, (1 << 22) // HammingParams(m).n_b)

    def run(batches):
        for batch in batches:
            every, places = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            for at in range(0, len(every), step):
                order = np.lexsort((places[at : at + step], every[at : at + step] // share))
                some, flips = every[at : at + step][order], places[at : at + step][order]
                balls, firsts = np.unique(some // share, return_index=True)
                chunks, _ = ball_chunks([f"{seed}:{b}" for b in balls.tolist()], np.split(flips, firsts[1:]), m)
                yield pa.RecordBatch.from_arrays([pa.array((some % 16).astype(str)), pa.array(some), pa.array([c.tobytes() for c in chunks], pa.binary())], ["source_id", "packet_id", "payload"])

    known = ids.select(F.col(ids.columns[0]).cast("long").alias("id")).dropna()
    place = F.pmod("id", F.lit(share))
    flip = place if per_basis else F.conv(F.substring(F.sha2(F.concat(F.lit(f"{seed}:flip:"), F.col("id").cast("string")), 256), 1, 8), 16, 10).cast("long") % share
    placed = known.select("id", flip.cast("long").alias("flip"), (F.col("id") - place).alias("base"))
    return dealt(placed, "base", "flip").sortWithinPartitions("base", "flip").select("id", "flip").mapInArrow(run, "source_id string, packet_id long, payload binary")
