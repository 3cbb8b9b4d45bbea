"""Hamming codes used backwards: decoding splits a chunk into basis and deviation.

A chunk is a big-endian number; its bit of significance p is at position p. Position 0
is the spare bit, positions that are powers of two are parity positions. The
syndrome is the XOR of the positions of all set bits, so it names the position to
flip; the basis is the bits at all other positions of the flipped word, high
positions first, padded with zero bits on the left.

Numpy kernels take any size of chunk; ``with_codeword`` builds plain columns,
in whole-stage codegen, for chunks of up to 64 bytes.
"""

from __future__ import annotations

import functools

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from basisflow.config import HammingParams, m_for_chunk


@functools.cache
def _byte_tables():
    values = np.arange(256, dtype=np.uint32)
    bits = (values[:, None] >> np.arange(8)) & 1
    return np.bitwise_xor.reduce(bits * np.arange(8, dtype=np.uint32), axis=1), (bits.sum(1) & 1).astype(np.uint32)


@functools.cache
def _data_positions(m: int) -> np.ndarray:
    p = np.arange((1 << m) - 1, 2, -1)
    return p[(p & (p - 1)) != 0]


def syndromes(chunks: np.ndarray) -> np.ndarray:
    """Of rows of bytes."""
    inner, odd = _byte_tables()
    n_b = chunks.shape[1]
    base = 8 * np.arange(n_b - 1, -1, -1, dtype=np.uint32)
    return np.bitwise_xor.reduce(inner[chunks] ^ (odd[chunks] * base), axis=1).astype(np.int64) if len(chunks) else np.zeros(0, np.int64)


def flip(chunks: np.ndarray, positions: np.ndarray) -> np.ndarray:
    """Flips one bit of every row."""
    out = chunks.copy()
    rows = np.arange(len(out))
    out[rows, out.shape[1] - 1 - positions // 8] ^= (1 << (positions % 8)).astype(np.uint8)
    return out


def codewords(chunks: np.ndarray):
    """(error-free words with a cleared spare bit, syndromes, spare bits)."""
    found = syndromes(chunks)
    words = flip(chunks, found)
    spare = chunks[:, -1] & 1
    words[:, -1] &= 0xFE  # a syndrome of 0 has flipped the spare bit, which is dropped anyway
    return words, found, spare.astype(np.int64)


def pack_basis(words: np.ndarray) -> np.ndarray:
    m = m_for_chunk(words.shape[1])
    bits = np.unpackbits(words, axis=1)[:, (1 << m) - 1 - _data_positions(m)]
    params = HammingParams(m)
    pad = 8 * params.k_b - params.k
    return np.packbits(np.concatenate([np.zeros((len(bits), pad), np.uint8), bits], axis=1), axis=1)


def split(chunks: np.ndarray):
    """(bases, syndromes, spare bits)."""
    words, found, spare = codewords(chunks)
    return pack_basis(words), found, spare


def join(bases: np.ndarray, syndrome: np.ndarray, spare: np.ndarray, m: int) -> np.ndarray:
    """The inverse: encodes bases, flips the named bits, appends spare bits."""
    params = HammingParams(m)
    bits = np.unpackbits(bases, axis=1)[:, 8 * params.k_b - params.k :]
    word = np.zeros((len(bases), 1 << m), np.uint8)
    word[:, (1 << m) - 1 - _data_positions(m)] = bits
    packed = np.packbits(word, axis=1)
    parity = syndromes(packed)
    for t in range(m):
        word[:, (1 << m) - 1 - (1 << t)] = (parity >> t) & 1
    packed = flip(np.packbits(word, axis=1), syndrome)
    packed[:, -1] = (packed[:, -1] & 0xFE) | spare.astype(np.uint8)
    return packed


# --- plain columns ----------------------------------------------------------


def _signed(value: int) -> Column:
    return F.lit(value - (1 << 64) if value >= 1 << 63 else value).cast("long")


def words_of(chunk: Column, n_b: int) -> list[Column]:
    """The chunk as 64-bit words, the last bytes first."""
    half = lambda at, n: F.conv(F.hex(F.substring(chunk, at, n)), 16, 10).cast("long")
    if n_b < 8:
        return [half(1, n_b)]
    # two halves: a cast of an unsigned 64-bit number fails in ANSI mode
    return [F.shiftleft(half(n_b - 8 * i - 7, 4), 32).bitwiseOR(half(n_b - 8 * i - 3, 4)) for i in range(n_b // 8)]


def word_syndrome(words: list[Column]) -> Column:
    mixed = words[0]
    for w in words[1:]:
        mixed = mixed.bitwiseXOR(w)
    out = F.lit(0)
    for t in range(6):
        mask = sum(1 << p for p in range(64) if p >> t & 1)
        out = out.bitwiseOR(F.shiftleft(F.bit_count(mixed.bitwiseAND(_signed(mask))).bitwiseAND(F.lit(1)), t))
    for i, w in enumerate(words[1:], 1):
        out = out.bitwiseXOR(F.bit_count(w).bitwiseAND(F.lit(1)) * (64 * i))
    return out


def corrected_words(words: list[Column], found: Column) -> list[Column]:
    one = F.lit(1).cast("long")
    place = found.bitwiseAND(F.lit(63))
    out = [w.bitwiseXOR(F.when(F.shiftright(found, 6) == i, F.call_function("shiftleft", one, place)).otherwise(F.lit(0).cast("long"))) for i, w in enumerate(words)]
    return [out[0].bitwiseAND(F.lit(-2).cast("long")), *out[1:]]


def with_codeword(df: DataFrame, n_b: int, chunk: str = "chunk") -> DataFrame:
    """Adds syndrome, spare and codeword (error-free, spare bit cleared: one for each basis).

    Words and syndrome are columns of their own, so that none is worked out twice.
    """
    m_for_chunk(n_b)
    if n_b > 64:
        raise ValueError("columns are built for chunks of up to 64 bytes")
    names = [f"__w{i}" for i in range(max(1, n_b // 8))]
    out = df.withColumns(dict(zip(names, words_of(F.col(chunk), n_b), strict=True)))
    words = [F.col(name) for name in names]
    out = out.withColumn("syndrome", word_syndrome(words)).withColumn("spare", words[0].bitwiseAND(F.lit(1)))
    fixed = corrected_words(words, F.col("syndrome"))
    body = F.unhex(F.concat(*(F.lpad(F.hex(w), 2 * min(n_b, 8), "0") for w in reversed(fixed))))
    return out.withColumn("codeword", body).drop(*names)


def basis8(word: Column) -> Column:
    """The 57-bit basis of an 8-byte error-free word: its stretches between parity positions, closed up."""
    stretch = lambda low, high, shift: F.shiftright(word.bitwiseAND(_signed(sum(1 << p for p in range(low, high + 1)))), shift)
    top = F.shiftrightunsigned(word, 7).bitwiseAND(_signed(((1 << 31) - 1) << 26))
    parts = [stretch(3, 3, 3), stretch(5, 7, 4), stretch(9, 15, 5), stretch(17, 31, 6), top]
    out = parts[0]
    for part in parts[1:]:
        out = out.bitwiseOR(part)
    return out
