"""Lossless preparation of chunks of fixed-width unsigned big-endian samples.

``offset`` takes the smallest sample of a chunk off all of them and keeps it beside
the deviation. ``delta`` keeps the first sample and turns the others into differences
to the one before, either modulo the sample's range (same length) or one bit wider.
"""

from __future__ import annotations

import numpy as np


def samples(chunks: np.ndarray, width: int) -> np.ndarray:
    """Rows of integers."""
    parts = chunks.reshape(len(chunks), -1, width).astype(np.int64)
    out = np.zeros(parts.shape[:2], np.int64)
    for i in range(width):
        out = (out << 8) | parts[:, :, i]
    return out


def to_bytes(values: np.ndarray, width: int) -> np.ndarray:
    out = np.empty((*values.shape, width), np.uint8)
    for i in range(width):
        out[:, :, i] = (values >> (8 * (width - 1 - i))) & 0xFF
    return out.reshape(len(values), -1)


def _checked(width: int):
    if not 1 <= width <= 7:
        raise ValueError("samples of 1 to 7 bytes are supported")


def remove_offset(chunks: np.ndarray, width: int = 1):
    """(chunks, smallest samples)."""
    _checked(width)
    if width == 1:
        least = chunks.min(axis=1)
        return chunks - least[:, None], least.astype(np.int64)
    values = samples(chunks, width)
    least = values.min(axis=1)
    return to_bytes(values - least[:, None], width), least


def restore_offset(chunks: np.ndarray, least: np.ndarray, width: int = 1) -> np.ndarray:
    return to_bytes(samples(chunks, width) + least[:, None], width)


def delta_modular(chunks: np.ndarray, width: int = 1) -> np.ndarray:
    _checked(width)
    values = samples(chunks, width)
    values[:, 1:] = (values[:, 1:] - values[:, :-1]) % (1 << 8 * width)
    return to_bytes(values, width)


def restore_delta(chunks: np.ndarray, width: int = 1) -> np.ndarray:
    return to_bytes(np.cumsum(samples(chunks, width), axis=1) % (1 << 8 * width), width)


def wide_bits(count: int, width: int) -> int:
    """Bits of a chunk of ``count`` samples after ``delta_wide``: the first sample, then differences with a sign bit more."""
    return count and 8 * width + (count - 1) * (8 * width + 1)


def _bit_places(count: int, width: int):
    """For every bit of a widened chunk: the number it belongs to, and its place in it."""
    size = np.full(count, 8 * width + 1)
    size[0] = 8 * width
    owner = np.repeat(np.arange(count), size)
    return owner, np.concatenate([np.arange(n - 1, -1, -1) for n in size])


def delta_wide(chunks: np.ndarray, width: int = 1) -> np.ndarray:
    """First sample and signed differences, bit after bit, the rest of the last byte zero."""
    _checked(width)
    values = samples(chunks, width)
    values[:, 1:] -= values[:, :-1].copy()
    owner, place = _bit_places(values.shape[1], width)
    return np.packbits((values[:, owner] >> place & 1).astype(np.uint8), axis=1)


def restore_wide(body: np.ndarray, width: int = 1) -> np.ndarray:
    count = (8 * body.shape[1] - 8 * width) // (8 * width + 1) + 1
    owner, place = _bit_places(count, width)
    bits = np.unpackbits(body, axis=1)[:, : len(owner)].astype(np.int64) << place
    values = np.add.reduceat(bits, np.searchsorted(owner, np.arange(count)), axis=1)
    values[:, 1:] -= (values[:, 1:] >> 8 * width) << (8 * width + 1)  # sign
    return to_bytes(np.cumsum(values, axis=1), width)


def apply(chunks: np.ndarray, kind: str, width: int):
    """(chunks, side data as rows of bytes or None)."""
    if kind == "offset":
        out, least = remove_offset(chunks, width)
        return out, to_bytes(least[:, None], width)
    change = {"delta": delta_modular, "delta_wide": delta_wide}.get(kind)
    return (change(chunks, width) if change else chunks), None


def undo(chunks: np.ndarray, side: np.ndarray | None, kind: str, width: int) -> np.ndarray:
    if kind == "offset":
        return restore_offset(chunks, samples(side, width)[:, 0], width)
    change = {"delta": restore_delta, "delta_wide": restore_wide}.get(kind)
    return change(chunks, width) if change else chunks
