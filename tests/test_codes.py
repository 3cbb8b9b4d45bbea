"""Codes, preprocessing, codecs and configuration."""

import itertools
import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from basisflow.config import PUBLISHED_RADIUS, DedupConfig, HammingParams, RSParams, chunks_per_basis, covering_radius, expected_collisions, m_for_chunk, max_ratio, pool_capacity, rs_deviation_bits
from basisflow.functions import codecs, hamming, preprocess, reed_solomon
from basisflow.operators import encode


def rows(n, width, seed=0):
    return np.random.default_rng(seed).integers(0, 256, (n, width), dtype=np.uint8)


def test_parameters():
    p = HammingParams(8)
    assert (p.n, p.k, p.n_b, p.k_b, p.deviation_bits, p.deviation_bytes) == (255, 247, 32, 31, 9, 2)
    assert m_for_chunk(4096) == 15 and chunks_per_basis(4) == 16 and chunks_per_basis(4, True) == 32
    assert max_ratio(40, 20) == 2 and pool_capacity(256, 32) == 22_369_621
    assert covering_radius(255, 247) == 8 and PUBLISHED_RADIUS[64, 56] == 11 and RSParams(255, 247).t == 4
    assert rs_deviation_bits(16, 2) == 24
    assert abs(expected_collisions(1000, 8) - (1000 - 256 * (1 - (255 / 256) ** 1000))) < 1e-6


@pytest.mark.parametrize("bad", [dict(n_b=12), dict(n_b=300, transform="rs"), dict(n_b=8, fp_bytes=17), dict(n_b=8, transform="x"), dict(n_b=9, transform="identity", sample_width=2)])
def test_bad_configurations(bad):
    with pytest.raises(ValueError):
        DedupConfig(**bad)


def test_fingerprint_lengths():
    cfg = DedupConfig(128)
    assert cfg.short_fp_bytes(2) + 2 == cfg.fp_bytes == 2 * cfg.half_fp_bytes()
    with pytest.raises(ValueError):
        cfg.short_fp_bytes(6)
    with pytest.raises(ValueError):
        DedupConfig(8, fp_bytes=5).half_fp_bytes()


@pytest.mark.parametrize("m, count", [(3, 256), (4, 65536)])
def test_all_chunks_of_small_codes(m, count):
    n_b = HammingParams(m).n_b
    chunks = np.arange(count, dtype=">u2").view(np.uint8).reshape(-1, 2)[:, 2 - n_b :].copy()
    basis, syndrome, spare = hamming.split(chunks)
    assert (hamming.join(basis, syndrome, spare, m) == chunks).all()
    _, counts = np.unique(basis, axis=0, return_counts=True)
    assert len(counts) == 1 << HammingParams(m).k and (counts == chunks_per_basis(m, True)).all()
    words, _, _ = hamming.codewords(chunks)
    assert np.bitwise_count((chunks ^ words) & np.array([255] * (n_b - 1) + [254], np.uint8)).sum(1).max() <= 1


@pytest.mark.parametrize("m", range(5, 16))
def test_hamming_round_trip(m):
    chunks = np.concatenate([rows(20, HammingParams(m).n_b, m), np.zeros((1, HammingParams(m).n_b), np.uint8), np.full((1, HammingParams(m).n_b), 255, np.uint8)])
    basis, syndrome, spare = hamming.split(chunks)
    assert basis.shape[1] == HammingParams(m).k_b
    assert (hamming.join(basis, syndrome, spare, m) == chunks).all()
    words, _, _ = hamming.codewords(chunks)
    assert (hamming.syndromes(words) == 0).all()
    again, zero, _ = hamming.split(words)
    assert (again == basis).all() and (zero == 0).all()


def test_one_flip_keeps_the_basis():
    words, _, _ = hamming.codewords(rows(1, 8))
    flipped = hamming.flip(np.repeat(words, 64, axis=0), np.arange(64))
    assert len(np.unique(hamming.split(flipped)[0], axis=0)) == 1


@pytest.mark.parametrize("n_b, k_b", [(16, 14), (255, 253), (20, 12), (64, 56), (255, 247)])
def test_rs_round_trip_and_planted_errors(n_b, k_b):
    r = n_b - k_b
    words = reed_solomon.encode(rows(12, k_b, n_b), n_b)
    assert (reed_solomon.rs_syndromes(words, r) == 0).all()
    rnd = random.Random(n_b)
    for wrong in range(r // 2 + 1):
        broken = words.copy()
        for row in broken:
            for at in rnd.sample(range(n_b), wrong):
                row[at] ^= rnd.randint(1, 255)
        basis, errors = reed_solomon.split(broken, k_b)
        assert (basis == words[:, :k_b]).all() and ((errors != 0).sum(1) <= wrong).all()
        assert (reed_solomon.join(basis, reed_solomon.pairs(errors), n_b) == broken).all()
    anything = rows(12, n_b, 7)
    basis, errors = reed_solomon.split(anything, k_b)
    assert ((errors != 0).sum(1) <= r).all()
    assert (reed_solomon.join(basis, reed_solomon.pairs(errors), n_b) == anything).all()
    assert (reed_solomon.rs_syndromes(anything ^ errors, r) == 0).all()


def test_worked_samples():
    chunk = np.array([[0, 0, 128, 0, 0, 127, 0, 0, 128]], np.uint8)
    # 128 in 24 bits, then -1 and 1 in 25 bits each
    wide = int.from_bytes(preprocess.delta_wide(chunk, 3)[0].tobytes(), "big") >> 6
    assert preprocess.wide_bits(3, 3) == 74 and wide == (128 << 50) | (((1 << 25) - 1) << 25) | 1
    out, least = preprocess.remove_offset(chunk, 3)
    assert preprocess.samples(out, 3).tolist() == [[1, 0, 1]] and least.tolist() == [127]
    assert preprocess.samples(preprocess.delta_modular(chunk, 3), 3).tolist() == [[128, (1 << 24) - 1, 1]]


@pytest.mark.parametrize("kind, width", list(itertools.product(["none", "offset", "delta", "delta_wide"], [1, 2, 3, 4])))
def test_preprocessing_is_lossless(kind, width):
    chunks = rows(50, 24)
    out, side = preprocess.apply(chunks, kind, width)
    assert (preprocess.undo(out, side, kind, width) == chunks).all()


@pytest.mark.parametrize("cfg", [DedupConfig(8), DedupConfig(32, preprocess="offset", sample_width=2), DedupConfig(16, "rs", preprocess="delta"), DedupConfig(16, "rs", preprocess="offset"), DedupConfig(9, "identity", preprocess="offset", sample_width=3), DedupConfig(16, "identity", preprocess="delta_wide", sample_width=4), DedupConfig(12, "rs", preprocess="delta_wide", sample_width=2)])
def test_split_and_restore(cfg):
    chunks = rows(40, cfg.n_b)
    basis, deviation, lengths = encode.split(chunks, cfg)
    deviation = [bytes(d) for d in deviation]
    assert basis.shape[1] == cfg.basis_bytes and [len(d) for d in deviation] == lengths.tolist()
    assert (encode.restore(basis, deviation, cfg) == chunks).all()


def test_wide_differences_need_a_code_of_their_length():
    with pytest.raises(ValueError):
        DedupConfig(16, preprocess="delta_wide")
    assert DedupConfig(16, "identity", preprocess="delta_wide", sample_width=2).basis_bytes == 17


def test_lzw_example():
    codes, bits = codecs.lzw_encode(b"ababab")
    assert codes == [97, 98, 256, 256] and bits == 36
    assert codecs.lzw_size(b"") == 0


@settings(max_examples=100, deadline=None)
@given(st.binary(max_size=600), st.sampled_from([9, 10, 16]))
def test_lzw_round_trip(data, bits):
    assert codecs.lzw_decode(codecs.lzw_encode(data, bits)[0], bits) == data


def test_small_chunks_do_not_compress():
    data = rows(1, 64)[0].tobytes()
    assert all(codecs.CODECS[c](data) >= 64 for c in ("deflate", "lzw"))


@settings(max_examples=200, deadline=None)
@given(st.integers(0, 300), st.sampled_from([2, 4, 16, 256]), st.integers(0, 1 << 32))
def test_lzw_sizes_of_many_chunks(length, symbols, seed):
    data = np.random.default_rng(seed).integers(0, symbols, (7, length), dtype=np.uint8)
    chunks = [c.tobytes() for c in data]
    assert codecs.lzw_sizes(chunks) == [codecs.lzw_size(c) for c in chunks]


def test_lzw_sizes_of_long_chunks():
    data = rows(20, 4096)
    data[:, 3000:3400] = data[:, 100:500]  # codes of many bytes beside those of one
    data[5:9] %= 8
    chunks = [c.tobytes() for c in data]
    assert codecs.lzw_sizes(chunks) == [-(-codecs.lzw_encode(c)[1] // 8) for c in chunks]
    long = [rows(1, codecs.LZW_LONGEST + n, n)[0].tobytes() for n in (0, 1, 4000)]
    assert all(codecs.lzw_sizes([c]) == [codecs.lzw_size(c)] for c in long)
    assert codecs.lzw_sizes([]) == []
