"""Shared configuration and code parameters.

Every node of a network uses one configuration, so none of it travels with messages.
"""

from __future__ import annotations

import hashlib
import math
from dataclasses import asdict, dataclass

from basisflow.functions.preprocess import wide_bits

#: Fingerprint presets: real-data study, synthetic study, worked cost example.
FP_STUDY, FP_SYNTH, FP_EXAMPLE = 6, 4, 20
SCHEMES = ("raw", "exact", "sim_plain", "sim_short", "sim_dual")
TRANSFORMS = ("identity", "hamming", "rs")
PREPROCESS = ("none", "offset", "delta", "delta_wide")
DIGEST_BYTES = {"sha1": 20, "sha256": 32, "md5": 16, "crc32": 4}


@dataclass(frozen=True)
class HammingParams:
    """A code of ``n`` = 2^m - 1 bits plus one spare bit, so chunks are whole bytes (from m = 3)."""

    m: int

    def __post_init__(self):
        if not 3 <= self.m <= 15:
            raise ValueError("m must be 3 to 15")

    @property
    def n(self) -> int:
        return (1 << self.m) - 1

    @property
    def k(self) -> int:
        return self.n - self.m

    @property
    def n_b(self) -> int:
        return (1 << self.m) // 8

    @property
    def k_b(self) -> int:
        return -(-self.k // 8)

    @property
    def deviation_bits(self) -> int:
        return self.m + 1

    @property
    def deviation_bytes(self) -> int:
        return -(-self.deviation_bits // 8)


def m_for_chunk(n_b: int) -> int:
    m = (8 * n_b).bit_length() - 1
    if n_b < 1 or 8 * n_b != 1 << m:
        raise ValueError("a Hamming chunk has a power of two of bytes")
    return m


@dataclass(frozen=True)
class RSParams:
    """A code over GF(256) of ``n_b`` symbols with ``k_b`` message symbols; short codes are allowed."""

    n_b: int
    k_b: int

    def __post_init__(self):
        if not 0 < self.k_b < self.n_b < 256:
            raise ValueError("0 < k_b < n_b < 256 must hold")

    @property
    def parity(self) -> int:
        return self.n_b - self.k_b

    @property
    def t(self) -> int:
        return self.parity // 2


def covering_radius(n_b: int, k_b: int) -> int:
    """Largest distance that our decoder leaves: the number of parity symbols."""
    return RSParams(n_b, k_b).parity


#: Radii as published. The last exceeds what a code of eight check symbols can have; it is kept for reference only.
PUBLISHED_RADIUS = {(16, 14): 2, (255, 253): 2, (255, 247): 8, (64, 56): 11}


def rs_deviation_bits(n_b: int, radius: int, q: int = 256) -> int:
    """Bound on a deviation: a place and a value for each of ``radius`` symbols."""
    return radius * math.ceil(math.log2(n_b)) + radius * math.ceil(math.log2(q))


def chunks_per_basis(m: int, count_spare: bool = False) -> int:
    return 1 << (m + 1 if count_spare else m)


def max_ratio(n_b: int, h: int) -> float:
    """No fingerprint of ``h`` bytes can compress chunks of ``n_b`` bytes further."""
    return n_b / h


def pool_capacity(megabytes: int, fp_bits: int, pointer_bytes: int = 8) -> int:
    """Records of a fingerprint and a pointer that fit into memory."""
    return megabytes * (1 << 20) // (fp_bits // 8 + pointer_bytes)


def expected_collisions(bases: float, bits: int) -> float:
    """Expected fingerprints lost to earlier equal ones, of random ``bits``-bit fingerprints."""
    space = 2.0**bits
    return bases - space * -math.expm1(bases * math.log1p(-1 / space))


@dataclass(frozen=True)
class DedupConfig:
    n_b: int
    transform: str = "hamming"
    k_b: int | None = None
    fp_algo: str = "md5"
    fp_bytes: int = FP_STUDY
    preprocess: str = "none"
    sample_width: int = 1
    rs_length: str = "actual"
    #: How nodes that deduplicate by similarity send: the plain scheme unless the network agrees on another.
    scheme: str = "sim_plain"

    def __post_init__(self):
        if self.scheme not in SCHEMES:
            raise ValueError("unknown scheme")
        if self.transform not in TRANSFORMS or self.preprocess not in PREPROCESS or self.fp_algo not in DIGEST_BYTES:
            raise ValueError("unknown transform, preprocessing or fingerprint")
        if not 0 < self.fp_bytes <= DIGEST_BYTES[self.fp_algo]:
            raise ValueError("the fingerprint is longer than its digest")
        if self.n_b < 1 or self.n_b % self.sample_width:
            raise ValueError("chunks must hold whole samples")
        if self.transform == "hamming":
            if self.preprocess == "delta_wide":
                raise ValueError("wide differences do not fill a power of two of bytes: use identity or rs")
            HammingParams(m_for_chunk(self.n_b))
        if self.transform == "rs":
            RSParams(self.body_bytes, self.basis_bytes)

    @property
    def body_bytes(self) -> int:
        """Bytes of a chunk after preprocessing."""
        if self.preprocess == "delta_wide":
            return -(-wide_bits(self.n_b // self.sample_width, self.sample_width) // 8)
        return self.n_b

    @property
    def basis_bytes(self) -> int:
        if self.transform == "identity":
            return self.body_bytes
        if self.transform == "hamming":
            return HammingParams(m_for_chunk(self.n_b)).k_b
        return self.body_bytes - 2 if self.k_b is None else self.k_b

    @property
    def side_bytes(self) -> int:
        """What preprocessing adds to a deviation."""
        return self.sample_width if self.preprocess == "offset" else 0

    @property
    def fixed_deviation(self) -> int | None:
        """Deviation bytes where they are the same for every chunk."""
        if self.transform == "identity":
            return self.side_bytes
        if self.transform == "hamming":
            return HammingParams(m_for_chunk(self.n_b)).deviation_bytes + self.side_bytes
        if self.rs_length == "max":
            return -(-rs_deviation_bits(self.body_bytes, covering_radius(self.body_bytes, self.basis_bytes)) // 8) + self.side_bytes
        return None

    def scheme_of(self, kind: str) -> str:
        """The scheme that a node of a class sends with."""
        return {"basic": "raw", "exact": "exact", "similar": self.scheme}[kind]

    def short_fp_bytes(self, deviation: int) -> int:
        """The shortened fingerprint fills what the deviation leaves of the full one."""
        if self.fp_bytes <= deviation:
            raise ValueError("the short scheme needs a fingerprint longer than the deviation")
        return self.fp_bytes - deviation

    def half_fp_bytes(self) -> int:
        if self.fp_bytes % 2:
            raise ValueError("the dual scheme halves the fingerprint: an even number of bytes is needed")
        return self.fp_bytes // 2

    def digest(self) -> str:
        """Stored with a pool; pools of different configurations never mix."""
        return hashlib.md5(repr(sorted(asdict(self).items())).encode()).hexdigest()
