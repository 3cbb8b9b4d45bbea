"""SQL functions: gd_syndrome, gd_basis, gd_deviation, gd_restore, gd_rs_basis, gd_fingerprint, gd_deflate_size, gd_lzw_size, and the table function gd_chunks."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from basisflow.config import HammingParams
from basisflow.functions import codecs, hamming, reed_solomon


def _by_length(values: pd.Series, run) -> pd.Series:
    """Applies a kernel to chunks of equal length together; nulls stay."""
    out = pd.Series([None] * len(values), index=values.index, dtype=object)
    lengths = values.dropna().map(len)
    for n in lengths.unique():
        where = lengths.index[lengths == n]
        chunks = np.frombuffer(b"".join(map(bytes, values[where])), np.uint8).reshape(-1, n)
        out[where] = run(chunks)
    return out


@F.pandas_udf(T.LongType())
def gd_syndrome(chunk: pd.Series) -> pd.Series:
    return _by_length(chunk, lambda c: list(map(int, hamming.syndromes(c)))).astype("Int64")


@F.pandas_udf(T.BinaryType())
def gd_basis(chunk: pd.Series) -> pd.Series:
    return _by_length(chunk, lambda c: [b.tobytes() for b in hamming.split(c)[0]])


def _deviations(chunks: np.ndarray) -> list[bytes]:
    width = HammingParams(hamming.m_for_chunk(chunks.shape[1])).deviation_bytes
    _, syndrome, spare = hamming.split(chunks)
    return [int(s << 1 | p).to_bytes(width, "big") for s, p in zip(syndrome, spare, strict=True)]


@F.pandas_udf(T.BinaryType())
def gd_deviation(chunk: pd.Series) -> pd.Series:
    return _by_length(chunk, _deviations)


@F.pandas_udf(T.BinaryType())
def gd_restore(basis: pd.Series, deviation: pd.Series, n_b: pd.Series) -> pd.Series:
    out = pd.Series([None] * len(basis), index=basis.index, dtype=object)
    whole = ~(basis.isna() | deviation.isna() | n_b.isna())
    for n in n_b[whole].unique():
        where = basis.index[whole & (n_b == n)]
        bases = np.frombuffer(b"".join(map(bytes, basis[where])), np.uint8).reshape(len(where), -1)
        value = np.zeros(len(where), np.int64)
        for part in np.frombuffer(b"".join(map(bytes, deviation[where])), np.uint8).reshape(len(where), -1).T:
            value = value << 8 | part
        out[where] = [c.tobytes() for c in hamming.join(bases, value >> 1, value & 1, hamming.m_for_chunk(int(n)))]
    return out


@F.pandas_udf(T.BinaryType())
def gd_rs_basis(chunk: pd.Series) -> pd.Series:
    """The basis under the Reed-Solomon code with two check symbols."""
    return _by_length(chunk, lambda c: [b.tobytes() for b in reed_solomon.split(c, c.shape[1] - 2)[0]])


def _sizes(codec: str):
    @F.pandas_udf(T.LongType())
    def size(body: pd.Series) -> pd.Series:
        return body.map(lambda b: None if b is None else codecs.CODECS[codec](bytes(b))).astype("Int64")

    return size


@F.udtf(returnType=T.StructType([T.StructField("chunk_seq", T.IntegerType()), T.StructField("chunk", T.BinaryType()), T.StructField("valid_len", T.IntegerType())]))
class gd_chunks:  # noqa: N801
    def eval(self, payload: bytes, n_b: int):
        for i in range(0, len(payload or b""), n_b):
            part = bytes(payload[i : i + n_b])
            yield i // n_b, part.ljust(n_b, b"\0"), len(part)


def register(spark: SparkSession) -> None:
    for name, function in (("gd_syndrome", gd_syndrome), ("gd_basis", gd_basis), ("gd_deviation", gd_deviation), ("gd_restore", gd_restore), ("gd_rs_basis", gd_rs_basis), ("gd_deflate_size", _sizes("deflate")), ("gd_lzw_size", _sizes("lzw"))):
        spark.udf.register(name, function)
    spark.udtf.register("gd_chunks", gd_chunks)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION gd_fingerprint(body BINARY, n INT) RETURNS BINARY RETURN substring(unhex(md5(body)), 1, n)")
