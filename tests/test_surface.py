"""Stored pools, file sources, the SQL functions and packets of several chunks."""

import pytest
from pyspark.sql import functions as F

from basisflow import sqlapi
from basisflow.config import DedupConfig
from basisflow.operators import encode, packets, schemes
from basisflow.operators.pool_store import PoolStore
from basisflow.sources import files
from basisflow.sources import payloads as source


def test_pool_store(spark, small, tmp_path):
    cfg = DedupConfig(8)
    encoded = encode.encode_payloads(source.conversations(spark, small), cfg)
    store = PoolStore(spark, str(tmp_path / "pool"), cfg)
    assert store.load() is None
    total = encoded.select("basis_key").distinct().count()
    assert store.append(encoded) == total and store.append(encoded) == 0
    assert store.compact(str(tmp_path / "compact")).load().count() == total
    with pytest.raises(ValueError):
        PoolStore(spark, str(tmp_path / "pool"), DedupConfig(16)).load()


def test_file_sources(spark, tmp_path):
    (tmp_path / "a.bin").write_bytes(b"\x00\x01\x02")
    (tmp_path / "t.txt").write_text("one\ntwo\n")
    (tmp_path / "c.csv").write_text("id,source,body\n1,s,hello\n")
    assert bytes(files.binary_files(spark, str(tmp_path), "*.bin").first().payload) == b"\x00\x01\x02"
    assert sorted(bytes(r.payload) for r in files.text_lines(spark, str(tmp_path / "t.txt")).collect()) == [b"one", b"two"]
    row = files.csv_records(spark, str(tmp_path / "c.csv"), "id long, source string, body string", "source", "id", "body").first()
    assert (row.source_id, row.packet_id, bytes(row.payload)) == ("s", 1, b"hello")
    assert files.rate_stream(spark).columns == ["source_id", "packet_id", "ts", "payload"]


def test_sql_functions_keep_nulls(spark):
    sqlapi.register(spark)
    row = spark.sql("SELECT gd_basis(CAST(NULL AS BINARY)) AS b, gd_syndrome(X'0000000000000001') AS s, length(gd_fingerprint(X'00', 6)) AS n").first()
    assert (row.b, row.s, row.n) == (None, 0, 6)


def test_vectors_send_the_same_bytes(spark, small):
    cfg = DedupConfig(8)
    found = schemes.outcomes(encode.encode_payloads(source.conversations(spark, small), cfg))
    for scheme in ("exact", "sim_plain", "sim_dual"):
        one = schemes.traffic(found, cfg, (scheme,)).agg(F.sum("up_bytes"), F.sum("messages")).first()
        many = packets.packed_traffic(found, cfg, scheme, 16).agg(F.sum("up_bytes"), F.sum("messages")).first()
        assert many[0] == one[0] and many[1] < one[1]
    with pytest.raises(ValueError):
        packets.uplink_variant(found, cfg, "nothing")


def test_rate_source_runs(spark, tmp_path):
    query = files.rate_stream(spark).writeStream.format("memory").queryName("rates").option("checkpointLocation", str(tmp_path / "c")).start()
    try:
        for _ in range(60):
            if spark.table("rates").limit(1).count():
                break
            query.awaitTermination(1)
        row = spark.table("rates").first()
        assert row is not None and len(row.payload) > 0
    finally:
        query.stop()


def test_doubles_and_integers_keep_their_bits(spark):
    import struct

    rows = [(-1, 1.5), (1 << 40, -0.0), (0, None)]
    out = spark.createDataFrame(rows, "i long, d double").select(source.pack_i64(F.col("i")).alias("i"), source.pack_f64(F.col("d")).alias("d")).collect()
    assert [bytes(r.i) for r in out] == [struct.pack(">q", i) for i, _ in rows]
    assert [r.d and bytes(r.d) for r in out] == [struct.pack(">d", 1.5), struct.pack(">d", -0.0), None]


def test_codec_functions(spark):
    sqlapi.register(spark)
    row = spark.sql("SELECT gd_deflate_size(X'6162616261626162') AS a, gd_lzw_size(X'616261626162') AS b, gd_lzw_size(CAST(NULL AS BINARY)) AS c").first()
    assert row.b == 5 and row.a > 0 and row.c is None
