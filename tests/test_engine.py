"""Schemes, pools and protocol against a simulator that keeps its pools in dictionaries."""

import bz2
import glob
import hashlib
import itertools
import lzma
import os
import random
import zlib

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from basisflow.config import DedupConfig, HammingParams
from basisflow.functions import codecs
from basisflow.functions.hamming import basis8, with_codeword
from basisflow.operators import chunking, costs, encode, pool, protocol, schemes, synthetic
from basisflow.plans import registry
from basisflow.sources import payloads as source
from basisflow.streaming import pool as live


def simulate(chunks, cfg):
    """Bytes that a source sends for chunks in order, one sink."""
    out = dict.fromkeys(("raw", "exact", "sim_plain", "sim_short", "sim_dual"), 0)
    known, bases = set(), set()
    h = cfg.fp_bytes
    for chunk in chunks:
        basis, deviation, _ = encode.split(np.frombuffer(chunk, np.uint8)[None], cfg)
        basis, d = basis.tobytes(), len(deviation[0])
        out["raw"] += cfg.n_b
        out["exact"] += h + (0 if chunk in known else cfg.n_b)
        out["sim_plain"] += h + d + (0 if basis in bases else cfg.basis_bytes)
        out["sim_short"] += h + (0 if basis in bases else cfg.basis_bytes)
        out["sim_dual"] += h + (0 if chunk in known else d if basis in bases else cfg.n_b)
        known.add(chunk)
        bases.add(basis)
    return out


@pytest.mark.parametrize("cfg", [DedupConfig(4), DedupConfig(8), DedupConfig(16, "rs"), DedupConfig(32, preprocess="offset", sample_width=2)])
def test_totals_equal_a_simulation(spark, small, cfg):
    data = source.conversations(spark, small)
    rows = sorted(data.collect(), key=lambda r: r.packet_id)
    chunks = [p[i : i + cfg.n_b].ljust(cfg.n_b, b"\0") for r in rows for p in [bytes(r.payload)] for i in range(0, len(p), cfg.n_b)]
    want = simulate(chunks, cfg)
    unique = encode.unique_chunks(data, [cfg])
    got = {r.scheme: r.total_bytes for r in costs.scheme_table(costs.counts(unique), cfg).collect()}
    assert got == want
    found = schemes.outcomes(encode.encode_payloads(data, cfg))
    by_traffic = {r.scheme: r.b for r in schemes.traffic(found, cfg).groupBy("scheme").agg(F.sum("up_bytes").alias("b")).collect()}
    assert by_traffic == want
    # order changes who pays, not the sum
    turned = schemes.outcomes(encode.encode_payloads(data.withColumn("packet_id", -F.col("packet_id")), cfg))
    assert {r.outcome: r["count"] for r in turned.groupBy("outcome").count().collect()} == {r.outcome: r["count"] for r in found.groupBy("outcome").count().collect()}


def test_published_counts_give_the_published_gains():
    """Counts of the water data at 256 and 128 bytes."""
    water = {256: (1_007_815, 260_276, 259_720, 168_140), 128: (2_015_630, 335_678, 334_244, 269_619)}

    def ratio(n_b, scheme, bases, extra):
        n, exact, _, _ = water[n_b]
        k_b, d, h = HammingParams((8 * n_b).bit_length() - 1).k_b, 2 + extra, 6
        total = {"exact": exact * n_b + n * h, "sim_plain": bases * k_b + n * (h + d), "sim_short": bases * k_b + n * h}[scheme]
        return n * n_b / total

    n, exact, plain, offset = water[256]
    base = ratio(256, "exact", exact, 0)
    assert round(base, 3) == 3.550
    assert round(ratio(256, "sim_plain", offset, 1) / base, 2) == 1.40
    assert round(ratio(256, "sim_short", offset, 1) / base, 2) == 1.49 or round(ratio(256, "sim_short", offset, 1) / base, 3) == 1.486
    n, exact, plain, offset = water[128]
    assert round(ratio(128, "sim_plain", offset, 1) / ratio(128, "exact", exact, 0), 2) == 1.05


def test_worked_cost_example():
    assert costs.exact_pays_from(10**6, 128, 20) == 156_250
    assert costs.exact_pays(800_000, 10**6, 128, 20) and not costs.exact_pays(850_000, 10**6, 128, 20)


@pytest.mark.parametrize("m, plain", [(14, 334.4), (15, 668.7)])
def test_synthetic_ratios(m, plain):
    got = synthetic.expected_ratio(m, 4)
    assert round(got["sim_plain"], 1) == plain and round(got["exact"], 2) == 1.58


def test_random_balls_reach_the_expected_ratio(spark):
    cfg = DedupConfig(128, fp_algo="crc32", fp_bytes=4)
    got = {r.scheme: r.ratio for r in costs.scheme_table(costs.counts(encode.unique_chunks(synthetic.ball(spark, 10, 20, 1024), [cfg])), cfg).collect()}
    want = synthetic.expected_ratio(10, 4)
    assert abs(got["sim_plain"] / want["sim_plain"] - 1) < 0.01 and abs(got["exact"] / want["exact"] - 1) < 0.02
    counted = costs.counts(encode.unique_chunks(synthetic.ball(spark, 6, 10, 0, "all"), [DedupConfig(8)])).first()
    assert (counted.chunks, counted.exact_bases, counted.bases) == (640, 640, 10)


def test_kernels_agree(spark, small):
    rows = with_codeword(encode.chunk_payloads(source.documents(spark, small), 8), 8)
    native = {(r.packet_id, r.chunk_seq): (r.syndrome << 1) | r.spare for r in rows.select("packet_id", "chunk_seq", "syndrome", "spare").collect()}
    kernel = {(r.packet_id, r.chunk_seq): r.deviation[0] for r in encode.encode_payloads(source.documents(spark, small), DedupConfig(8)).select("packet_id", "chunk_seq", "deviation").collect()}
    assert native == kernel


def test_packed_basis_column(spark):
    import numpy as np

    from basisflow.functions import hamming

    chunks = np.random.default_rng(1).integers(0, 256, (50, 8), dtype=np.uint8)
    words, _, _ = hamming.codewords(chunks)
    want = [int.from_bytes(b.tobytes(), "big") for b in hamming.pack_basis(words)]
    df = spark.createDataFrame([(i, int.from_bytes(w.tobytes(), "big", signed=True)) for i, w in enumerate(words)], "i int, w long")
    assert [r.b for r in df.select("i", basis8(F.col("w")).alias("b")).orderBy("i").collect()] == want


def test_pool_grows_only_by_what_is_new(spark, small):
    cfg = DedupConfig(8)
    encoded = encode.encode_payloads(source.conversations(spark, small), cfg)
    half = encoded.where(F.col("packet_id") % 2 == 0)
    first = pool.build(half)
    both = pool.extend(first, encoded)
    assert both.count() == encoded.select("basis_key").distinct().count()
    assert pool.missing(half, first).count() == 0


def test_dual_catches_what_short_corrupts(spark, small):
    cfg = DedupConfig(8, fp_bytes=2)
    unique = encode.unique_chunks(source.documents(spark, small), [cfg])
    wrong = {s: schemes.corruption(unique, cfg, s).first() for s in ("exact", "sim_plain", "sim_short", "sim_dual")}
    assert wrong["sim_short"].wrong_chunks > wrong["sim_plain"].wrong_chunks > 0
    assert wrong["sim_dual"].caught_chunks > 0 and wrong["sim_dual"].wrong_chunks < wrong["sim_short"].wrong_chunks


def test_edge_payloads(spark):
    rows = [("a", 1, bytearray()), ("a", 2, None), ("a", 3, bytearray(b"x")), ("b", 4, bytearray(64)), ("b", 5, bytearray(b"\xff" * 65))]
    data = spark.createDataFrame(rows, "source_id string, packet_id long, payload binary")
    for cfg in (DedupConfig(64), DedupConfig(16, "rs"), DedupConfig(8, preprocess="delta", sample_width=4)):
        encoded = encode.encode_payloads(data, cfg)
        restored = pool.reconstruct(encoded, pool.build(encoded), cfg)
        assert {r.packet_id for r in restored.collect()} == {3, 4, 5}
        assert pool.roundtrip_mismatches(data, restored).count() == 0


def test_spare_bit_only(spark):
    data = spark.createDataFrame([("a", 1, bytearray(b"12345670")), ("a", 2, bytearray(b"12345671"))], "source_id string, packet_id long, payload binary")
    found = schemes.outcomes(encode.encode_payloads(data, DedupConfig(8))).orderBy("packet_id").collect()
    assert [r.outcome for r in found] == ["new_basis", "new_chunk"]


def test_topology_is_checked(spark):
    with pytest.raises(ValueError):
        protocol.topology(spark, [protocol.Node("a", "source", "basic", "nowhere")])


def test_poison_is_rejected(spark, small):
    bodies = encode.chunk_payloads(source.conversations(spark, small), 16).select("source_id", F.col("chunk").alias("body"))
    marked = protocol.validate(protocol.inject_bad_fingerprints(bodies, 0.2))
    share = marked.agg(F.avg(F.when(F.col("valid"), 0).otherwise(1))).first()[0]
    assert 0.15 < share < 0.25
    assert protocol.validate(protocol.inject_bad_fingerprints(bodies, 0.0)).where(~F.col("valid")).count() == 0


def test_content_defined_cuts_follow_content():
    import random

    rnd = random.Random(1)
    data = bytes(rnd.randrange(256) for _ in range(20_000))
    ends = chunking.boundaries(data, 64, 256, 1024)
    assert ends[-1] == len(data) and all(b - a <= 1024 for a, b in zip([0, *ends], ends))
    pieces = lambda d: {d[a:b] for e in [chunking.boundaries(d, 64, 256, 1024)] for a, b in zip([0, *e], e)}
    assert len(pieces(data) & pieces(b"new start" + data)) > 0.9 * len(ends)


def test_stream_outcomes_equal_batch(spark, small, tmp_path):
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    cfg = DedupConfig(4)
    stream = live.stream_outcomes(live.event_records(live.read_events(spark, small)), cfg)
    live.run_once(stream, "outcome_table", str(tmp_path / "c"))
    got = spark.table("outcome_table").agg(F.sum("new_basis"), F.sum("new_chunk"), F.sum("repeat")).first()
    batch = schemes.outcomes(encode.encode_payloads(live.event_records(source.table(spark, small, "events")), cfg))
    want = {r.outcome: r["count"] for r in batch.groupBy("outcome").count().collect()}
    assert tuple(got) == (want["new_basis"], want["new_chunk"], want.get("repeat", 0))


def test_forgetting_stream_and_sessions(spark, small, tmp_path):
    records = live.event_records(live.read_events(spark, small))
    live.run_once(live.new_bases(records, DedupConfig(4), forget="365 days"), "forgetting", str(tmp_path / "a"))
    assert spark.table("forgetting").count() == live.new_bases(live.event_records(source.table(spark, small, "events")), DedupConfig(4)).count()
    live.run_once(live.sessions(records, "1 hour", late="365 days"), "bursts", str(tmp_path / "b"), "append")
    assert spark.table("bursts").columns == ["start", "end", "source_id", "packets"]


def test_a_chunk_of_a_third_of_all_rows(spark):
    """Blanks everywhere: outcomes and totals are as in a simulation, and the common chunk's rows never meet in a join on its key."""
    rows = [("s", i, bytearray((b"        " if i % 3 == 0 else f"{i:08d}".encode()) + f"{i % 7:08d}".encode())) for i in range(300)]
    data = spark.createDataFrame(rows, "source_id string, packet_id long, payload binary")
    cfg = DedupConfig(8)
    found = schemes.outcomes(encode.encode_payloads(data, cfg))
    want = {"new_basis": 0, "new_chunk": 0, "repeat": 0}
    chunks, bases = set(), set()
    for r in sorted(encode.encode_payloads(data, cfg).collect(), key=lambda r: (r.packet_id, r.chunk_seq)):
        key, basis = bytes(r.chunk_key), bytes(r.basis_key)
        want["repeat" if key in chunks else "new_chunk" if basis in bases else "new_basis"] += 1
        chunks.add(key)
        bases.add(basis)
    assert {r.outcome: r["count"] for r in found.groupBy("outcome").count().collect()} == {k: n for k, n in want.items() if n}
    totals = schemes.outcome_totals(costs.counts(encode.unique_chunks(data, [cfg])))
    assert {r.outcome: r.chunks for r in totals.collect()} == {k: n for k, n in want.items() if n}
    assert schemes.traffic_of_totals(totals, cfg).orderBy("scheme", "outcome").collect() == schemes.traffic(found, cfg).orderBy("scheme", "outcome").collect()
    # a private pool for each source
    private = schemes.outcomes(encode.encode_payloads(data.withColumn("source_id", (F.col("packet_id") % 2).cast("string")), cfg), ("source_id",))
    assert private.where("outcome = 'repeat'").count() < want["repeat"]


def test_places_and_sums_of_a_large_source(spark):
    """One source with most rows, others with few: places and sums are those of a window over whole sources."""
    from pyspark.sql import Window

    from basisflow.operators import ordered

    rows = spark.range(5000).selectExpr("if(id % 7 = 0, concat('s', id % 5), if(id % 11 = 0, null, 'big')) AS s", "hash(id) AS o", "id % 13 AS v")
    got = ordered.numbered(rows, "s", ["o"])
    by = Window.partitionBy("s").orderBy("o")
    want = rows.withColumn("at", F.row_number().over(by) - 1)
    assert sorted(map(str, got.select("s", "o", "v", "at").collect())) == sorted(map(str, want.select("s", "o", "v", "at").collect()))
    sums = ordered.sums_before(got, "s", "at", F.col("v"), 16, "held").groupBy("s").agg(F.sum("held"), F.max("held"), F.count("*"))
    plain = rows.select("s", F.sum("v").over(by.rowsBetween(-16, 0)).alias("held")).groupBy("s").agg(F.sum("held"), F.max("held"), F.count("*"))
    assert sorted(map(str, (tuple(r) for r in sums.collect()))) == sorted(map(str, (tuple(r) for r in plain.collect())))


def test_restoration_spreads_common_bases(spark, small, monkeypatch):
    monkeypatch.setattr(pool, "HOT_REFS", 20)
    cfg = DedupConfig(8)
    data = source.conversations(spark, small)
    encoded = encode.encode_payloads(data, cfg)
    assert pool.roundtrip_mismatches(data, pool.reconstruct(encoded, pool.build(encoded), cfg)).count() == 0


def pieces(data, n_b):
    return [data[i : i + n_b].ljust(n_b, b"\0") for i in range(0, len(data), n_b)]


@pytest.mark.parametrize("name, load, codecs_, sizes", [("deflate_ratio", source.conversations, ["deflate"], (16, 64, 256)), ("lzw_ratio", source.conversations, ["lzw"], (16, 64, 256)), ("codec_matrix", lambda s, d: source.ship_dates(s, d, 256), list(codecs.CODECS), (64, 128, 256)), ("codec_ratio_conversations", source.conversations, ["deflate", "lzw"], (16, 64, 128, 256)), ("codec_ratio_pages", source.pages, ["deflate", "lzw"], (16, 64, 128, 256)), ("codec_ratio_documents", source.documents, ["deflate", "lzw"], (16, 64, 128, 256))])
def test_codec_totals_equal_single_chunks(spark, small, name, load, codecs_, sizes):
    data = [bytes(r.payload) for r in load(spark, small).collect()]
    want = {}
    for codec, n_b in itertools.product(codecs_, sizes):
        chunks = [c for d in data for c in pieces(d, n_b)]
        total = 0
        for c in chunks:
            if codec == "deflate":
                packer = zlib.compressobj(6, zlib.DEFLATED, -15)
                total += len(packer.compress(c) + packer.flush())
            elif codec == "lzw":
                codes, bits = codecs.lzw_encode(c)
                assert codecs.lzw_decode(codes) == c
                total += -(-bits // 8)
            elif codec == "bz2":
                total += len(bz2.compress(c))
            else:
                total += len(lzma.compress(c, format=lzma.FORMAT_RAW, filters=[{"id": lzma.FILTER_LZMA2, "preset": 6}]))
        want[codec, n_b] = (len(chunks), len(chunks) * n_b, total, len(chunks) * n_b / total)
    got = {(r.codec, r.n_b): (r.chunks, r.original_bytes, r.total_bytes, r.ratio) for r in registry.QUERIES[name](spark, small).collect()}
    assert got == want


def test_stream_compression_equals_one_stream_per_source(spark, small):
    data = sorted(((r.source_id, r.packet_id, bytes(r.payload)) for r in source.conversations(spark, small).collect()))
    whole = 0
    for _, own in itertools.groupby(data, key=lambda r: r[0]):
        packer = zlib.compressobj(6, zlib.DEFLATED, -15)
        whole += sum(len(packer.compress(d) + packer.flush(zlib.Z_SYNC_FLUSH)) for _, _, d in own)
    got = {r.scope: (r.original_bytes, r.total_bytes) for r in registry.QUERIES["stream_compression"](spark, small).collect()}
    assert got["source"] == (sum(len(d) for *_, d in data), whole)
    alone = [c for *_, d in data for c in pieces(d, 64)]
    assert got["packet of 64"] == (64 * len(alone), sum(codecs.deflate_size(c) for c in alone))


def test_content_defined_totals(spark, small):
    seen, n = {}, 0
    for r in source.documents(spark, small).collect():
        data, at = bytes(r.payload), 0
        for end in chunking.boundaries(data, 64, 256, 1024):
            n, seen[data[at:end]], at = n + 1, seen.get(data[at:end], 0) + 1, end
    got = registry.QUERIES["content_defined_chunks"](spark, small).first()
    assert (got.chunks, got.unique_chunks, got.bytes, got.unique_bytes) == (n, len(seen), sum(len(c) * k for c, k in seen.items()), sum(map(len, seen)))


def test_reed_solomon_codes_by_brute_force(spark, small):
    from basisflow.functions import reed_solomon

    payloads = [bytes(r.payload) for r in source.conversations(spark, small).collect()]
    got = {(r.n_b, r.k_b): (r.chunks, r.exact_bases, r.bases, r.farthest) for r in registry.QUERIES["rs_codes"](spark, small).collect()}
    for n_b, k_b in ((16, 14), (64, 56), (255, 253), (255, 247)):
        chunks = [c for p in payloads for c in pieces(p, n_b)]
        unique = np.frombuffer(b"".join(sorted(set(chunks))), np.uint8).reshape(-1, n_b)
        basis, wrong = reed_solomon.split(unique, k_b)
        assert (reed_solomon.rs_syndromes(unique ^ wrong, n_b - k_b) == 0).all()  # every basis is that of a word of the code
        assert ((unique ^ wrong)[:, :k_b] == basis).all() and got[n_b, k_b] == (len(chunks), len(unique), len(np.unique(basis, axis=0)), int((wrong != 0).sum(1).max()))
        assert (wrong != 0).sum(1).max() <= n_b - k_b


def test_sketched_counts_are_near(spark, small):
    got = registry.QUERIES["approximate_bases"](spark, small).first()
    exact = registry.QUERIES["basis_count_documents_8"](spark, small).first()
    assert got.chunks == exact.chunks
    assert abs(got.bases / exact.bases - 1) < 0.03 and abs(got.exact_bases / exact.exact_bases - 1) < 0.03


def test_sketched_sharing_is_near(spark, small):
    got = registry.QUERIES["approximate_sharing"](spark, small).first()
    rows = with_codeword(encode.chunk_payloads(source.documents(spark, small), 8), 8).select("source_id", "codeword").distinct().collect()
    halves = [{bytes(r.codeword) for r in rows if zlib.crc32(r.source_id.encode()) % 2 == side} for side in (0, 1)]
    want = len(halves[0]), len(halves[1]), len(halves[0] & halves[1]), len(halves[0] | halves[1])
    assert all(abs(g - w) < 0.05 * want[3] / 2 for g, w in zip(got, want, strict=True))


def test_codecs_of_one_row_group_run_in_many_tasks(spark, small):
    """Sizes alone equal those of the codes, whatever the table's limit; equal chunks are weighed, not lost."""
    rnd = random.Random(8)
    for size in (0, 1, 2, 16, 255, 256, 257, 3000):
        for symbols in (1, 2, 256):
            data = bytes(rnd.randrange(symbols) for _ in range(size))
            assert all(codecs.lzw_size(data, most) == -(-codecs.lzw_encode(data, most)[1] // 8) for most in (9, 10, 16))
    docs = source.documents(spark, small).coalesce(1)
    once, twice = (codecs.codec_totals(d, ["deflate", "lzw"], [16, 64]) for d in (docs, docs.union(docs)))
    assert "REPARTITION" in once._jdf.queryExecution().executedPlan().toString()
    want = {(r.codec, r.n_b): (2 * r.chunks, 2 * r.total_bytes) for r in once.collect()}
    assert {(r.codec, r.n_b): (r.chunks, r.total_bytes) for r in twice.collect()} == want and len(want) == 4


def test_repeated_delivery_changes_nothing(spark, small):
    cfg = DedupConfig(8)
    data = source.conversations(spark, small)
    once, twice = (pool.build(encode.encode_payloads(d, cfg)).select("basis_key", "basis") for d in (data, data.union(data)))
    assert once.exceptAll(twice).count() == 0 and twice.exceptAll(once).count() == 0


def test_synthetic_study_is_as_published():
    """Published ratios of the similar and the exact scheme at 2048 and 4096 bytes."""
    con = duckdb.connect()
    con.execute("CREATE TABLE customer AS SELECT range AS c_custkey FROM range(131072)")  # whole balls for every parity
    rows = {(m, scheme): ratio for m, _, scheme, _, _, _, ratio in con.execute(registry.ORACLE_SQL["synthetic_ratio"]).fetchall()}
    assert abs(rows[14, "sim_plain"] / 334 - 1) < 0.01 and abs(rows[15, "sim_plain"] / 668 - 1) < 0.01
    assert all(abs(rows[m, "exact"] / 1.58 - 1) < 0.01 for m in (14, 15))
    assert all(rows[m, "sim_plain"] > 1 for m in range(6, 16)) and rows[5, "sim_plain"] < 1  # from 8 bytes up
    assert all(rows[m, s] >= rows[m, "exact"] for m in range(6, 16) for s in ("sim_short", "sim_dual"))


def test_random_chunks_grow_under_codecs(spark, small, monkeypatch):
    from basisflow.plans import experiments

    monkeypatch.setattr(experiments, "CODEC_PARITY", 8)
    rows = registry.QUERIES["synthetic_codecs"](spark, small).collect()
    assert {r.m for r in rows} == set(range(3, 9)) and all(r.ratio < 1 for r in rows)


def test_codecs_are_shown_every_parity(spark, small):
    """Each customer's chunk of each parity of ``synthetic_ratio``, made one by one."""
    ids = duckdb.sql(f"SELECT c_custkey FROM '{small}/customer.parquet'").fetchnumpy()["c_custkey"].tolist()
    want = {}
    for m in {r[0] for r in views(small).execute(registry.ORACLE_SQL["synthetic_ratio"]).fetchall()}:
        flips = [np.array([int(hashlib.sha256(f"1:flip:{i}".encode()).hexdigest()[:8], 16) % (1 << m)]) for i in ids]
        chunks = [c.tobytes() for c in synthetic.ball_chunks([f"1:{i >> m}" for i in ids], flips, m)[0]]
        n_b = HammingParams(m).n_b
        want |= {(m, codec, n_b): (len(ids), len(ids) * n_b, sum(map(size, chunks))) for codec, size in (("deflate", codecs.deflate_size), ("lzw", codecs.lzw_size))}
    got = registry.QUERIES["synthetic_codecs"](spark, small).collect()
    assert len(got) == len(want) == 2 * len(range(3, 16))
    assert {(r.m, r.codec, r.n_b): (r.chunks, r.original_bytes, r.total_bytes) for r in got} == want


@pytest.mark.parametrize("per_basis", [None, 16])
def test_a_chunk_is_drawn_for_each_id(spark, per_basis):
    ids = [5, 5, 0, 1, 63, 64, -1, -65, 1 << 40, *range(200, 300)]
    given = spark.createDataFrame([(i,) for i in [*ids, None]], "id long")
    got = sorted((r.source_id, r.packet_id, bytes(r.payload)) for r in synthetic.drawn(given, 6, per_basis).collect())
    share = per_basis or 64
    flips = [np.array([i % share if per_basis else int(hashlib.sha256(f"1:flip:{i}".encode()).hexdigest()[:8], 16) % share]) for i in ids]
    chunks, _ = synthetic.ball_chunks([f"1:{i // share}" for i in ids], flips, 6)
    assert got == sorted((str(i % 16), i, c.tobytes()) for i, c in zip(ids, chunks, strict=True))


def views(folder):
    con = duckdb.connect()
    for path in glob.glob(f"{folder}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(path)[:-8]} AS SELECT * FROM '{path}'")
    return con


def plain(value):
    return "null" if value is None or value != value else f"{float(value):.9g}" if isinstance(value, (int, float)) and not isinstance(value, bool) else str(value)


@pytest.mark.parametrize("name", sorted(registry.ORACLE_SQL))
def test_queries_equal_duckdb(spark, small, name):
    got = registry.QUERIES[name](spark, small)
    cursor = views(small).execute(registry.ORACLE_SQL[name])
    names = [d[0] for d in cursor.description]
    assert sorted(names) == sorted(got.columns)
    want = sorted(tuple(plain(v) for _, v in sorted(zip(names, r, strict=True))) for r in cursor.fetchall())
    assert sorted(tuple(plain(r[c]) for c in sorted(got.columns)) for r in got.collect()) == want


@pytest.mark.parametrize("name, table", [("chunk_to_basis_ratio", "documents"), ("default_schemes", "lineitem"), ("fingerprint_ceiling", "documents"), ("hamming_table", "documents"), ("illegal_messages", "events"), ("min_matches_example", "documents"), ("pool_capacity", "orders"), ("rs_radius_table", "pages"), ("storage_repeat_sweep", "documents"), ("synthetic_codecs", "customer"), ("synthetic_ratio", "customer"), ("unique_sweep", "customer")])
def test_queries_read_their_tables(spark, small, monkeypatch, name, table):
    read = []
    whole = source.table
    monkeypatch.setattr(source, "table", lambda s, d, n: read.append(n) or whole(s, d, n))
    registry.QUERIES[name](spark, small)
    assert table in read


def test_entry(spark):
    assert __spark_entry__.entry(spark).count() == 5
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
