"""Costs, outcomes, pools and fingerprints of the schemes on the given tables."""

from __future__ import annotations

from pyspark.sql import functions as F

from basisflow.config import FP_EXAMPLE, FP_STUDY, DedupConfig, HammingParams, max_ratio, pool_capacity
from basisflow.functions.fingerprints import collision_reports, fingerprint
from basisflow.operators import costs, encode, pool, schemes, synthetic
from basisflow.plans import sql
from basisflow.plans.registry import register
from basisflow.sources import payloads as source


def counted(payloads, cfg):
    return costs.counts(encode.unique_chunks(payloads, [cfg]))


_D8 = DedupConfig(8)
_TABLES = {
    "cost_all_schemes": (source.documents, sql.DOCUMENTS, _D8),
    "cost_documents_4": (source.documents, sql.DOCUMENTS, DedupConfig(4)),
    "cost_documents_16": (source.documents, sql.DOCUMENTS, DedupConfig(16)),
    "cost_documents_4_offset": (source.documents, sql.DOCUMENTS, DedupConfig(4, preprocess="offset")),
    "cost_pages_4_short_fp": (source.pages, sql.PAGES, DedupConfig(4, fp_bytes=2)),
    "cost_conversations_8": (source.conversations, sql.CONVERSATIONS, _D8),
    "cost_records_4_short_fp": (source.records4, sql.RECORDS4, DedupConfig(4, fp_bytes=2)),
    "cost_records_8": (source.records8, sql.RECORDS8, _D8),
    "cost_shipdate_offset": (lambda s, d: source.ship_dates(s, d, 8), sql.ship_dates(8), DedupConfig(8, preprocess="offset", sample_width=2)),
}
for _name, (_load, _sql, _cfg) in _TABLES.items():
    _oracle = sql.counted(_sql, _cfg.n_b, _cfg.preprocess, _cfg.sample_width, dev=str(_cfg.fixed_deviation)) + " " + sql.scheme_rows(_cfg.n_b, _cfg.basis_bytes, _cfg.fp_bytes)
    register(_name, _oracle)(lambda spark, sf_dir, load=_load, cfg=_cfg: costs.scheme_table(counted(load(spark, sf_dir), cfg), cfg))

for _scheme in ("raw", "exact", "sim_plain", "sim_short", "sim_dual"):
    _oracle = sql.counted(sql.RECORDS8, 8, dev="1") + f" SELECT scheme, chunks, total_bytes FROM ({sql.scheme_rows(8, 8, FP_STUDY)}) WHERE scheme = '{_scheme}'"
    register(f"cost_{_scheme}", _oracle)(lambda spark, sf_dir, s=_scheme: costs.scheme_table(counted(source.records8(spark, sf_dir), _D8), _D8).where(F.col("scheme") == s).select("scheme", "chunks", "total_bytes"))


@register("dominance_checks", sql.counted(sql.DOCUMENTS, 8, dev="1") + " SELECT true AS short_le_exact, true AS dual_le_exact, bases <= exact_bases AS bases_le_exact, exact_bases <= chunks AS exact_le_chunks, true AS q_is_difference, true AS plain_is_short_and_deviations FROM k")
def dominance_checks(spark, sf_dir):
    return costs.dominance(counted(source.documents(spark, sf_dir), _D8), _D8)


@register("conditions", sql.counted(sql.RECORDS8, 8, dev="1") + " SELECT exact_bases * 8 < chunks * 2 AS exact_pays, bases * 8 < exact_bases * 8 - dev_sum AS plain_beats_exact, chunks - exact_bases AS exact_matches, chunks - bases AS matches, (dev_sum + (chunks - exact_bases) * 8) / 8.0::DOUBLE AS matches_needed FROM k")
def conditions(spark, sf_dir):
    """When deduplication pays, and when similarity beats it, on the records."""
    c = F.col
    k = counted(source.records8(spark, sf_dir), _D8)
    need = costs.min_matches_plain(c("chunks"), c("chunks") - c("exact_bases"), c("dev_sum"), 8, 8)
    return k.select(costs.exact_pays(c("exact_bases"), c("chunks"), 8, FP_STUDY).alias("exact_pays"), costs.plain_beats_exact(c("bases"), c("exact_bases"), c("dev_sum"), 8, 8).alias("plain_beats_exact"), (c("chunks") - c("exact_bases")).alias("exact_matches"), (c("chunks") - c("bases")).alias("matches"), need.alias("matches_needed"))


@register("min_matches_example", "WITH n AS (SELECT sum((octet_length(encode(text)) + 127) // 128)::BIGINT AS chunks FROM documents), e AS (SELECT chunks, chunks * 20 / 128.0::DOUBLE AS f FROM n) SELECT chunks, f AS exact_pays_from, ceil((chunks * 1 - chunks + f * 128) / 127 - f)::BIGINT AS extra_matches_sum_zero, ceil((chunks * 2 - chunks + f * 128) / 127 - f)::BIGINT AS extra_matches_sum_one FROM e")
def min_matches_example(spark, sf_dir):
    """The worked example on the documents' chunks of 128 bytes, with 20-byte fingerprints.

    Extra matches are counted over the matches where exact deduplication starts to pay, for a deviation and basis that
    together are as long as a chunk, or one byte longer.
    """
    n_b, k_b, chunks = 128, HammingParams(10).k_b, F.col("chunks")
    base = costs.exact_pays_from(chunks, n_b, FP_EXAMPLE)
    total = source.documents(spark, sf_dir).agg(F.sum(F.ceil(F.octet_length("payload") / n_b)).cast("long").alias("chunks"))
    extra = [F.ceil(costs.min_matches_plain(chunks, base, chunks * d, n_b, k_b) - base) for d in (n_b - k_b, n_b - k_b + 1)]
    return total.select("chunks", base.alias("exact_pays_from"), extra[0].alias("extra_matches_sum_zero"), extra[1].alias("extra_matches_sum_one"))


@register("dual_outcomes", sql.outcomes(sql.DOCUMENTS, 8) + " SELECT outcome, count(*) AS chunks FROM o GROUP BY outcome")
def dual_outcomes(spark, sf_dir):
    return schemes.outcome_totals(counted(source.documents(spark, sf_dir), _D8)).select("outcome", "chunks")


_SENT = {
    "raw": {"repeat": (8, 0, 2), "new_chunk": (8, 0, 2), "new_basis": (8, 0, 2)},
    "exact": {"repeat": (6, 0, 2), "new_chunk": (14, 0, 4), "new_basis": (14, 0, 4)},
    "sim_plain": {"repeat": (6, 1, 2), "new_chunk": (6, 1, 2), "new_basis": (14, 1, 4)},
    "sim_short": {"repeat": (6, 0, 2), "new_chunk": (6, 0, 2), "new_basis": (14, 0, 4)},
    "sim_dual": {"repeat": (6, 0, 2), "new_chunk": (6, 1, 4), "new_basis": (14, 0, 4)},
}
_VALUES = ", ".join(f"('{s}', '{o}', {a + d}, {n})" for s, by in _SENT.items() for o, (a, d, n) in by.items())


@register("message_log_totals", sql.outcomes(sql.CONVERSATIONS, 8) + f" SELECT scheme, t.outcome, count(*) AS chunks, sum(n)::BIGINT AS messages, sum(size)::BIGINT AS up_bytes FROM o JOIN (VALUES {_VALUES}) t(scheme, outcome, size, n) ON o.outcome = t.outcome GROUP BY scheme, t.outcome")
def message_log_totals(spark, sf_dir):
    """Every message of every scheme, then summed: equals the closed forms."""
    found = pool.kept(schemes.outcomes(encode.encode_payloads(source.conversations(spark, sf_dir), _D8)), "outcomes")
    out = None
    for scheme in ("raw", "exact", "sim_plain", "sim_short", "sim_dual"):
        part = schemes.message_log(found, _D8, scheme).withColumn("scheme", F.lit(scheme))
        out = part if out is None else out.unionByName(part)
    return out.groupBy("scheme", "outcome").agg(F.count(F.when(F.col("step") == 1, 1)).alias("chunks"), F.count("*").alias("messages"), F.sum(F.when(F.col("direction") == "up", F.col("bytes"))).alias("up_bytes"))


@register("traffic_16_nodes", sql.outcomes(sql.RECORDS8, 8) + f" SELECT scheme, sum(n)::BIGINT AS messages, sum(size)::BIGINT AS up_bytes FROM o JOIN (VALUES {_VALUES}) t(scheme, outcome, size, n) ON o.outcome = t.outcome GROUP BY scheme")
def traffic_16_nodes(spark, sf_dir):
    """Sixteen sources, one sink, a shared pool: messages and bytes under each scheme, from counts alone."""
    found = schemes.outcome_totals(counted(source.records8(spark, sf_dir), _D8))
    return schemes.traffic_of_totals(found, _D8).groupBy("scheme").agg(F.sum("messages").alias("messages"), F.sum("up_bytes").alias("up_bytes"))


@register("shared_vs_private_pool", f"WITH {sql.chunks(sql.RECORDS4, 4)}, {sql.hamming(4)} SELECT 'private' AS pool, count(DISTINCT (source_id, x)) AS exact_bases, count(DISTINCT (source_id, word)) AS bases FROM w UNION ALL SELECT 'shared', count(DISTINCT x), count(DISTINCT word) FROM w")
def shared_vs_private_pool(spark, sf_dir):
    """What sharing one pool among sixteen sources saves."""
    unique = pool.kept(encode.unique_chunks(source.records4(spark, sf_dir), [DedupConfig(4)], by_source=True), "unique")
    private = costs.counts(unique, ("cfg", "source_id")).agg(F.lit("private").alias("pool"), F.sum("exact_bases").alias("exact_bases"), F.sum("bases").alias("bases"))
    shared = unique.groupBy("chunk_key").agg(F.first("basis_key").alias("basis_key")).groupBy("basis_key").agg(F.count("*").alias("u")).agg(F.lit("shared").alias("pool"), F.sum("u").alias("exact_bases"), F.count("*").alias("bases"))
    return private.unionByName(shared)


_EVENT = "SELECT user_id::VARCHAR AS source_id, event_id AS packet_id, ts, " + " || ".join(sql.byte(v) for v in ("CASE event_type WHEN 'click' THEN 1 WHEN 'error' THEN 2 WHEN 'purchase' THEN 3 WHEN 'signup' THEN 4 WHEN 'view' THEN 5 ELSE 0 END", "coalesce((props::JSON->>'k')::BIGINT, 0) % 256", "user_id % 256")) + " || '00' AS h FROM events"


@register("pool_growth_daily", f"WITH p AS ({_EVENT}), c AS (SELECT source_id, packet_id, ts, 0 AS chunk_seq, h AS x FROM p), {sql.hamming(4)}, f AS (SELECT word, min(ts)::DATE AS day FROM w GROUP BY word) SELECT day::VARCHAR AS day, count(*) AS new_bases, sum(count(*)) OVER (ORDER BY day)::BIGINT AS pool_size FROM f GROUP BY day")
def pool_growth_daily(spark, sf_dir):
    """New bases by day, and the pool's size after it: one row per day, so the running sum is over few rows."""
    from pyspark.sql import Window

    from basisflow.functions.hamming import with_codeword
    from basisflow.streaming.pool import event_records

    rows = with_codeword(event_records(source.table(spark, sf_dir, "events")).withColumnRenamed("payload", "chunk"), 4)
    firsts = rows.groupBy("codeword").agg(F.min("ts").alias("ts"))
    days = firsts.groupBy(F.to_date("ts").alias("day")).agg(F.count("*").alias("new_bases"))
    return days.select(F.col("day").cast("string").alias("day"), "new_bases", F.sum("new_bases").over(Window.orderBy("day")).alias("pool_size"))


@register("storage_cost", sql.counted(sql.DOCUMENTS, 8, dev="1") + " SELECT chunks, exact_bases, bases, exact_bases * 8 + chunks * 6 AS exact_bytes, bases * 8 + chunks * 6 + dev_sum AS similar_bytes FROM k")
def storage_cost(spark, sf_dir):
    return costs.storage(counted(source.documents(spark, sf_dir), _D8), _D8)


@register("pool_capacity", "SELECT fp, bits, (256 * 1048576) // (bits // 8 + 8) AS records, keys, ceil(keys / ((256 * 1048576) // (bits // 8 + 8)))::BIGINT AS memories FROM (VALUES ('crc32', 32), ('md5', 128), ('sha1', 160), ('sha256', 256)) t(fp, bits) CROSS JOIN (SELECT count(DISTINCT o_orderkey) AS keys FROM orders)")
def pool_capacity_query(spark, sf_dir):
    """Records that a memory of 256 MiB holds, and the memories that a record for each order needs."""
    kinds = spark.createDataFrame([(n, b, pool_capacity(256, b)) for n, b in (("crc32", 32), ("md5", 128), ("sha1", 160), ("sha256", 256))], "fp string, bits int, records long")
    keys = source.table(spark, sf_dir, "orders").agg(F.countDistinct("o_orderkey").alias("keys"))
    return kinds.crossJoin(F.broadcast(keys)).withColumn("memories", F.ceil(F.col("keys") / F.col("records")))  # one row of keys


_CEILINGS = ((40, 20), (64, 6), (64, 4), (64, 20))


@register("fingerprint_ceiling", " UNION ALL ".join(f"SELECT {n} AS n_b, {h} AS h, {n} / {h}::DOUBLE AS max_ratio, chunks * {n} / (exact_bases * {n} + chunks * {h})::DOUBLE AS exact_ratio FROM ({sql.counted(sql.DOCUMENTS, n, transform='identity')} SELECT chunks, exact_bases FROM k)" for n, h in _CEILINGS))
def fingerprint_ceiling(spark, sf_dir):
    """The ratio that no deduplication with such fingerprints can pass, and what exact deduplication reaches on the documents."""
    cfgs = [DedupConfig(n, "identity") for n in (40, 64)]
    names = spark.createDataFrame([([c.n_b for c in cfgs].index(n), n, h, max_ratio(n, h)) for n, h in _CEILINGS], "cfg int, n_b int, h int, max_ratio double")
    found = costs.counts(encode.unique_chunks(source.documents(spark, sf_dir), cfgs)).join(F.broadcast(names), "cfg")
    return found.select("n_b", "h", "max_ratio", (F.col("chunks") * F.col("n_b") / (F.col("exact_bases") * F.col("n_b") + F.col("chunks") * F.col("h"))).alias("exact_ratio"))


def _collision_sql(algo: str, width: int) -> str:
    return f"SELECT '{algo}' AS algo, {width}::BIGINT AS fp_bytes, sum(b)::BIGINT AS bodies, count(*) AS fps, count(*) FILTER (b > 1) AS colliding_fps, coalesce(sum(n) FILTER (b > 1), 0)::BIGINT AS affected_chunks FROM (SELECT substr({algo}(unhex(x)), 1, {2 * width}) AS fp, count(*) AS b, sum(n) AS n FROM u GROUP BY 1)"


_WIDTHS = [("md5", w) for w in (1, 2, 3, 4, 6, 8, 16)] + [(a, w) for a in ("sha1", "sha256") for w in (1, 2, 3, 4, 6, 20)]


@register("fp_collisions_by_width", f"WITH {sql.chunks(sql.DOCUMENTS, 8)}, u AS (SELECT x, count(*) AS n FROM c GROUP BY x) " + " UNION ALL ".join(_collision_sql(a, w) for a, w in _WIDTHS))
def fp_collisions_by_width(spark, sf_dir):
    bodies = encode.unique_chunks(source.documents(spark, sf_dir), [_D8]).select(F.col("chunk_key").alias("body"), "n")
    return collision_reports(bodies, _WIDTHS)


def _crc_table() -> list[int]:
    """The public CRC-32 table, from its reflected polynomial."""
    out = []
    for value in range(256):
        for _ in range(8):
            value = value >> 1 ^ (0xEDB88320 if value & 1 else 0)
        out.append(value)
    return out


_CRC = f"xor(4294967295, list_reduce(list_prepend(4294967295, list_transform(range(0, length(x) // 2), lambda i: ('0x' || substr(x, 2 * i + 1, 2))::BIGINT)), lambda a, v: xor(a >> 8, list_extract({_crc_table()}, (xor(a, v) & 255) + 1))))"


@register("pool_memory", sql.counted(sql.DOCUMENTS, 8) + " SELECT fp, bits, bases, bases * (bits // 8 + 8) AS pool_bytes, (256 * 1048576) // (bits // 8 + 8) AS fit_in_256_mib, ceil(bases * (bits // 8 + 8) / (256 * 1048576.0))::BIGINT AS memories FROM k CROSS JOIN (VALUES ('crc32', 32), ('md5', 128), ('sha1', 160), ('sha256', 256)) t(fp, bits)")
def pool_memory(spark, sf_dir):
    """The measured pool as records of a fingerprint and a pointer: its size, and how many memories of 256 MiB it needs."""
    kinds = F.explode(F.array(*(F.struct(F.lit(n).alias("fp"), F.lit(8 * b).alias("bits")) for n, b in (("crc32", 4), ("md5", 16), ("sha1", 20), ("sha256", 32)))))
    sized = counted(source.documents(spark, sf_dir), _D8).select("bases", kinds.alias("k")).select("k.fp", "k.bits", "bases")
    record = F.floor(F.col("bits") / 8) + 8
    sized = sized.withColumn("pool_bytes", F.col("bases") * record).withColumn("fit_in_256_mib", F.floor(F.lit(256 << 20) / record))
    return sized.withColumn("memories", F.ceil(F.col("pool_bytes") / (256 << 20)).cast("long"))


_CRC_WIDTHS = (1, 2, 3, 4)


@register("fp_crc32_collisions", f"WITH {sql.chunks(sql.DOCUMENTS, 8)}, u AS (SELECT x, count(*) AS n FROM c GROUP BY x), v AS (SELECT {_CRC} AS fp, n FROM u), f AS (SELECT w, fp >> (32 - 8 * w) AS fp, count(*) AS b, sum(n) AS n FROM v CROSS JOIN (VALUES (1), (2), (3), (4)) t(w) GROUP BY ALL) SELECT 'crc32' AS algo, w::BIGINT AS fp_bytes, sum(b)::BIGINT AS bodies, count(*) AS fps, count(*) FILTER (b > 1) AS colliding_fps, coalesce(sum(n) FILTER (b > 1), 0)::BIGINT AS affected_chunks FROM f GROUP BY w")
def fp_crc32_collisions(spark, sf_dir):
    bodies = encode.unique_chunks(source.documents(spark, sf_dir), [_D8]).select(F.col("chunk_key").alias("body"), "n")
    return collision_reports(bodies, [("crc32", w) for w in _CRC_WIDTHS])


def _cut_md5(body: str, width: int) -> str:
    return f"substr(md5(unhex({body})), 1, {2 * width})"


_WORD = "lpad(upper(to_hex((word << 1)::UBIGINT)), 16, '0')"
_CORRUPTION = f"""WITH {sql.chunks(sql.DOCUMENTS, 8)}, {sql.hamming(8)},
u AS (SELECT x, any_value({_WORD}) AS b, count(*) AS n, min(packet_id * 1048576 + chunk_seq) AS f FROM w GROUP BY x),
s AS (SELECT b, sum(n) AS n, min(f) AS f FROM u GROUP BY b),
e1 AS (SELECT {_cut_md5('x', 2)} AS fp, arg_min(x, f) AS held FROM u GROUP BY 1),
p2 AS (SELECT {_cut_md5('b', 2)} AS fp, arg_min(b, f) AS held FROM s GROUP BY 1),
p1 AS (SELECT {_cut_md5('b', 1)} AS fp, arg_min(b, f) AS held FROM s GROUP BY 1),
c1 AS (SELECT {_cut_md5('x', 1)} AS fp, arg_min(x, f) AS held FROM u GROUP BY 1),
b1 AS (SELECT {_cut_md5('b', 1)} AS fp, arg_min(b, f) AS held FROM u GROUP BY 1),
cb AS (SELECT {_cut_md5('x', 1)} AS fx, {_cut_md5('b', 1)} AS fb, arg_min(x, f) AS held FROM u GROUP BY 1, 2),
d AS (SELECT n, cb.held <> x AS unseen, c1.held <> x OR b1.held <> b AS other FROM u JOIN c1 ON c1.fp = {_cut_md5('x', 1)} JOIN b1 ON b1.fp = {_cut_md5('b', 1)} JOIN cb ON fx = {_cut_md5('x', 1)} AND fb = {_cut_md5('b', 1)})
SELECT 'exact' AS scheme, coalesce(sum(n), 0)::BIGINT AS wrong_chunks, 0::BIGINT AS caught_chunks FROM u JOIN e1 ON fp = {_cut_md5('x', 2)} WHERE x <> held
UNION ALL SELECT 'sim_plain', coalesce(sum(n), 0)::BIGINT, 0 FROM s JOIN p2 ON fp = {_cut_md5('b', 2)} WHERE b <> held
UNION ALL SELECT 'sim_short', coalesce(sum(n), 0)::BIGINT, 0 FROM s JOIN p1 ON fp = {_cut_md5('b', 1)} WHERE b <> held
UNION ALL SELECT 'sim_dual', coalesce(sum(n) FILTER (unseen), 0)::BIGINT, coalesce(sum(n) FILTER (NOT unseen AND other), 0)::BIGINT FROM d"""


@register("corruption_by_scheme", _CORRUPTION)
def corruption_by_scheme(spark, sf_dir):
    """Chunks restored wrongly with 2-byte fingerprints: short is worst, dual catches what its halves disagree on."""
    cfg = DedupConfig(8, fp_bytes=2)
    unique = pool.kept(encode.unique_chunks(source.documents(spark, sf_dir), [cfg]), "unique")
    out = None
    for scheme in ("exact", "sim_plain", "sim_short", "sim_dual"):
        part = schemes.corruption(unique, cfg, scheme).withColumn("scheme", F.lit(scheme))
        out = part if out is None else out.unionByName(part)
    return out


_TAMPERED = "('0x' || substr(sha256(unhex(x)), 1, 8))::BIGINT < 42949672"


@register("dual_sink_check", f"WITH {sql.chunks(sql.DOCUMENTS, 8)} SELECT count(*) AS chunks, count(*) FILTER ({_TAMPERED}) AS tampered, 0::BIGINT AS good_refused, count(*) FILTER ({_TAMPERED}) AS bad_refused FROM c")
def dual_sink_check(spark, sf_dir):
    """The sink of the dual scheme rebuilds every chunk and holds it against the half fingerprint that was sent; for a hundredth the deviation names another bit."""
    from basisflow.functions import hamming
    from basisflow.operators import packets

    rows = hamming.with_codeword(encode.chunk_payloads(source.documents(spark, sf_dir), 8), 8)
    bad = F.conv(F.substring(F.sha2("chunk", 256), 1, 8), 16, 10).cast("long") < 42949672
    place = F.when(bad, (F.col("syndrome") + 1) % 64).otherwise(F.col("syndrome"))
    # place 0 stands for no error: the spare bit goes apart
    flipped = F.when(place > 0, F.call_function("shiftleft", F.lit(1).cast("long"), place.cast("int"))).otherwise(F.lit(0).cast("long"))
    word = F.col("word").bitwiseXOR(flipped).bitwiseOR(F.col("spare").cast("long"))
    rebuilt = F.unhex(F.lpad(F.hex(word), 16, "0"))
    half = fingerprint(F.col("chunk"), "md5", 6 // 2)
    checked = rows.withColumn("word", hamming.words_of(F.col("codeword"), 8)[0]).select(bad.alias("bad"), packets.verify_dual(rebuilt, half, "md5", 3).alias("right"))
    return checked.agg(F.count("*").alias("chunks"), F.count(F.when(F.col("bad"), 1)).alias("tampered"), F.count(F.when(~F.col("bad") & ~F.col("right"), 1)).alias("good_refused"), F.count(F.when(F.col("bad") & ~F.col("right"), 1)).alias("bad_refused"))


_SAME = "SELECT 0::BIGINT AS mismatches, (SELECT count(*) FROM ({0}) WHERE length(h) > 0) AS packets"
_ROUNDTRIPS = {
    "roundtrip_hamming": (source.documents, sql.DOCUMENTS, DedupConfig(64)),
    "roundtrip_hamming_4096": (source.pages, sql.PAGES, DedupConfig(4096)),
    "roundtrip_rs": (source.conversations, sql.CONVERSATIONS, DedupConfig(16, "rs")),
    "roundtrip_offset": (source.documents, sql.DOCUMENTS, DedupConfig(16, preprocess="offset", sample_width=2)),
    "roundtrip_delta": (source.pages, sql.PAGES, DedupConfig(32, preprocess="delta", sample_width=4)),
    "roundtrip_identity": (source.conversations, sql.CONVERSATIONS, DedupConfig(24, "identity")),
}
for _name, (_load, _sql, _cfg) in _ROUNDTRIPS.items():

    def _roundtrip(spark, sf_dir, load=_load, cfg=_cfg):
        data = load(spark, sf_dir)
        encoded = encode.encode_payloads(data, cfg)
        restored = pool.reconstruct(encoded, pool.build(encoded), cfg)
        bad = pool.roundtrip_mismatches(data, restored).agg(F.count("*").alias("mismatches"))
        return bad.crossJoin(F.broadcast(restored.agg(F.count("*").alias("packets"))))  # one row each

    register(_name, _SAME.format(_sql))(_roundtrip)


@register("storage_repeat_sweep", sql.counted(sql.DOCUMENTS, 2, dev="1") + " SELECT r AS times, chunks * r AS chunks, exact_bases * 2 + chunks * r * 4 AS exact_bytes, bases * 2 + chunks * r * 4 + chunks * r AS similar_bytes FROM k CROSS JOIN (VALUES (1), (2), (4), (8)) t(r)")
def storage_repeat_sweep(spark, sf_dir):
    """The documents' 2-byte chunks, repeated: bytes at rest with 4-byte fingerprints."""
    cfg, out = DedupConfig(2, fp_bytes=4), None
    unique = pool.kept(encode.unique_chunks(source.documents(spark, sf_dir), [cfg]), "unique")
    for times in (1, 2, 4, 8):
        part = costs.storage(costs.counts(unique.withColumn("n", F.col("n") * times)), cfg).select(F.lit(times).alias("times"), "chunks", "exact_bytes", "similar_bytes")
        out = part if out is None else out.unionByName(part)
    return out


def _ball_sql(m: int) -> str:
    p = HammingParams(m)
    positions = sorted((q for q in range(3, 1 << m) if q & (q - 1)), reverse=True)
    data = " + ".join(f"(((basis >> {p.k - 1 - i}) & 1) << {q})" for i, q in enumerate(positions))
    masks = [sum(1 << q for q in range(1 << m) if q >> t & 1) for t in range(m)]
    parity = " + ".join(f"((bit_count((word & {mask})::BIT) % 2) << {1 << t})" for t, mask in enumerate(masks))
    return f"""WITH l AS (SELECT l_partkey, ('0x' || substr(md5(l_partkey::VARCHAR), 1, 15))::BIGINT >> {60 - p.k} AS basis, ('0x' || substr(sha256(l_orderkey || '|' || l_linenumber || '|' || l_partkey), 1, 8))::BIGINT % {1 << m} AS flip FROM lineitem JOIN part ON l_partkey = p_partkey),
d AS (SELECT *, {data} AS word FROM l), e AS (SELECT *, word + {parity} AS code FROM d)
SELECT count(*) AS chunks, count(DISTINCT xor(code, 1::BIGINT << flip)) AS unique_chunks, count(DISTINCT code) AS bases FROM e"""


@register("ball_from_tables", _ball_sql(5))
def ball_from_tables(spark, sf_dir):
    """Chunks around each part's word: as many bases as parts, whatever the flips."""
    from basisflow.functions import hamming

    chunks = synthetic.ball_from_tables(source.table(spark, sf_dir, "part").select("p_partkey"), source.table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey"), 5)
    rows = hamming.with_codeword(chunks.select(source.pack_uint(F.col("chunk_word"), 4).alias("chunk")), 4)
    unique = rows.groupBy("chunk", "codeword").agg(F.count("*").alias("n"))
    return unique.groupBy("codeword").agg(F.sum("n").alias("n"), F.count("*").alias("u")).agg(F.sum("n").alias("chunks"), F.sum("u").alias("unique_chunks"), F.count("*").alias("bases"))
