"""The experiments: ratios of all schemes, bases by chunk length, synthetic balls, and sweeps over a deployment."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from basisflow.config import FP_SYNTH, DedupConfig, HammingParams
from basisflow.functions.codecs import codec_totals
from basisflow.operators import costs, encode, synthetic
from basisflow.plans import sql
from basisflow.plans.registry import register
from basisflow.sources import payloads as source


def _study_sql(payloads: str, cfgs: list[DedupConfig]) -> str:
    parts = []
    for cfg in cfgs:
        counted = sql.counted(payloads, cfg.n_b, cfg.preprocess, cfg.sample_width, dev=str(cfg.fixed_deviation), transform=cfg.transform)
        rows = sql.scheme_rows(cfg.n_b, cfg.basis_bytes, cfg.fp_bytes)
        parts.append(f"SELECT '{cfg.transform}' AS transform, '{cfg.preprocess}' AS preprocess, {cfg.n_b}::BIGINT AS n_b, scheme, chunks, bodies, total_bytes, ratio FROM ({counted} {rows})")
    return " UNION ALL ".join(parts)


def study(payloads, cfgs):
    return costs.study(costs.counts(encode.unique_chunks(payloads, cfgs)), cfgs)


# --- ratios of every scheme, with and without offset removal, beside the codecs

_STREAMS = {"documents": (source.documents, sql.DOCUMENTS), "pages": (source.pages, sql.PAGES), "conversations": (source.conversations, sql.CONVERSATIONS)}
STUDY_SIZES = (16, 64, 128, 256)
STUDY = [DedupConfig(n, preprocess=p) for n in STUDY_SIZES for p in ("none", "offset")]

for _stream, (_load, _sql) in _STREAMS.items():
    register(f"ratio_study_{_stream}", _study_sql(_sql, STUDY))(lambda spark, sf_dir, load=_load: study(load(spark, sf_dir), STUDY))

    def _codecs(spark, sf_dir, load=_load):
        """DEFLATE and LZW, each chunk alone."""
        return codec_totals(load(spark, sf_dir), ["deflate", "lzw"], list(STUDY_SIZES)).withColumn("ratio", F.col("original_bytes") / F.col("total_bytes"))

    register(f"codec_ratio_{_stream}")(_codecs)


_DATES = [DedupConfig(n, preprocess=p, sample_width=2) for n in STUDY_SIZES for p in ("none", "offset", "delta")]


@register("ratio_study_shipdate", _study_sql(sql.ship_dates(256), _DATES))
def ratio_study_shipdate(spark, sf_dir):
    """The same on a slowly rising column, where offsets and differences help most."""
    return study(source.ship_dates(spark, sf_dir, 256), _DATES)


# --- bases by chunk length and method, column by column

#: Chunk lengths of the study, bytes of one packet of a column, and the longest chunk that a Reed-Solomon code over bytes can have.
LENGTHS, PACKET, LONGEST_RS = (32, 64, 128, 256, 512, 1024), 1024, 255


def _line(value, width):
    return lambda spark, sf_dir: source.column_stream(source.table(spark, sf_dir, "lineitem"), "l_suppkey", ["l_shipdate", "l_orderkey", "l_linenumber"], source.pack_uint(value(), width), PACKET // width)


def _line_sql(value: str, width: int) -> str:
    return sql.column("lineitem", "l_suppkey", "l_shipdate, l_orderkey, l_linenumber", sql.uint(value, width), PACKET // width)


_DAYS = "date_diff('day', DATE '1970-01-01', l_shipdate::DATE)"
#: name: (payloads, their SQL, bytes of a sample)
COLUMNS = {
    "shipdate": (_line(lambda: F.datediff(F.col("l_shipdate").cast("date"), F.lit("1970-01-01").cast("date")), 2), _line_sql(_DAYS, 2), 2),
    "quantity": (_line(lambda: F.col("l_quantity").cast("long"), 1), _line_sql("l_quantity", 1), 1),
    "price": (_line(lambda: source.hundredths(F.col("l_extendedprice")), 4), _line_sql("round(l_extendedprice * 100)", 4), 4),
    "partkey": (_line(lambda: F.col("l_partkey"), 4), _line_sql("l_partkey", 4), 4),
    "events": (lambda spark, sf_dir: source.column_stream(source.table(spark, sf_dir, "events"), "user_id", ["ts", "event_id"], source.pack_uint(source.hundredths(F.col("value")), 4), PACKET // 4), sql.column("events", "user_id", "ts, event_id", sql.uint("round(value * 100)", 4), PACKET // 4), 4),
    "embeddings": (source.embeddings, f"SELECT '0' AS source_id, vec_id AS packet_id, list_aggregate(list_transform(embedding, lambda x: {sql.uint('floor(x::DOUBLE * 1024 + 0.5) + 32768', 2)}), 'string_agg', '') AS h FROM embeddings", 2),
}


def _methods(width: int) -> list[tuple[str, int, DedupConfig]]:
    """(column, chunk length, configuration); 256 bytes stand for the longest Reed-Solomon code of 255, longer ones have none."""
    out = []
    for n in LENGTHS:
        out += [("exact", n, DedupConfig(n, "identity")), ("hamming", n, DedupConfig(n)), ("hamming_offset", n, DedupConfig(n, preprocess="offset", sample_width=width)), ("hamming_delta", n, DedupConfig(n, preprocess="delta", sample_width=width))]
        if n <= LONGEST_RS + 1:
            out.append(("rs", n, DedupConfig(min(n, LONGEST_RS), "rs")))
    return out


def _bases_sql(payloads: str, width: int) -> str:
    parts = []
    for method, n, cfg in _methods(width):
        counted = sql.counted(payloads, cfg.n_b, cfg.preprocess, cfg.sample_width, transform=cfg.transform)
        parts.append(f"SELECT '{method}' AS method, {n}::BIGINT AS n_b, chunks, bases FROM ({counted} SELECT chunks, bases FROM k)")
    every = ", ".join(f"max(bases) FILTER (method = '{m}') AS {m}" for m in ("exact", "hamming", "hamming_offset", "hamming_delta", "rs"))
    return f"SELECT n_b, max(chunks) FILTER (method = 'exact') AS chunks, {every} FROM ({' UNION ALL '.join(parts)}) GROUP BY n_b"


def bases_by_length(payloads, width: int):
    """A row per chunk length, a column per method, from one scan."""
    methods = _methods(width)
    names = payloads.sparkSession.createDataFrame([(i, m, n) for i, (m, n, _) in enumerate(methods)], "cfg int, method string, n_b long")
    counted = costs.counts(encode.unique_chunks(payloads, [c for *_, c in methods])).join(F.broadcast(names), "cfg")
    every = [F.max(F.when(F.col("method") == m, F.col("bases"))).alias(m) for m in ("exact", "hamming", "hamming_offset", "hamming_delta", "rs")]
    return counted.groupBy("n_b").agg(F.max(F.when(F.col("method") == "exact", F.col("chunks"))).alias("chunks"), *every)


for _name, (_load, _sql, _width) in COLUMNS.items():
    register(f"bases_by_length_{_name}", _bases_sql(_sql, _width))(lambda spark, sf_dir, load=_load, width=_width: bases_by_length(load(spark, sf_dir), width))


# --- balls of random flips: every scheme, and the codecs

#: Parity bits, and the largest parity whose chunks the codecs are shown: every one.
PARITIES = range(3, 16)
CODEC_PARITY = PARITIES[-1]


def _flips_sql(m: int) -> str:
    """``WITH`` clause up to k for a draw of each customer, 2^m to a ball: what a chunk is follows from its basis and its flipped bit alone."""
    p = HammingParams(m)
    mask, dev = 0xFF >> (8 * p.k_b - p.k), DedupConfig(p.n_b).fixed_deviation
    first = f"lpad(to_hex(('0x' || substr(h, 1, 2))::BIGINT & {mask}), 2, '0')"
    return f"""WITH f AS (SELECT {first} || substr(h, 3, {2 * min(p.k_b, 32) - 2}) AS base, flip FROM (SELECT sha256('1:' || (c_custkey // {1 << m}) || ':0') AS h, ('0x' || substr(sha256('1:flip:' || c_custkey), 1, 8))::BIGINT % {1 << m} AS flip FROM customer)),
k AS (SELECT count(*) AS chunks, count(DISTINCT (base, flip)) AS exact_bases, count(DISTINCT base) AS bases, count(*) * {dev} AS dev_sum, (count(DISTINCT (base, flip)) - count(DISTINCT base)) * {dev} AS q_dev FROM f)"""


def _synthetic_sql() -> str:
    parts = []
    for m in PARITIES:
        p = HammingParams(m)
        parts.append(f"SELECT {m}::BIGINT AS m, {p.n_b}::BIGINT AS n_b, scheme, chunks, bodies, total_bytes, ratio FROM ({_flips_sql(m)} {sql.scheme_rows(p.n_b, p.k_b, FP_SYNTH)})")
    return " UNION ALL ".join(parts)


def _drawn(spark, sf_dir, m: int):
    return synthetic.drawn(source.table(spark, sf_dir, "customer").select("c_custkey"), m)


def _balls(spark, sf_dir, m: int):
    cfg = DedupConfig(HammingParams(m).n_b, fp_algo="crc32", fp_bytes=FP_SYNTH)
    counted = costs.counts(encode.unique_chunks(_drawn(spark, sf_dir, m), [cfg]))
    return costs.study(counted, [cfg]).select(F.lit(m).cast("long").alias("m"), "n_b", "scheme", "chunks", "bodies", "total_bytes", "ratio")


def _union(parts):
    out = parts[0]
    for part in parts[1:]:
        out = out.unionByName(part)
    return out


@register("synthetic_ratio", _synthetic_sql())
def synthetic_ratio(spark, sf_dir):
    """Ratios of all schemes on balls of as many random one-bit flips as a chunk has bits, one flip for each customer: similar grows with the chunk, exact stays near 1.6."""
    return _union([_balls(spark, sf_dir, m) for m in PARITIES])


@register("synthetic_codecs")
def synthetic_codecs(spark, sf_dir):
    """DEFLATE and LZW on the same balls, for each parity, each chunk alone: random chunks only grow."""
    parts = [codec_totals(_drawn(spark, sf_dir, m), ["deflate", "lzw"], [HammingParams(m).n_b], deal=False).withColumn("m", F.lit(m).cast("long")) for m in PARITIES if m <= CODEC_PARITY]
    return _union(parts).withColumn("ratio", F.col("original_bytes") / F.col("total_bytes"))


_COLLAPSE = [DedupConfig(HammingParams(m).n_b) for m in range(3, 13)]


@register("chunk_to_basis_ratio", " UNION ALL ".join(f"SELECT {m}::BIGINT AS m, chunks, exact_bases, bases, chunks / bases::DOUBLE AS chunks_per_basis FROM ({sql.counted(sql.DOCUMENTS, HammingParams(m).n_b)} SELECT chunks, exact_bases, bases FROM k)" for m in range(3, 13)))
def chunk_to_basis_ratio(spark, sf_dir):
    """Measured on the documents, by parity bits: chunks, different ones and bases, and how many chunks share a basis."""
    counted = costs.counts(encode.unique_chunks(source.documents(spark, sf_dir), _COLLAPSE))
    return counted.select((F.col("cfg") + 3).cast("long").alias("m"), "chunks", "exact_bases", "bases", (F.col("chunks") / F.col("bases")).alias("chunks_per_basis"))


@register("unique_sweep", " UNION ALL ".join(f"SELECT {u} AS unique_per_basis, count(*) AS chunks, count(DISTINCT c_custkey // {u}) AS bases, count(DISTINCT c_custkey) * 8 + count(*) * 4 AS exact_bytes, count(DISTINCT c_custkey // {u}) * 8 + count(*) * 5 AS similar_bytes FROM customer" for u in (1, 4, 16, 64)))
def unique_sweep(spark, sf_dir):
    """A chunk for each customer, ever more of them on one basis: bytes at rest."""
    cfg, parts = DedupConfig(8, fp_bytes=4), []
    for unique in (1, 4, 16, 64):
        rows = synthetic.drawn(source.table(spark, sf_dir, "customer").select("c_custkey"), 6, unique)
        parts.append(costs.storage(costs.counts(encode.unique_chunks(rows, [cfg])), cfg).select(F.lit(unique).alias("unique_per_basis"), "chunks", "bases", "exact_bytes", "similar_bytes"))
    return _union(parts)


# --- one node, and sixteen

#: Stated, not measured: power of a node in watts and speed of its link in bits a second.
WATTS, LINK = 5.0, 1e9
MICRO = [DedupConfig(1 << i, fp_algo="crc32", fp_bytes=FP_SYNTH) for i in range(13)]
MACRO = [DedupConfig(HammingParams(m).n_b) for m in range(4, 13)]


def modelled(table):
    """Adds the modelled energy for each original bit: the link's time for what is sent, at a stated power."""
    return table.withColumn("joule_per_bit", F.col("total_bytes") * WATTS / LINK / (F.col("chunks") * F.col("n_b")))


def _modelled_sql(rows: str) -> str:
    return f"SELECT *, total_bytes::DOUBLE * {WATTS}::DOUBLE / {LINK}::DOUBLE / (chunks * n_b) AS joule_per_bit FROM ({rows})"


@register("micro_benchmark", _modelled_sql(_study_sql(sql.CONVERSATIONS, MICRO)))
def micro_benchmark(spark, sf_dir):
    """One source, chunks of 1 to 4096 bytes: what every scheme sends, and its modelled energy."""
    return modelled(study(source.conversations(spark, sf_dir), MICRO))


_MESSAGES = {"raw": "0", "exact": "exact_bases", "sim_plain": "bases", "sim_short": "bases", "sim_dual": "exact_bases"}


def _macro_sql() -> str:
    parts = []
    for cfg in MACRO:
        m = int(math.log2(8 * cfg.n_b))
        counted = sql.counted(sql.DOCUMENTS, cfg.n_b, dev=str(cfg.fixed_deviation))
        extra = " ".join(f"WHEN '{s}' THEN {e}" for s, e in _MESSAGES.items())
        parts.append(f"SELECT {m}::BIGINT AS parity_bits, {cfg.n_b}::BIGINT AS n_b, scheme, chunks, bodies, total_bytes, 2 * chunks + 2 * (CASE scheme {extra} END) AS messages FROM ({counted}, s AS ({sql.scheme_rows(cfg.n_b, cfg.basis_bytes, cfg.fp_bytes)}) SELECT s.*, exact_bases, bases FROM s CROSS JOIN k)")
    return _modelled_sql(" UNION ALL ".join(parts))


@register("macro_benchmark", _macro_sql())
def macro_benchmark(spark, sf_dir):
    """All sources into one sink, 4 to 12 parity bits: bytes and messages of every scheme, and their modelled energy."""
    counted = costs.counts(encode.unique_chunks(source.documents(spark, sf_dir), MACRO))
    names = spark.createDataFrame([(i, int(math.log2(8 * c.n_b)), c.n_b) for i, c in enumerate(MACRO)], "cfg int, parity_bits long, n_b long")
    misses = counted.join(F.broadcast(names), "cfg").select("parity_bits", "n_b", "exact_bases", "bases")
    extra = F.coalesce(*(F.when(F.col("scheme") == s, F.expr(e).cast("long")) for s, e in _MESSAGES.items()))
    rows = costs.study(counted, MACRO).join(misses, "n_b")  # a row for each configuration and scheme
    return modelled(rows.select("parity_bits", "n_b", "scheme", "chunks", "bodies", "total_bytes", (2 * F.col("chunks") + 2 * extra).alias("messages")))


def throughput(spark, sf_dir, sizes=(8, 64, 512, 4096)) -> list[dict]:
    """Measured input megabits a second of cut, split and look-up by chunk length and method; for ``bench.py``."""
    import time

    data, rows = source.documents(spark, sf_dir), []
    size = data.agg(F.sum(F.octet_length("payload"))).first()[0]
    for n_b in sizes:
        for method in ("identity", "hamming"):
            began = time.time()
            costs.counts(encode.unique_chunks(data, [DedupConfig(n_b, method)])).collect()
            rows.append({"n_b": n_b, "method": method, "mbps": round(costs.throughput_mbps(size, time.time() - began), 1)})
    return rows


# --- other Reed-Solomon codes, and a fixed length for their deviations

_MAX = DedupConfig(16, "rs", rs_length="max")


@register("rs_fixed_deviation", f"SELECT scheme, chunks, bodies, total_bytes, ratio FROM ({sql.counted(sql.DOCUMENTS, 16, dev=str(_MAX.fixed_deviation), transform='rs')} {sql.scheme_rows(16, _MAX.basis_bytes, _MAX.fp_bytes)})")
def rs_fixed_deviation(spark, sf_dir):
    """Costs where every deviation is charged the most that the code can have."""
    return study(source.documents(spark, sf_dir), [_MAX]).select("scheme", "chunks", "bodies", "total_bytes", "ratio")


@register("rs_codes")
def rs_codes(spark, sf_dir):
    """Bases and distances of the published codes with two and eight check symbols, on the conversations."""
    cfgs = [DedupConfig(n, "rs", k) for n, k in ((16, 14), (64, 56), (255, 253), (255, 247))]
    names = spark.createDataFrame([(i, c.n_b, c.basis_bytes) for i, c in enumerate(cfgs)], "cfg int, n_b long, k_b long")
    unique = encode.unique_chunks(source.conversations(spark, sf_dir), cfgs)
    far = unique.groupBy("cfg").agg(F.max(F.col("dev_bytes") / 2).cast("long").alias("farthest"))
    counted = costs.counts(unique).join(far, "cfg").join(F.broadcast(names), "cfg")  # four rows
    return counted.select("n_b", "k_b", "chunks", "exact_bases", "bases", "farthest")


# --- differences one bit wider, and what a pool's references tell

_WIDE = DedupConfig(16, "identity", preprocess="delta_wide", sample_width=2)


@register("wide_differences", f"SELECT scheme, chunks, bodies, total_bytes, ratio FROM ({sql.counted(sql.ship_dates(16), 16, transform='identity')} {sql.scheme_rows(16, _WIDE.basis_bytes, _WIDE.fp_bytes)})")
def wide_differences(spark, sf_dir):
    """Differences with a sign bit of their own make chunks longer: bodies of 17 bytes for 16."""
    return study(source.ship_dates(spark, sf_dir, 16), [_WIDE]).select("scheme", "chunks", "bodies", "total_bytes", "ratio")


@register("pool_entropy", f"WITH {sql.chunks(sql.DOCUMENTS, 8)}, {sql.hamming(8)}, r AS (SELECT source_id, word, count(*) AS n FROM w GROUP BY ALL) SELECT source_id, sum(n)::BIGINT AS chunks, count(*) AS bases, round(log2(sum(n)) - sum(n * log2(n)) / sum(n), 6) AS entropy_bits FROM r GROUP BY source_id")
def pool_entropy(spark, sf_dir):
    """Bits that naming a basis needs at least, by source: the entropy of how often each is referred to."""
    from basisflow.functions.statistics import entropy_bits

    unique = encode.unique_chunks(source.documents(spark, sf_dir), [DedupConfig(8)], by_source=True)
    refs = unique.groupBy("source_id", "basis_key").agg(F.sum("n").alias("n"))
    return refs.groupBy("source_id").agg(F.sum("n").alias("chunks"), F.count("*").alias("bases"), F.round(entropy_bits(F.col("n")), 6).alias("entropy_bits"))
