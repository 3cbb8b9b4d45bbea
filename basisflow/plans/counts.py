"""Chunks, bases and deviations on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from basisflow.config import HammingParams, PUBLISHED_RADIUS, DedupConfig, chunks_per_basis, covering_radius, rs_deviation_bits
from basisflow.functions import hamming
from basisflow.operators import costs, encode
from basisflow.plans import sql
from basisflow.plans.registry import register
from basisflow.sources import payloads as source


def count_row(payloads: DataFrame, cfg: DedupConfig) -> DataFrame:
    return costs.counts(encode.unique_chunks(payloads, [cfg])).select("chunks", "exact_bases", "bases")


#: name: (payloads, their SQL, configuration)
_COUNTS = {
    "basis_count_documents_4": (source.documents, sql.DOCUMENTS, DedupConfig(4)),
    "basis_count_documents_8": (source.documents, sql.DOCUMENTS, DedupConfig(8)),
    "basis_count_documents_16": (source.documents, sql.DOCUMENTS, DedupConfig(16)),
    "basis_count_pages_4": (source.pages, sql.PAGES, DedupConfig(4)),
    "basis_count_conversations_8": (source.conversations, sql.CONVERSATIONS, DedupConfig(8)),
    "basis_count_records_4": (source.records4, sql.RECORDS4, DedupConfig(4)),
    "basis_count_records_8": (source.records8, sql.RECORDS8, DedupConfig(8)),
    "offset_basis_documents_4": (source.documents, sql.DOCUMENTS, DedupConfig(4, preprocess="offset")),
    "offset_basis_records_4": (source.records4, sql.RECORDS4, DedupConfig(4, preprocess="offset")),
    "offset_basis_shipdate": (lambda s, d: source.ship_dates(s, d, 8), sql.ship_dates(8), DedupConfig(8, preprocess="offset", sample_width=2)),
    "delta_basis_shipdate": (lambda s, d: source.ship_dates(s, d, 8), sql.ship_dates(8), DedupConfig(8, preprocess="delta", sample_width=2)),
    "rs_basis_documents_16": (source.documents, sql.DOCUMENTS, DedupConfig(16, "rs")),
}
_COUNTS["basis_count_readings_16"] = (source.readings, "SELECT user_id::VARCHAR AS source_id, event_id AS packet_id, lpad(upper(to_hex(user_id::BIGINT)), 16, '0') || hex(value::DOUBLE::BIT::BLOB) AS h FROM events", DedupConfig(16))
for _name, (_load, _sql, _cfg) in _COUNTS.items():
    _oracle = sql.counted(_sql, _cfg.n_b, _cfg.preprocess, _cfg.sample_width, transform=_cfg.transform) + " SELECT chunks, exact_bases, bases FROM k"
    register(_name, _oracle)(lambda spark, sf_dir, load=_load, cfg=_cfg: count_row(load(spark, sf_dir), cfg))


@register("chunk_inventory", " UNION ALL ".join(f"SELECT '{n}' AS stream, {b}::BIGINT AS n_b, count(*) AS packets, sum(length(h) // 2)::BIGINT AS payload_bytes, sum((length(h) + {2 * b - 1}) // {2 * b})::BIGINT AS chunks FROM ({q})" for n, q in (("documents", sql.DOCUMENTS), ("pages", sql.PAGES), ("conversations", sql.CONVERSATIONS)) for b in (4, 64)))
def chunk_inventory(spark, sf_dir):
    """Packets, bytes and chunks of every stream; lengths alone are read."""
    out = None
    for name, load in (("documents", source.documents), ("pages", source.pages), ("conversations", source.conversations)):
        size = F.octet_length("payload")
        for n_b in (4, 64):
            part = load(spark, sf_dir).agg(F.lit(name).alias("stream"), F.lit(n_b).cast("long").alias("n_b"), F.count("*").alias("packets"), F.sum(size).cast("long").alias("payload_bytes"), F.sum(F.ceil(size / n_b)).cast("long").alias("chunks"))
            out = part if out is None else out.unionByName(part)
    return out


@register("basis_counts_native_8", sql.counted(sql.DOCUMENTS, 8) + " SELECT chunks, exact_bases, bases FROM k")
def basis_counts_native_8(spark, sf_dir):
    """The same counts in plain columns: no Python on the way."""
    rows = hamming.with_codeword(encode.chunk_payloads(source.documents(spark, sf_dir), 8), 8)
    unique = rows.groupBy("chunk").agg(F.count("*").alias("n"), F.first("codeword").alias("codeword"))
    bases = unique.groupBy("codeword").agg(F.count("*").alias("u"), F.sum("n").alias("n"))
    return bases.agg(F.sum("n").alias("chunks"), F.sum("u").alias("exact_bases"), F.count("*").alias("bases"))


@register("syndrome_histogram", f"WITH {sql.chunks(sql.DOCUMENTS, 8)}, {sql.hamming(8)} SELECT syn AS syndrome, spare, count(*) AS chunks FROM w GROUP BY syn, spare")
def syndrome_histogram(spark, sf_dir):
    rows = hamming.with_codeword(encode.chunk_payloads(source.documents(spark, sf_dir), 8), 8)
    return rows.groupBy(F.col("syndrome").cast("long").alias("syndrome"), F.col("spare").cast("long").alias("spare")).agg(F.count("*").alias("chunks"))


@register("spare_bit_split", f"WITH {sql.chunks(sql.PAGES, 4)}, {sql.hamming(4)} SELECT spare, count(*) AS chunks, count(DISTINCT word) AS bases FROM w GROUP BY spare")
def spare_bit_split(spark, sf_dir):
    rows = hamming.with_codeword(encode.chunk_payloads(source.pages(spark, sf_dir), 4), 4)
    by_word = rows.groupBy(F.col("spare").cast("long").alias("spare"), "codeword").agg(F.count("*").alias("n"))
    return by_word.groupBy("spare").agg(F.sum("n").alias("chunks"), F.count("*").alias("bases"))


@register("chunks_per_basis", f"WITH {sql.chunks(sql.DOCUMENTS, 8)}, {sql.hamming(8)} SELECT unique_chunks, count(*) AS bases FROM (SELECT word, count(DISTINCT x) AS unique_chunks FROM w GROUP BY word) GROUP BY unique_chunks")
def chunks_per_basis_query(spark, sf_dir):
    return costs.chunks_per_basis(encode.unique_chunks(source.documents(spark, sf_dir), [DedupConfig(8)]))


@register("hot_bases_topk", f"WITH {sql.chunks(sql.RECORDS4, 4)}, {sql.hamming(4)} SELECT (word << 1)::BIGINT AS word, count(*) AS refs, count(DISTINCT x) AS unique_chunks FROM w GROUP BY word ORDER BY refs DESC, word LIMIT 20")
def hot_bases_topk(spark, sf_dir):
    """The heaviest bases of the records; top-k is the feature."""
    unique = encode.unique_chunks(source.records4(spark, sf_dir), [DedupConfig(4)])
    word = F.conv(F.hex("basis_key"), 16, 10).cast("long").alias("word")
    return unique.groupBy(word).agg(F.sum("n").alias("refs"), F.count("*").alias("unique_chunks")).orderBy(F.desc("refs"), "word").limit(20)


@register("rs_distances", f"WITH {sql.chunks(sql.DOCUMENTS, 16)}, {sql.rs2(16)} SELECT errs::BIGINT AS distance, count(*) AS unique_chunks FROM (SELECT x, first(errs) AS errs FROM w GROUP BY x) GROUP BY errs")
def rs_distances(spark, sf_dir):
    """How far chunks lie from their error-free words: never beyond the radius."""
    unique = encode.unique_chunks(source.documents(spark, sf_dir), [DedupConfig(16, "rs")])
    return unique.groupBy((F.col("dev_bytes") / 2).cast("long").alias("distance")).agg(F.count("*").alias("unique_chunks"))


def stream_chunks(payloads: DataFrame, lengths) -> DataFrame:
    """(n, chunks): how many chunks of each length a stream has; lengths of payloads alone are needed."""
    rows = F.explode(F.array(*(F.struct(F.lit(n).cast("long").alias("n"), F.ceil(F.octet_length("payload") / n).alias("c")) for n in lengths))).alias("r")
    return payloads.select(rows).groupBy(F.col("r.n").alias("n")).agg(F.sum("r.c").cast("long").alias("chunks"))


def _chunks_of(text: str, table: str, n: str) -> str:
    return f"(SELECT sum((octet_length(encode({text})) + {n} - 1) // {n})::BIGINT FROM {table})"


@register("hamming_table", f"SELECT *, chunks * dev_bytes AS dev_total FROM (SELECT m, (2 ** m / 8)::BIGINT AS n_b, (2 ** m - 1 - m)::BIGINT AS k, ceil((2 ** m - 1 - m) / 8)::BIGINT AS k_b, m + 1 AS dev_bits, ceil((m + 1) / 8)::BIGINT AS dev_bytes, (2 ** m)::BIGINT AS chunks_per_basis, chunks FROM ({' UNION ALL '.join(f'SELECT {m} AS m, {_chunks_of("text", "documents", str((1 << m) // 8))} AS chunks' for m in range(3, 16))}))")
def hamming_table(spark, sf_dir):
    """Codes by parity bits, and what the documents take of each: chunks, and bytes of their deviations."""
    rows = [(m, p.n_b, p.k, p.k_b, p.deviation_bits, p.deviation_bytes, chunks_per_basis(m)) for m in range(3, 16) for p in [HammingParams(m)]]
    codes = spark.createDataFrame(rows, "m long, n_b long, k long, k_b long, dev_bits long, dev_bytes long, chunks_per_basis long")
    measured = stream_chunks(source.documents(spark, sf_dir), [r[1] for r in rows])
    return measured.join(F.broadcast(codes), F.col("n") == F.col("n_b")).drop("n").withColumn("dev_total", F.col("chunks") * F.col("dev_bytes"))


@register("rs_radius_table", f"SELECT n_b, k_b, radius, n_b - k_b AS bound, (radius * ceil(log2(n_b)) + radius * 8)::BIGINT AS dev_bits, CASE n_b {' '.join(f'WHEN {n} THEN {_chunks_of("html", "pages", str(n))}' for n in (16, 64, 255))} END AS chunks FROM (VALUES (16, 14, 2), (255, 253, 2), (255, 247, 8), (64, 56, 11)) t(n_b, k_b, radius)")
def rs_radius_table(spark, sf_dir):
    """Radii of the published codes, and the chunks that the pages make for each."""
    rows = [(n, k, r, covering_radius(n, k), rs_deviation_bits(n, r)) for (n, k), r in PUBLISHED_RADIUS.items()]
    codes = spark.createDataFrame(rows, "n_b int, k_b int, radius int, bound int, dev_bits long")
    measured = stream_chunks(source.pages(spark, sf_dir), sorted({r[0] for r in rows}))
    return measured.join(F.broadcast(codes), F.col("n") == F.col("n_b")).drop("n")


def _table_rows(stream: str, n_bs, width: int = 1):
    cfgs = []
    for n_b in n_bs:
        cfgs += [("identity", n_b, DedupConfig(n_b, "identity")), ("hamming", n_b, DedupConfig(n_b)), ("hamming_offset", n_b, DedupConfig(n_b, preprocess="offset", sample_width=width))]
        if 2 < n_b < 256:
            cfgs.append(("rs", n_b, DedupConfig(n_b, "rs")))
    return cfgs


def basis_table(payloads: DataFrame, cfgs) -> DataFrame:
    """A row per chunk length, a column per transform, from one scan."""
    spark = payloads.sparkSession
    names = spark.createDataFrame([(i, t, n) for i, (t, n, _) in enumerate(cfgs)], "cfg int, transform string, n_b long")
    counted = costs.counts(encode.unique_chunks(payloads, [c for *_, c in cfgs])).join(F.broadcast(names), "cfg")
    return counted.groupBy("n_b").pivot("transform", ["identity", "hamming", "hamming_offset", "rs"]).agg(F.first("bases"))


def _basis_table_sql(payloads: str, n_bs) -> str:
    parts = []
    for n_b in n_bs:
        base = f"WITH {sql.chunks(payloads, n_b)}, c2 AS (SELECT * FROM c), "
        ham = f"(SELECT bases FROM ({sql.counted(payloads, n_b)} SELECT bases FROM k))"
        off = f"(SELECT bases FROM ({sql.counted(payloads, n_b, 'offset')} SELECT bases FROM k))"
        rs = f"(SELECT bases FROM ({sql.counted(payloads, n_b, transform='rs')} SELECT bases FROM k))" if n_b > 2 else "NULL"
        parts.append(f"SELECT {n_b}::BIGINT AS n_b, (SELECT exact_bases FROM ({sql.counted(payloads, n_b)} SELECT exact_bases FROM k)) AS identity, {ham} AS hamming, {off} AS hamming_offset, {rs} AS rs")
    return " UNION ALL ".join(parts)


@register("basis_table_records", _basis_table_sql(sql.RECORDS8, (4, 8)))
def basis_table_records(spark, sf_dir):
    return basis_table(source.records8(spark, sf_dir), _table_rows("records8", (4, 8)))


@register("basis_table_shipdate", _basis_table_sql(sql.ship_dates(32), (4, 8, 16)))
def basis_table_shipdate(spark, sf_dir):
    """The column-wise study: one rising column per source, several chunk lengths, four transforms."""
    return basis_table(source.ship_dates(spark, sf_dir, 32), _table_rows("shipdate", (4, 8, 16)))


_EVENTS3 = sql.column("events", "user_id", "ts, event_id", sql.uint("round(value * 100)", 3), 64)


@register("basis_table_events", _basis_table_sql(_EVENTS3, (4, 8, 16, 32, 64)))
def basis_table_events(spark, sf_dir):
    return basis_table(source.event_values(spark, sf_dir, 192), _table_rows("events", (4, 8, 16, 32, 64)))
