"""Registered queries of the training-data operators, with SQL where it can say them."""

from __future__ import annotations

from . import cotrain, decontam, langid, lengths, merkle, packing, secrets, simhash, suffixes, warc
from .common import table, written

QUERIES = {}
ORACLE_SQL: dict[str, str] = {}


def op1_secret_scan(spark, sf_dir):
    return secrets.scan(table(spark, sf_dir, "documents"))


QUERIES["op1_secret_scan"] = op1_secret_scan


def _kind_sql(rule) -> str:
    """Spans of one kind: gaps and matches alternate, so running sums give positions."""
    pattern = rule.pattern.replace("'", "''")
    return f"""
    SELECT doc_id, '{rule.kind}' AS kind, {secrets.RULES.index(rule)} AS rank, i,
           list_sum(list_transform(p[1:i], lambda x: length(x)))::BIGINT + coalesce(list_sum(list_transform(m[1:i-1], lambda x: length(x))), 0)::BIGINT AS s,
           length(m[i]) AS n, length(g[i]) AS checked, {rule.least} AS least
    FROM (SELECT doc_id, string_split_regex(t, '{pattern}') AS p, regexp_extract_all(t, '{pattern}') AS m, regexp_extract_all(t, '{pattern}', {rule.group}) AS g FROM d)
    CROSS JOIN LATERAL (SELECT unnest(range(1, len(m) + 1)) AS i)"""


ORACLE_SQL["op1_secret_scan"] = f"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
found AS ({" UNION ALL ".join(_kind_sql(r) for r in secrets.RULES)}),
kept AS (SELECT doc_id, kind, rank, s, kind || ':' || s || ':' || (s + n) AS span FROM found WHERE checked >= least),
per AS (
  SELECT doc_id, count(*) FILTER (kind = 'assign') AS n_assign, count(*) FILTER (kind = 'access') AS n_access, count(*) FILTER (kind = 'hex') AS n_hex,
         string_agg(span, ',' ORDER BY s, rank) FILTER (rank < 3) AS base, string_agg(span, ',' ORDER BY s, rank) AS spans
  FROM kept GROUP BY doc_id)
SELECT d.doc_id, coalesce(n_assign, 0) AS n_assign, coalesce(n_access, 0) AS n_access, coalesce(n_hex, 0) AS n_hex,
       sha256(coalesce(base, '')) AS base_sha256, coalesce(spans, '') AS spans
FROM d LEFT JOIN per USING (doc_id)"""


def op8_simhash_groups(spark, sf_dir):
    return simhash.near_groups(table(spark, sf_dir, "documents"))


QUERIES["op8_simhash_groups"] = op8_simhash_groups


def op3_length_histogram(spark, sf_dir):
    return lengths.histogram(lengths.document_lengths(table(spark, sf_dir, "documents")))


def op5_curve_packing(spark, sf_dir):
    return packing.pack(table(spark, sf_dir, "documents"))


QUERIES["op3_length_histogram"] = op3_length_histogram
QUERIES["op5_curve_packing"] = op5_curve_packing


def op9_language_id(spark, sf_dir):
    return langid.identify(table(spark, sf_dir, "documents"))


QUERIES["op9_language_id"] = op9_language_id


def op2_warc_round_trip(spark, sf_dir):
    return warc.round_trip(table(spark, sf_dir, "pages"))


QUERIES["op2_warc_round_trip"] = op2_warc_round_trip
ORACLE_SQL["op2_warc_round_trip"] = f"""
WITH p AS (SELECT page_id, coalesce(html, '') AS h FROM pages),
d AS (SELECT page_id, octet_length(encode(h)) AS payload_bytes, sha256(h) AS payload_digest FROM p),
f AS (SELECT *, min(page_id) OVER (PARTITION BY payload_digest) AS first FROM d)
SELECT page_id, payload_bytes, payload_digest,
       CASE WHEN payload_bytes >= {warc.LEAST} AND page_id <> first THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN payload_bytes >= {warc.LEAST} AND page_id <> first THEN first END AS refers_to
FROM f"""


def op6_merkle_fingerprints(spark, sf_dir):
    return merkle.edited_neighbours(table(spark, sf_dir, "documents"))


QUERIES["op6_merkle_fingerprints"] = op6_merkle_fingerprints


def op4_benchmark_leaks(spark, sf_dir):
    return decontam.leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


QUERIES["op4_benchmark_leaks"] = op4_benchmark_leaks


def op10_quality_cotraining(spark, sf_dir):
    return cotrain.classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


QUERIES["op10_quality_cotraining"] = op10_quality_cotraining


def op7_suffix_dedup(spark, sf_dir):
    return suffixes.removed(table(spark, sf_dir, "documents"))


QUERIES["op7_suffix_dedup"] = op7_suffix_dedup


def repeat_groups(spark, sf_dir):
    """The maximal repeats themselves, a row for each occurrence."""
    return suffixes.repeat_groups(table(spark, sf_dir, "documents"))


def context_limits(spark, sf_dir):
    """Documents that common context limits cut, and the tokens that are left."""
    histogram = lengths.histogram(lengths.document_lengths(table(spark, sf_dir, "documents")))
    return lengths.limits(written(histogram, "histogram"), [1 << i for i in range(7, 18)])


def language_spans(spark, sf_dir):
    """Languages of every text, stretch by stretch."""
    docs = table(spark, sf_dir, "documents")
    return langid.label_spans(docs, langid.train(langid.training_rows(docs)))


QUERIES |= {"repeat_groups": repeat_groups, "context_limits": context_limits, "language_spans": language_spans}
