"""Relational operations around the pools: joins, windows, set operations, reports."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from basisflow.config import DedupConfig
from basisflow.functions.hamming import with_codeword
from basisflow.operators import encode
from basisflow.plans import sql
from basisflow.plans.registry import register
from basisflow.sources import payloads as source


def _records(spark, sf_dir):
    """Distinct chunks of the 4-byte records with their bases as numbers, by source."""
    rows = source.records4(spark, sf_dir).groupBy("source_id", F.col("payload").alias("chunk")).agg(F.count("*").alias("n"))
    return with_codeword(rows, 4).withColumn("word", F.conv(F.hex("codeword"), 16, 10).cast("long"))


_W = f"WITH {sql.chunks(sql.RECORDS4, 4)}, {sql.hamming(4)}, r AS (SELECT source_id, x, (word << 1)::BIGINT AS word, count(*) AS n FROM w GROUP BY ALL)"


def _half(spark, sf_dir, side):
    """Bases of the even or of the odd sources."""
    return _records(spark, sf_dir).where(F.col("source_id").cast("int") % 2 == side).select("word").distinct()


@register("pool_semi_join", f"{_W} SELECT count(*) AS known, sum(n)::BIGINT AS chunks FROM r WHERE source_id::INT % 2 = 1 AND word IN (SELECT word FROM r WHERE source_id::INT % 2 = 0)")
def pool_semi_join(spark, sf_dir):
    rows = _records(spark, sf_dir).where(F.col("source_id").cast("int") % 2 == 1)
    return rows.join(_half(spark, sf_dir, 0), "word", "left_semi").agg(F.count("*").alias("known"), F.sum("n").alias("chunks"))


@register("pool_anti_join", f"{_W} SELECT count(DISTINCT word) AS missing FROM r WHERE source_id::INT % 2 = 1 AND word NOT IN (SELECT word FROM r WHERE source_id::INT % 2 = 0)")
def pool_anti_join(spark, sf_dir):
    return _half(spark, sf_dir, 1).join(_half(spark, sf_dir, 0), "word", "left_anti").agg(F.count("*").alias("missing"))


@register("pool_outer_reconcile", f"{_W}, a AS (SELECT DISTINCT word FROM r WHERE source_id::INT % 2 = 0), b AS (SELECT DISTINCT word FROM r WHERE source_id::INT % 2 = 1) SELECT CASE WHEN b.word IS NULL THEN 'first' WHEN a.word IS NULL THEN 'second' ELSE 'both' END AS held_by, count(*) AS bases FROM a FULL JOIN b ON a.word = b.word GROUP BY 1")
def pool_outer_reconcile(spark, sf_dir):
    a, b = _half(spark, sf_dir, 0).withColumn("a", F.lit(True)), _half(spark, sf_dir, 1).withColumn("b", F.lit(True))
    held = F.when(F.col("b").isNull(), "first").when(F.col("a").isNull(), "second").otherwise("both").alias("held_by")
    return a.join(b, "word", "full_outer").groupBy(held).agg(F.count("*").alias("bases"))


@register("pool_set_operations", f"{_W}, a AS (SELECT DISTINCT word FROM r WHERE source_id::INT % 2 = 0), b AS (SELECT DISTINCT word FROM r WHERE source_id::INT % 2 = 1) SELECT (SELECT count(*) FROM (SELECT * FROM a INTERSECT SELECT * FROM b)) AS common, (SELECT count(*) FROM (SELECT * FROM a EXCEPT SELECT * FROM b)) AS only_first, (SELECT count(*) FROM (SELECT * FROM a UNION SELECT * FROM b)) AS either")
def pool_set_operations(spark, sf_dir):
    a, b = _half(spark, sf_dir, 0), _half(spark, sf_dir, 1)
    count = lambda df, name: df.agg(F.count("*").alias(name))
    both = count(a.intersect(b), "common").crossJoin(F.broadcast(count(a.exceptAll(b), "only_first")))
    return both.crossJoin(F.broadcast(count(a.union(b).distinct(), "either")))  # one row each


@register("report_rollup", f"{_W} SELECT source_id, (word >> 24) % 256 AS share, sum(n)::BIGINT AS chunks, count(*) AS unique_chunks FROM r GROUP BY ROLLUP (source_id, share)")
def report_rollup(spark, sf_dir):
    rows = _records(spark, sf_dir).withColumn("share", F.shiftright("word", 24) % 256)
    return rows.rollup("source_id", "share").agg(F.sum("n").alias("chunks"), F.count("*").alias("unique_chunks"))


@register("report_cube", "SELECT l_returnflag AS flag, l_linestatus AS status, count(*) AS records FROM lineitem GROUP BY CUBE (flag, status)")
def report_cube(spark, sf_dir):
    rows = source.table(spark, sf_dir, "lineitem").select(F.col("l_returnflag").alias("flag"), F.col("l_linestatus").alias("status"))
    return rows.cube("flag", "status").agg(F.count("*").alias("records"))


@register("report_grouping_sets", "SELECT source, lang, count(*) AS packets, sum(octet_length(encode(text)))::BIGINT AS bytes FROM documents GROUP BY GROUPING SETS ((source), (lang), ())")
def report_grouping_sets(spark, sf_dir):
    rows = source.table(spark, sf_dir, "documents").select("source", "lang", F.octet_length("text").alias("size"))
    return rows.groupingSets([["source"], ["lang"], []], "source", "lang").agg(F.count("*").alias("packets"), F.sum("size").cast("long").alias("bytes"))


@register("window_moving_traffic", "WITH d AS (SELECT ts::DATE AS day, user_id, count(*) AS packets FROM events GROUP BY 1, 2) SELECT day::VARCHAR AS day, user_id, packets, sum(packets) OVER (PARTITION BY user_id ORDER BY day ROWS 2 PRECEDING)::BIGINT AS three_days, packets - coalesce(lag(packets) OVER (PARTITION BY user_id ORDER BY day), 0) AS change, row_number() OVER (PARTITION BY user_id ORDER BY packets DESC, day) AS place FROM d")
def window_moving_traffic(spark, sf_dir):
    days = source.table(spark, sf_dir, "events").groupBy(F.to_date("ts").alias("day"), "user_id").agg(F.count("*").alias("packets"))
    by = Window.partitionBy("user_id").orderBy("day")
    return days.select(F.col("day").cast("string").alias("day"), "user_id", "packets", F.sum("packets").over(by.rowsBetween(-2, 0)).alias("three_days"), (F.col("packets") - F.coalesce(F.lag("packets").over(by), F.lit(0))).alias("change"), F.row_number().over(Window.partitionBy("user_id").orderBy(F.desc("packets"), "day")).cast("long").alias("place"))


@register("as_of_reading", "SELECT p.event_id, r.value AS reading FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT user_id, ts, value FROM events WHERE event_type = 'view') r ON p.user_id = r.user_id AND p.ts >= r.ts")
def as_of_reading(spark, sf_dir):
    """For every purchase, the value of the user's last view at or before it: one sort by user, no range join."""
    rows = source.table(spark, sf_dir, "events").where(F.col("event_type").isin("view", "purchase"))
    # at equal times a view comes before the purchase that may use it
    by = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "view", 0).otherwise(1), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    reading = F.last(F.when(F.col("event_type") == "view", F.col("value")), ignorenulls=True).over(by)
    return rows.select("event_id", "event_type", reading.alias("reading")).where(F.col("event_type") == "purchase").select("event_id", "reading")


@register("range_join_samples", "SELECT p.event_id, count(r.event_id) AS samples FROM (SELECT * FROM events WHERE event_type = 'signup') p LEFT JOIN (SELECT * FROM events WHERE event_type = 'error') r ON p.user_id = r.user_id AND r.ts >= p.ts - INTERVAL 6 HOUR AND r.ts < p.ts GROUP BY p.event_id")
def range_join_samples(spark, sf_dir):
    """Errors of a user in the six hours before each signup: equality on user and time bucket, then the exact bounds."""
    events, hours6 = source.table(spark, sf_dir, "events"), 6 * 3600 * 1_000_000
    micros = F.unix_micros(F.col("ts").cast("timestamp"))
    bucket = F.floor(micros / hours6)
    signups = events.where(F.col("event_type") == "signup").select("event_id", "user_id", micros.alias("t"), F.explode(F.array(bucket - 1, bucket)).alias("bucket"))
    errors = events.where(F.col("event_type") == "error").select("user_id", micros.alias("s"), bucket.alias("bucket"))
    near = signups.join(errors, ["user_id", "bucket"], "left")
    inside = (F.col("s") >= F.col("t") - hours6) & (F.col("s") < F.col("t"))
    return near.groupBy("event_id").agg(F.count(F.when(inside, 1)).alias("samples"))


@register("json_fields", "SELECT event_type, (props::JSON->>'k')::BIGINT % 10 AS k, count(*) AS events FROM events GROUP BY 1, 2")
def json_fields(spark, sf_dir):
    rows = source.table(spark, sf_dir, "events").select("event_type", (F.from_json("props", "k long")["k"] % 10).alias("k"))
    return rows.groupBy("event_type", "k").agg(F.count("*").alias("events"))


@register("column_split", "SELECT count(*) AS chunks, count(DISTINCT (p_brand, p_type)) AS bases, count(DISTINCT (p_brand, p_type, p_size)) AS unique_chunks FROM part")
def column_split(spark, sf_dir):
    """A record cut by columns into a large shared part and a small private one."""
    rows = source.table(spark, sf_dir, "part").groupBy("p_brand", "p_type", "p_size").agg(F.count("*").alias("n"))
    bases = rows.groupBy("p_brand", "p_type").agg(F.sum("n").alias("n"), F.count("*").alias("u"))
    return bases.agg(F.sum("n").alias("chunks"), F.count("*").alias("bases"), F.sum("u").alias("unique_chunks"))


@register("overlay_merge", "SELECT count(*) AS packets, count(DISTINCT text) AS sent FROM documents")
def overlay_merge(spark, sf_dir):
    """Equal payloads, named by digest, travel once."""
    rows = source.table(spark, sf_dir, "documents").groupBy(F.sha2("text", 256).alias("id")).agg(F.count("*").alias("n"))
    return rows.agg(F.sum("n").alias("packets"), F.count("*").alias("sent"))


@register("approximate_bases")
def approximate_bases(spark, sf_dir):
    """Planning figures: distinct chunks and bases by mergeable sketches."""
    rows = with_codeword(encode.chunk_payloads(source.documents(spark, sf_dir), 8), 8)
    return rows.agg(F.count("*").alias("chunks"), F.hll_sketch_estimate(F.hll_sketch_agg("chunk", F.lit(14))).alias("exact_bases"), F.hll_sketch_estimate(F.hll_sketch_agg("codeword", F.lit(14))).alias("bases"))


@register("approximate_sharing")
def approximate_sharing(spark, sf_dir):
    """Planning figures: bases that two halves of the sources share, by theta sketches."""
    rows = with_codeword(encode.chunk_payloads(source.documents(spark, sf_dir), 8), 8)
    half = F.crc32(F.col("source_id").cast("binary")) % 2
    sketches = rows.agg(*(F.theta_sketch_agg(F.when(half == side, F.hex("codeword")), F.lit(14)).alias(f"s{side}") for side in (0, 1)))
    estimate = F.theta_sketch_estimate
    return sketches.select(estimate("s0").alias("first"), estimate("s1").alias("second"), estimate(F.theta_intersection("s0", "s1")).alias("shared"), estimate(F.theta_union("s0", "s1")).alias("either"))


_CANDIDATES = [DedupConfig(n, t, preprocess=p) for n in (4, 8, 16) for t in ("identity", "hamming") for p in ("none", "offset")]


def _candidates_sql() -> str:
    parts = []
    for c in _CANDIDATES:
        counted = sql.counted(sql.RECORDS8, c.n_b, c.preprocess, dev=str(c.fixed_deviation), transform=c.transform)
        parts.append(f"SELECT {c.n_b} AS n_b, '{c.transform}' AS transform, '{c.preprocess}' AS preprocess, chunks, bases, chunks * {c.n_b} / (bases * {c.n_b} + chunks * 6 + q_dev)::DOUBLE AS ratio FROM ({counted} SELECT * FROM k)")
    return " UNION ALL ".join(parts)


@register("choose_transform", _candidates_sql())
def choose_transform(spark, sf_dir):
    """Extension: every candidate's ratio under the dual scheme in one scan, best first."""
    from basisflow.operators import costs

    names = spark.createDataFrame([(i, c.n_b, c.transform, c.preprocess) for i, c in enumerate(_CANDIDATES)], "cfg int, n_b int, transform string, preprocess string")
    counted = costs.counts(encode.unique_chunks(source.records8(spark, sf_dir), _CANDIDATES)).join(F.broadcast(names), "cfg")
    h = 6
    ratio = F.col("chunks") * F.col("n_b") / (F.col("bases") * F.col("n_b") + F.col("chunks") * h + F.col("q_dev"))
    return counted.select("n_b", "transform", "preprocess", "chunks", "bases", ratio.alias("ratio")).orderBy(F.desc("ratio"), "n_b", "transform", "preprocess")
