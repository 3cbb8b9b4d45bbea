"""Hops, legality, poisoned fingerprints, the live stream and the measures around a deployment."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from basisflow.config import DedupConfig
from basisflow.operators import encode, pool, protocol, schemes
from basisflow.plans import sql
from basisflow.plans.registry import register
from basisflow.plans.schemes import _EVENT
from basisflow.sources import payloads as source
from basisflow.streaming import pool as live

_C8 = DedupConfig(8)
_HOPS = """(VALUES (1, 'repeat', 'data', 'up', 8, 0), (1, 'new_chunk', 'data', 'up', 8, 0), (1, 'new_basis', 'data', 'up', 8, 0), (1, 'repeat', 'ack', 'down', 0, 0), (1, 'new_chunk', 'ack', 'down', 0, 0), (1, 'new_basis', 'ack', 'down', 0, 0),
 (2, 'repeat', 'similar', 'up', 7, 0), (2, 'new_chunk', 'similar', 'up', 7, 0), (2, 'new_basis', 'similar', 'up', 7, 0), (2, 'new_basis', 'new_fp', 'down', 0, 0), (2, 'new_basis', 'similar_data', 'up', 8, 0), (2, 'repeat', 'ack', 'down', 0, 0), (2, 'new_chunk', 'ack', 'down', 0, 0), (2, 'new_basis', 'ack', 'down', 0, 0)) t(hop, outcome, msg_type, direction, size, z)"""


@register("traffic_by_hop", sql.outcomes(sql.CONVERSATIONS, 8) + f" SELECT hop, msg_type, count(*) AS messages, sum(size)::BIGINT AS bytes FROM o JOIN {_HOPS} ON o.outcome = t.outcome GROUP BY hop, msg_type")
def traffic_by_hop(spark, sf_dir):
    """A device, a gateway and a server: messages and bytes of each hop."""
    log = protocol.relay(encode.encode_payloads(source.conversations(spark, sf_dir), _C8), _C8, protocol.three_nodes())
    return log.groupBy("hop", "msg_type").agg(F.count("*").alias("messages"), F.sum("bytes").alias("bytes"))


_STEPS = """(VALUES ('repeat', 1, 1, 'device', 'gateway', 'data'), ('repeat', 1, 2, 'gateway', 'device', 'ack'), ('repeat', 2, 1, 'gateway', 'server', 'similar'), ('repeat', 2, 2, 'server', 'gateway', 'ack'),
 ('new_chunk', 1, 1, 'device', 'gateway', 'data'), ('new_chunk', 1, 2, 'gateway', 'device', 'ack'), ('new_chunk', 2, 1, 'gateway', 'server', 'similar'), ('new_chunk', 2, 2, 'server', 'gateway', 'ack'),
 ('new_basis', 1, 1, 'device', 'gateway', 'data'), ('new_basis', 1, 2, 'gateway', 'device', 'ack'), ('new_basis', 2, 1, 'gateway', 'server', 'similar'), ('new_basis', 2, 2, 'server', 'gateway', 'new_fp'), ('new_basis', 2, 3, 'gateway', 'server', 'similar_data'), ('new_basis', 2, 4, 'server', 'gateway', 'ack')) t(outcome, hop, step, from_node, to_node, msg_type)"""


@register("three_node_trace", sql.outcomes(sql.CONVERSATIONS, 8) + f" SELECT packet_id, chunk_seq, hop, step, from_node, to_node, msg_type FROM o JOIN {_STEPS} ON o.outcome = t.outcome")
def three_node_trace(spark, sf_dir):
    """What every chunk of the conversations causes on its way, message by message."""
    log = protocol.relay(encode.encode_payloads(source.conversations(spark, sf_dir), _C8), _C8, protocol.three_nodes())
    return log.select("packet_id", "chunk_seq", "hop", "step", "from_node", "to_node", "msg_type")


@register("illegal_messages", "SELECT from_node, msg_type, count(*) AS messages FROM (SELECT CASE user_id % 2 WHEN 0 THEN 'device' ELSE 'gateway' END AS from_node, ['data', 'exact', 'similar', 'ack'][event_id % 4 + 1] AS msg_type FROM events) WHERE (from_node, msg_type) NOT IN (('device', 'data'), ('device', 'ack'), ('gateway', 'similar'), ('gateway', 'ack')) GROUP BY ALL")
def illegal_messages(spark, sf_dir):
    """Events as messages, dealt over two nodes by user and over kinds by number: those that the sender's class may not send, by node and kind."""
    kinds = F.array(*map(F.lit, ("data", "exact", "similar", "ack")))
    sender = F.when(F.col("user_id") % 2 == 0, "device").otherwise("gateway")
    log = source.table(spark, sf_dir, "events").select(sender.alias("from_node"), F.get(kinds, (F.col("event_id") % 4).cast("int")).alias("msg_type"))
    found = protocol.illegal_messages(log, protocol.topology(spark, protocol.three_nodes()))
    return found.groupBy("from_node", "msg_type").agg(F.count("*").alias("messages"))


_BAD = "('0x' || substr(sha256(unhex(x)), 1, 8))::BIGINT < 42949672"


@register("poison_rejected", f"WITH {sql.chunks(sql.DOCUMENTS, 64)} SELECT source_id, count(*) AS sent, count(*) FILTER ({_BAD}) AS rejected FROM c GROUP BY source_id HAVING count(*) FILTER ({_BAD}) > 5")
def poison_rejected(spark, sf_dir):
    """A hundredth of the bodies claim another fingerprint: all are rejected, senders of more than five are named."""
    bodies = encode.chunk_payloads(source.documents(spark, sf_dir), 64).select("source_id", F.col("chunk").alias("body"))
    return protocol.excluded_senders(protocol.validate(protocol.inject_bad_fingerprints(bodies, 0.01)), 5)


@register("poison_responses", f"WITH {sql.chunks(sql.DOCUMENTS, 64)} SELECT source_id, CASE WHEN {_BAD} THEN 'failure' ELSE 'ack' END AS msg_type, count(*) AS messages FROM c GROUP BY ALL")
def poison_responses(spark, sf_dir):
    """What the sink answers to each sender: a failure to a body whose fingerprint is another's, else an acknowledgement."""
    bodies = encode.chunk_payloads(source.documents(spark, sf_dir), 64).select("source_id", F.col("chunk").alias("body"))
    answers = protocol.responses(protocol.validate(protocol.inject_bad_fingerprints(bodies, 0.01)))
    return answers.groupBy("source_id", "msg_type").agg(F.count("*").alias("messages"))


_LOST = " ".join(f"WHEN ('0x' || substr(sha256(packet_id || '|' || chunk_seq || '|' || step || '|{i}'), 1, 8))::BIGINT >= {int(0.1 * (1 << 32))} THEN {i}" for i in range(1, 8))


@register("lossy_link", sql.outcomes(sql.CONVERSATIONS, 8) + f", s AS (SELECT msg_type, CASE {_LOST} ELSE 8 END AS sent FROM (SELECT packet_id, chunk_seq, step, msg_type FROM o JOIN {_STEPS} ON o.outcome = t.outcome WHERE hop = 2)) SELECT msg_type, count(*) AS messages, sum(sent)::BIGINT AS sent FROM s GROUP BY msg_type")
def lossy_link(spark, sf_dir):
    """Extension: the second hop over a link that loses a tenth of all messages, each sent again until it arrives."""
    found = schemes.outcomes(encode.encode_payloads(source.conversations(spark, sf_dir), _C8))
    return schemes.resent(schemes.message_log(found, _C8, "sim_plain"), 0.1).groupBy("msg_type").agg(F.count("*").alias("messages"), F.sum("sent").alias("sent"))


@register("default_schemes", "SELECT kind, scheme, count(DISTINCT l_suppkey) AS nodes, count(*) AS packets FROM lineitem JOIN (VALUES (0, 'basic', 'raw'), (1, 'exact', 'exact'), (2, 'similar', 'sim_plain')) t(i, kind, scheme) ON l_suppkey % 3 = i GROUP BY ALL")
def default_schemes(spark, sf_dir):
    """Suppliers as nodes, dealt over the classes: the scheme that each class sends with where the configuration names none, its nodes and their packets."""
    names = spark.createDataFrame([(i, k, _C8.scheme_of(k)) for i, k in enumerate(protocol.CLASSES)], "i long, kind string, scheme string")
    nodes = source.table(spark, sf_dir, "lineitem").groupBy("l_suppkey").count()
    classed = nodes.join(F.broadcast(names), F.col("l_suppkey") % 3 == F.col("i"))
    return classed.groupBy("kind", "scheme").agg(F.count("*").alias("nodes"), F.sum("count").alias("packets"))


@register("stream_new_bases", f"WITH p AS ({_EVENT}), c AS (SELECT source_id, packet_id, 0 AS chunk_seq, h AS x FROM p), {sql.hamming(4)} SELECT count(DISTINCT word) AS bases FROM w")
def stream_new_bases(spark, sf_dir):
    """The live pool over the event stream ends as large as the batch pool."""
    return _streamed(spark, live.new_bases(live.event_records(live.read_events(spark, sf_dir)), DedupConfig(4)), "append").agg(F.count("*").alias("bases"))


@register("stream_pool_table", f"WITH p AS ({_EVENT}), c AS (SELECT source_id, packet_id, 0 AS chunk_seq, h AS x FROM p), {sql.hamming(4)} SELECT count(DISTINCT word) AS rows, count(DISTINCT word) AS bases FROM w")
def stream_pool_table(spark, sf_dir):
    """The live pool as a table, written batch by batch: every basis once."""
    folder = f"{pool.shared_folder(spark)}/pool-table-{uuid.uuid4().hex}"
    stream = live.new_bases(live.event_records(live.read_events(spark, sf_dir)), DedupConfig(4))
    live.write_pool(stream, f"{folder}/pool", f"{folder}/checkpoint")
    return spark.read.schema("basis_key binary, prefix string").parquet(f"{folder}/pool").agg(F.count("*").alias("rows"), F.countDistinct("basis_key").alias("bases"))


@register("stream_traffic", "SELECT time_bucket(INTERVAL 1 DAY, ts) AS start, user_id::VARCHAR AS source_id, count(*) AS packets, (count(*) * 4)::BIGINT AS bytes FROM events GROUP BY 1, 2")
def stream_traffic(spark, sf_dir):
    """Daily windows of the stream, complete when it has ended."""
    return _streamed(spark, live.traffic(live.event_values(live.read_events(spark, sf_dir)), "1 day", late="365 days"), "complete")


@register("stream_sliding", "SELECT d + o * INTERVAL 1 DAY AS start, source_id, sum(n)::BIGINT AS packets, (sum(n) * 4)::BIGINT AS bytes FROM (SELECT time_bucket(INTERVAL 1 DAY, ts) AS d, user_id::VARCHAR AS source_id, count(*) AS n FROM events GROUP BY 1, 2) CROSS JOIN (VALUES (0), (-1)) t(o) GROUP BY 1, 2")
def stream_sliding(spark, sf_dir):
    """Two-day windows that slide by a day."""
    return _streamed(spark, live.traffic(live.event_values(live.read_events(spark, sf_dir)), "2 days", "1 day", late="365 days"), "complete")


@register("stream_sessions", "WITH g AS (SELECT *, CASE WHEN ts < lag(ts) OVER w + INTERVAL 12 HOUR THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS session FROM g) SELECT min(ts) AS start, max(ts) + INTERVAL 12 HOUR AS \"end\", user_id::VARCHAR AS source_id, count(*) AS packets FROM s GROUP BY user_id, session")
def stream_sessions(spark, sf_dir):
    """Bursts of each user: packets less than twelve hours apart."""
    return _streamed(spark, live.sessions(live.event_values(live.read_events(spark, sf_dir)), "12 hours", late="365 days"), "complete")


def _streamed(spark, stream, mode):
    """Runs a stream of finite files to its end into a table in memory; its state is in the shared folder."""
    name = f"stream_{uuid.uuid4().hex}"
    live.run_once(stream, name, f"{pool.shared_folder(spark)}/{name}", mode)
    return spark.table(name)


@register("window_sharing", f"WITH p AS ({_EVENT}), c AS (SELECT source_id, packet_id, ts, 0 AS chunk_seq, h AS x FROM p), {sql.hamming(4)} SELECT count(DISTINCT (ts::DATE, source_id, word)) AS daily_private, count(DISTINCT (ts::DATE, word)) AS daily_shared, count(DISTINCT word) AS shared_for_ever FROM w")
def window_sharing(spark, sf_dir):
    """What sharing a pool over sources, and over days, saves on the events."""
    from basisflow.functions.hamming import with_codeword

    rows = with_codeword(live.event_records(source.table(spark, sf_dir, "events")).withColumnRenamed("payload", "chunk"), 4)
    keys = rows.groupBy(F.to_date("ts").alias("day"), "source_id", "codeword").count()
    days = keys.groupBy("day", "codeword").agg(F.count("*").alias("sources"))
    words = days.groupBy("codeword").agg(F.sum("sources").alias("private"), F.count("*").alias("days"))
    return words.agg(F.sum("private").alias("daily_private"), F.sum("days").alias("daily_shared"), F.count("*").alias("shared_for_ever"))
