"""Nodes, hops, legal messages, and defence against poisoned fingerprints."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from basisflow.config import DedupConfig
from basisflow.functions.fingerprints import fingerprint
from basisflow.operators import schemes

CLASSES = ("basic", "exact", "similar")
RESPONSES = ("ack", "request", "new_fp", "failure", "deviation_request", "chunk_request")
#: Which class of node sends which message. Responses are everyone's.
SENDS = {"basic": ("data",), "exact": ("exact", "exact_data"), "similar": ("similar", "similar_data", "deviation")}


@dataclass(frozen=True)
class Node:
    name: str
    role: str  # source, intermediate or sink
    kind: str
    next: str | None = None


def topology(spark: SparkSession, nodes: list[Node]) -> DataFrame:
    """A small table (node, role, kind, next_node); links must name known nodes and lead to a sink."""
    names = {n.name: n for n in nodes}
    for n in nodes:
        if n.role not in ("source", "intermediate", "sink") or n.kind not in CLASSES:
            raise ValueError(f"unknown role or class of {n.name}")
        if (n.next is None) != (n.role == "sink") or n.next is not None and n.next not in names:
            raise ValueError(f"{n.name} has a wrong next node")
    return spark.createDataFrame([(n.name, n.role, n.kind, n.next) for n in nodes], "node string, role string, kind string, next_node string")


def allowed(spark: SparkSession) -> DataFrame:
    """(kind, msg_type) of every legal pair."""
    return spark.createDataFrame([(c, m) for c in CLASSES for m in (*RESPONSES, *SENDS[c])], "kind string, msg_type string")


def illegal_messages(log: DataFrame, nodes: DataFrame) -> DataFrame:
    """Messages whose sender's class may not send them; ``log`` has from_node and msg_type."""
    kinds = nodes.select(F.col("node").alias("from_node"), "kind")
    return log.join(F.broadcast(kinds), "from_node").join(F.broadcast(allowed(log.sparkSession)), ["kind", "msg_type"], "left_anti")


def relay(encoded: DataFrame, cfg: DedupConfig, path: list[Node], response_bytes: int = 0) -> DataFrame:
    """The log of all hops of a path: hop, from_node, to_node and the columns of ``message_log``.

    The first hop of a basic source sends plain data; a node's class decides how it sends
    on, and every receiver has a pool of its own, so outcomes are the same at each hop.
    The path is known to the driver and short: a loop over hops, not over data.
    """
    found = schemes.outcomes(encoded)
    out = None
    for hop, (sender, receiver) in enumerate(zip(path, path[1:], strict=False), 1):
        log = schemes.message_log(found, cfg, cfg.scheme_of(sender.kind), response_bytes)
        up = F.col("direction") == "up"
        part = log.withColumns({"hop": F.lit(hop), "from_node": F.when(up, sender.name).otherwise(receiver.name), "to_node": F.when(up, receiver.name).otherwise(sender.name)})
        out = part if out is None else out.unionByName(part)
    return out


def three_nodes() -> list[Node]:
    return [Node("device", "source", "basic", "gateway"), Node("gateway", "intermediate", "similar", "server"), Node("server", "sink", "similar")]


def inject_bad_fingerprints(bodies: DataFrame, rate: float, algo: str = "sha256", n_bytes: int = 8, body: str = "body", sender: str = "source_id") -> DataFrame:
    """Adds ``claimed_fp``: right, but for a share of rows chosen by the body's hash, whose fingerprint is another body's."""
    bad = F.conv(F.substring(F.sha2(body, 256), 1, 8), 16, 10).cast("long") < F.lit(int(rate * (1 << 32)))
    right = fingerprint(F.col(body), algo, n_bytes)
    wrong = fingerprint(F.concat(F.lit(b"not this one"), F.col(body)), algo, n_bytes)
    return bodies.withColumn("claimed_fp", F.when(bad, wrong).otherwise(right))


def validate(messages: DataFrame, algo: str = "sha256", n_bytes: int = 8, body: str = "body") -> DataFrame:
    """Adds ``valid``: whether the claimed fingerprint is the body's own. Invalid bodies must not enter a pool."""
    return messages.withColumn("valid", F.col("claimed_fp") == fingerprint(F.col(body), algo, n_bytes))


def responses(validated: DataFrame) -> DataFrame:
    """Adds ``msg_type``: the sink's answer, ``failure`` to an invalid body and ``ack`` to others."""
    return validated.withColumn("msg_type", F.when(F.col("valid"), "ack").otherwise("failure"))


def excluded_senders(validated: DataFrame, limit: int, sender: str = "source_id") -> DataFrame:
    """Senders with more than ``limit`` invalid bodies."""
    return validated.groupBy(sender).agg(F.count("*").alias("sent"), F.count(F.when(~F.col("valid"), 1)).alias("rejected")).where(F.col("rejected") > limit)
