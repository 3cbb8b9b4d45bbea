"""The four fingerprint exchanges and raw transfer, message by message.

Chunks arrive in the order (packet_id, chunk_seq). What happens to a chunk depends only on
its own first arrival and its basis's, so outcomes come from two aggregations and
equality joins, never from a window over one basis.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from basisflow.config import DedupConfig

OUTCOMES = ("new_basis", "new_chunk", "repeat")


def first_seen(encoded: DataFrame, key: str, scope: tuple[str, ...] = ()) -> DataFrame:
    """First arrival of each key, and how many rows have it."""
    return encoded.groupBy(*scope, key).agg(F.min(F.struct("packet_id", "chunk_seq")).alias("first"), F.count("*").alias("refs"))


def outcomes(encoded: DataFrame, scope: tuple[str, ...] = ()) -> DataFrame:
    """Adds ``outcome``. ``scope`` is empty for a pool that all sources share, or ("source_id",) for private pools.

    The basis of a chunk is that of its key, so the second aggregation runs over distinct chunks. Only first
    arrivals come back, joined on the arrival and never on the key: a chunk that a third of all rows
    repeat is combined before it moves and meets one row. Where rows are not wanted, ``outcome_totals`` needs no join at all.
    """
    chunk = encoded.groupBy(*scope, "chunk_key").agg(F.min(F.struct("packet_id", "chunk_seq")).alias("chunk_first"), F.first("basis_key").alias("basis_key"))
    basis = chunk.groupBy(*scope, "basis_key").agg(F.min("chunk_first").alias("basis_first"))
    firsts = chunk.join(basis, [*scope, "basis_key"]).select(*scope, "chunk_key", "chunk_first.*", (F.col("chunk_first") == F.col("basis_first")).alias("opens"))
    joined = encoded.join(firsts, [*scope, "packet_id", "chunk_seq", "chunk_key"], "left")
    return joined.withColumn("outcome", F.when(F.col("opens").isNull(), "repeat").when(F.col("opens"), "new_basis").otherwise("new_chunk")).drop("opens")


def outcome_totals(counted: DataFrame) -> DataFrame:
    """(outcome, chunks, dev_bytes) from ``costs.counts`` of one configuration: N chunks, U distinct ones and B bases make
    B new bases, U - B new chunks and N - U repeats. ``dev_bytes`` is that of new chunks and null for the others, where no one cost needs it alone."""
    rows = F.array(
        F.struct(F.lit("new_basis").alias("outcome"), F.col("bases").alias("chunks"), F.lit(None).cast("long").alias("dev_bytes")),
        F.struct(F.lit("new_chunk").alias("outcome"), (F.col("exact_bases") - F.col("bases")).alias("chunks"), F.col("q_dev").alias("dev_bytes")),
        F.struct(F.lit("repeat").alias("outcome"), (F.col("chunks") - F.col("exact_bases")).alias("chunks"), F.lit(None).cast("long").alias("dev_bytes")),
    )
    return counted.select(F.explode(rows).alias("r")).select("r.*").where("chunks > 0")


def hinted(unique: DataFrame, cfg: DedupConfig) -> DataFrame:
    """Exact deduplication after a manifest of what the sink holds; ``unique`` has n (chunks) and held of every distinct chunk.

    The manifest goes down once, a fingerprint for each held chunk. Every chunk sends its fingerprint and is
    acknowledged; a chunk that is not held is asked for and sent the first time.
    """
    c, h = F.col, cfg.fp_bytes
    sums = unique.agg(F.sum("n").alias("chunks"), F.count("*").alias("unique_chunks"), F.count(F.when(c("held"), 1)).alias("hinted_chunks"))
    lacking = c("unique_chunks") - c("hinted_chunks")
    return sums.select("chunks", "unique_chunks", "hinted_chunks", (lacking * cfg.n_b).alias("body_bytes"), (c("hinted_chunks") * h).alias("manifest_bytes"), (c("chunks") * h + lacking * cfg.n_b).alias("up_bytes"), (2 * c("chunks") + 2 * lacking + 1).alias("messages"))


def _uplink(cfg: DedupConfig, scheme: str):
    """For each outcome, what the source sends: (message, bytes, whether a deviation comes on top)."""
    h, n_b, k_b = cfg.fp_bytes, cfg.n_b, cfg.basis_bytes
    if scheme == "raw":
        return {o: [("data", n_b, False)] for o in OUTCOMES}
    if scheme == "exact":
        hello, body = ("exact", h, False), ("exact_data", n_b, False)
        return {"repeat": [hello], "new_chunk": [hello, body], "new_basis": [hello, body]}
    if scheme in ("sim_plain", "sim_short"):
        # short fingerprint and deviation together are as long as a full fingerprint
        hello = ("similar", h, scheme == "sim_plain")
        return {"repeat": [hello], "new_chunk": [hello], "new_basis": [hello, ("similar_data", k_b, False)]}
    if scheme == "sim_dual":
        cfg.half_fp_bytes()
        hello = ("similar", h, False)
        return {"repeat": [hello], "new_chunk": [hello, ("deviation", 0, True)], "new_basis": [hello, ("similar_data", n_b, False)]}
    raise ValueError(f"unknown scheme {scheme!r}")


#: What the sink asks for after the first message, by scheme and outcome; everything ends in an acknowledgement.
_REQUEST = {"exact": {"new_chunk": "request", "new_basis": "request"}, "sim_plain": {"new_basis": "new_fp"}, "sim_short": {"new_basis": "new_fp"}, "sim_dual": {"new_chunk": "deviation_request", "new_basis": "chunk_request"}, "raw": {}}


def message_log(found: DataFrame, cfg: DedupConfig, scheme: str, response_bytes: int = 0) -> DataFrame:
    """A row per message: packet_id, chunk_seq, step, direction, msg_type, bytes; ``found`` has outcomes."""
    plans = []
    for outcome, sent in _uplink(cfg, scheme).items():
        messages = [("up", *sent[0])]
        if (ask := _REQUEST[scheme].get(outcome)) is not None:
            messages += [("down", ask, response_bytes, False), ("up", *sent[1])]
        messages.append(("down", "ack", response_bytes, False))
        rows = F.array(*(F.struct(F.lit(i + 1).alias("step"), F.lit(way).alias("direction"), F.lit(kind).alias("msg_type"), (F.lit(size).cast("long") + (F.col("dev_bytes") if deviation else 0)).alias("bytes")) for i, (way, kind, size, deviation) in enumerate(messages)))
        plans.append((outcome, rows))
    column = F.when(F.col("outcome") == plans[0][0], plans[0][1])
    for outcome, rows in plans[1:]:
        column = column.when(F.col("outcome") == outcome, rows)
    return found.select("source_id", "packet_id", "chunk_seq", "outcome", F.explode(column).alias("m")).select("source_id", "packet_id", "chunk_seq", "outcome", "m.*")


def traffic(found: DataFrame, cfg: DedupConfig, schemes=("raw", "exact", "sim_plain", "sim_short", "sim_dual")) -> DataFrame:
    """(scheme, outcome, chunks, messages, up_bytes) without message rows: sums over outcomes."""
    return _traffic(found.groupBy("outcome").agg(F.count("*").alias("chunks"), F.sum("dev_bytes").alias("dev_bytes")), cfg, schemes)


def traffic_of_totals(totals: DataFrame, cfg: DedupConfig, schemes=("raw", "exact", "sim_plain", "sim_short", "sim_dual")) -> DataFrame:
    """``traffic`` from ``outcome_totals``, for transforms whose deviations have one length."""
    if cfg.fixed_deviation is None:
        raise ValueError("deviations of one length are needed")
    return _traffic(totals.withColumn("dev_bytes", F.col("chunks") * cfg.fixed_deviation), cfg, schemes)


def _traffic(sums: DataFrame, cfg: DedupConfig, schemes) -> DataFrame:
    rows = []
    for scheme in schemes:
        size, steps = F.lit(None).cast("long"), F.lit(None).cast("long")
        for outcome, messages in _uplink(cfg, scheme).items():
            total = F.col("chunks") * sum(n for _, n, _ in messages) + sum(F.col("dev_bytes") for *_, deviation in messages if deviation)
            size = F.when(F.col("outcome") == outcome, total).otherwise(size)
            steps = F.when(F.col("outcome") == outcome, F.col("chunks") * (4 if outcome in _REQUEST[scheme] else 2)).otherwise(steps)
        rows.append(F.struct(F.lit(scheme).alias("scheme"), steps.cast("long").alias("messages"), size.cast("long").alias("up_bytes")))
    return sums.select("outcome", "chunks", F.explode(F.array(*rows)).alias("r")).select("r.scheme", "outcome", "chunks", "r.messages", "r.up_bytes")


def resent(log: DataFrame, rate: float, most: int = 8) -> DataFrame:
    """Adds ``sent``: how often each message goes out where a share ``rate`` is lost, at most ``most`` times.

    Whether an attempt is lost is read from the message's own digest, so that a run can be repeated. A receiver that
    gets a message twice changes nothing: its pool is keyed by fingerprints.
    """
    name = F.concat_ws("|", "packet_id", "chunk_seq", "step")
    lost = lambda i: F.conv(F.substring(F.sha2(F.concat_ws("|", name, F.lit(i)), 256), 1, 8), 16, 10).cast("long") < int(rate * (1 << 32))
    sent = F.lit(most)
    for attempt in range(most - 1, 0, -1):
        sent = F.when(lost(attempt), sent).otherwise(attempt)
    return log.withColumn("sent", sent)


def collisions(bodies: DataFrame, fp: str = "fp", body: str = "body") -> DataFrame:
    """Bodies that a receiver takes for another one: those behind a fingerprint whose first body differs."""
    firsts = bodies.groupBy(fp).agg(F.min_by(body, "first").alias("__first"))
    return bodies.join(firsts, fp).where(F.col(body) != F.col("__first")).drop("__first")


def corruption(unique: DataFrame, cfg: DedupConfig, scheme: str) -> DataFrame:
    """One row: chunks that a scheme would silently restore wrongly, and those that its local check catches.

    exact and plain name bodies by the full fingerprint, short by what the deviation leaves of it. The dual
    scheme rebuilds the chunk from its own basis and compares the chunk's half fingerprint, so only a collision in both halves stays unseen.
    """
    from basisflow.functions.fingerprints import fingerprint

    if scheme == "exact":
        wrong = collisions(unique.withColumn("body", F.col("chunk_key")).withColumn("fp", fingerprint(F.col("body"), cfg.fp_algo, cfg.fp_bytes)))
        return wrong.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("wrong_chunks"), F.lit(0).cast("long").alias("caught_chunks"))
    if scheme in ("sim_plain", "sim_short"):
        width = cfg.fp_bytes if scheme == "sim_plain" else cfg.short_fp_bytes(cfg.fixed_deviation or 0)
        bases = unique.groupBy("basis_key").agg(F.sum("n").alias("n"), F.min("first").alias("first")).withColumn("body", F.col("basis_key"))
        wrong = collisions(bases.withColumn("fp", fingerprint(F.col("body"), cfg.fp_algo, width)))
        return wrong.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("wrong_chunks"), F.lit(0).cast("long").alias("caught_chunks"))
    half = cfg.half_fp_bytes()
    marked = unique.withColumn("chunk_fp", fingerprint(F.col("chunk_key"), cfg.fp_algo, half)).withColumn("basis_fp", fingerprint(F.col("basis_key"), cfg.fp_algo, half))
    firsts = marked.groupBy("basis_fp").agg(F.min_by("basis_key", "first").alias("held"))
    chunk_first = marked.groupBy("chunk_fp").agg(F.min_by("chunk_key", "first").alias("held_chunk"))
    joined = marked.join(firsts, "basis_fp").join(chunk_first, "chunk_fp")
    other_chunk, other_basis = F.col("held_chunk") != F.col("chunk_key"), F.col("held") != F.col("basis_key")
    both = marked.groupBy("chunk_fp", "basis_fp").agg(F.min_by("chunk_key", "first").alias("both_held"))
    joined = joined.join(both, ["chunk_fp", "basis_fp"])
    unseen = F.col("both_held") != F.col("chunk_key")
    return joined.agg(F.coalesce(F.sum(F.when(unseen, F.col("n"))), F.lit(0)).alias("wrong_chunks"), F.coalesce(F.sum(F.when(~unseen & (other_chunk | other_basis), F.col("n"))), F.lit(0)).alias("caught_chunks"))
