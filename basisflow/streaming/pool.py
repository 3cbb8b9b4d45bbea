"""The live pool: new bases, outcomes and windowed traffic over a stream of payloads.

The kernels are the batch ones. Bases are deduplicated by ``dropDuplicates`` on their key,
whose state is the pool; with a watermark it forgets old bases instead of growing
without limit. Outcomes keep, for every basis, the chunks seen under it: a chunk
has one basis, so one key is enough. Repeated delivery changes no state.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

from basisflow.config import DedupConfig
from basisflow.operators.encode import encode_payloads
from basisflow.sources.payloads import hundredths, pack_uint

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
TYPES = ("click", "error", "purchase", "signup", "view")


def event_records(events: DataFrame) -> DataFrame:
    """Payload rows with a time: type, JSON number k, user, each a byte, and a zero byte."""
    kind = F.coalesce(F.array_position(F.array(*map(F.lit, TYPES)), F.col("event_type")), F.lit(0))
    k = F.from_json("props", "k int")["k"]
    payload = F.concat(pack_uint(kind, 1), pack_uint(F.coalesce(k, F.lit(0)), 1), pack_uint(F.col("user_id") % 256, 1), pack_uint(F.lit(0), 1))
    return events.select(F.col("user_id").cast("string").alias("source_id"), F.col("event_id").alias("packet_id"), F.col("ts"), payload.alias("payload"))


def event_values(events: DataFrame) -> DataFrame:
    return events.select(F.col("user_id").cast("string").alias("source_id"), F.col("event_id").alias("packet_id"), F.col("ts"), F.concat(pack_uint(hundredths(F.col("value")), 3), pack_uint(F.lit(0), 1)).alias("payload"))


def read_events(spark: SparkSession, sf_dir: str, max_files: int | None = None) -> DataFrame:
    """The events table as a stream of files; the folder may hold other tables."""
    reader = spark.readStream.schema(EVENTS).option("pathGlobFilter", "events.parquet")
    if max_files:
        reader = reader.option("maxFilesPerTrigger", max_files)
    return reader.parquet(sf_dir)


def new_bases(payloads: DataFrame, cfg: DedupConfig, forget: str | None = None) -> DataFrame:
    """The stream of bases the sink has not seen; ``forget`` is how long it remembers them (for ever if None)."""
    encoded = encode_payloads(payloads, cfg) if forget is None else None
    if encoded is not None:
        return encoded.dropDuplicates(["basis_key"]).select("basis_key", "basis", "source_id", "packet_id")
    timed = _encoded_with_time(payloads, cfg).withWatermark("ts", forget)
    return timed.dropDuplicatesWithinWatermark(["basis_key"]).select("basis_key", "ts", "source_id", "packet_id")


def _encoded_with_time(payloads: DataFrame, cfg: DedupConfig) -> DataFrame:
    """Basis keys beside times: the payload's time travels inside its source name and comes out again."""
    tagged = payloads.withColumn("source_id", F.concat_ws("@", F.unix_micros("ts"), "source_id"))
    out = encode_payloads(tagged, cfg)
    parts = F.split("source_id", "@", 2)
    return out.withColumn("ts", F.timestamp_micros(parts[0].cast("long"))).withColumn("source_id", parts[1])


def traffic(payloads: DataFrame, width: str, slide: str | None = None, late: str = "10 minutes") -> DataFrame:
    """Payload bytes by source in tumbling (or sliding) windows; rows later than ``late`` are not counted."""
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    sums = payloads.withWatermark("ts", late).groupBy(window, "source_id").agg(F.count("*").alias("packets"), F.sum(F.octet_length("payload")).alias("bytes"))
    return sums.select(F.col("window.start").alias("start"), "source_id", "packets", "bytes")


def sessions(payloads: DataFrame, gap: str, late: str = "10 minutes") -> DataFrame:
    """Bursts of each source: packets no further apart than ``gap``."""
    sums = payloads.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "source_id").agg(F.count("*").alias("packets"))
    return sums.select(F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "source_id", "packets")


class Outcomes(StatefulProcessor):
    """Per basis: counts of new_basis, new_chunk and repeat, with the chunks seen as map state."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self._seen = handle.getMapState("seen", "chunk_key binary", "n long")

    def handleInputRows(self, key, rows, timerValues):
        fresh, again, opened = 0, 0, 0
        known = self._seen.exists()
        for part in rows:
            # the state is asked once for each distinct chunk of a batch
            for chunk, n in part["chunk_key"].map(bytes).value_counts().items():
                if known and self._seen.containsKey((chunk,)):
                    again += n
                    continue
                opened, fresh = (opened, fresh + 1) if known else (1, fresh)
                again, known = again + n - 1, True
                self._seen.updateValue((chunk,), (1,))
        yield pd.DataFrame({"basis_key": [key[0]], "new_basis": [opened], "new_chunk": [fresh], "repeat": [again]})

    def close(self) -> None:
        pass


def stream_outcomes(payloads: DataFrame, cfg: DedupConfig) -> DataFrame:
    """Outcome counts per basis and micro-batch. Needs the RocksDB state store provider."""
    encoded = encode_payloads(payloads, cfg).select("basis_key", "chunk_key")
    return encoded.groupBy("basis_key").transformWithStateInPandas(Outcomes(), "basis_key binary, new_basis long, new_chunk long, repeat long", "Append", "None")


def run_once(stream: DataFrame, name: str, checkpoint: str, mode: str = "append") -> None:
    """Runs what is there to the end, into a table in memory."""
    stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


def append_pool(batch: DataFrame, number: int, path: str) -> None:
    """For ``foreachBatch``: writes a micro-batch's new bases to a Parquet pool, by key prefix. A batch that is run again replaces what it wrote."""
    rows = batch.withColumn("prefix", F.substring(F.hex("basis_key"), 1, 2))
    rows.write.mode("overwrite").partitionBy("prefix").parquet(f"{path}/batch={number}")


def write_pool(stream: DataFrame, path: str, checkpoint: str) -> None:
    """Runs what is there to the end, into a pool on disk."""
    writer = stream.writeStream.foreachBatch(lambda batch, number: append_pool(batch, number, path))
    writer.option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
