"""WARC archives compressed with Zstandard: a writer and a validating reader.

An archive starts with a skippable frame (magic 0x184D2A5D) that holds the
dictionary; then each record is one frame. Records follow WARC/1.1: a version line,
named fields, an empty line, the block, two empty lines. A page whose payload an
earlier page (by id) has already is a revisit record, without the payload.

Each task writes one archive under a fresh name through ``pyarrow.fs`` and returns
one manifest row. Only archives in the checkpointed manifest are ever read, so those
that a lost or repeated task left behind do no harm.

Defined results: null html is an empty payload; payloads under ``LEAST`` bytes are never
revisits; rows with the smallest id of equal payloads are responses, all of them where
that id is repeated; a null id never becomes the response of others and refers to
one as others do; an empty table gives no archives and no rows; further columns are ignored,
whatever their names; a payload of any length is one record, held whole by the task that writes or reads it.
"""

from __future__ import annotations

import hashlib
import io
import struct
import uuid

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import shared_dir, small_side, tidied, written

#: Fixed values of the public formats.
DICTIONARY_MAGIC, FRAME_MAGIC = 0x184D2A5D, 0xFD2FB528
VERSION = b"WARC/1.1"
TYPES = ("response", "revisit", "warcinfo", "request", "metadata", "resource", "conversion", "continuation")
IDENTICAL = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
#: Fixed value of the contract: payloads of fewer bytes are never revisits.
LEAST = 100
#: Bytes of first records that a dictionary is trained on, its size, and bytes read at once.
TRAIN_BYTES, DICTIONARY_BYTES, READ_BYTES = 1 << 20, 1 << 14, 1 << 16
#: Each repeated payload's group is spread over so many keys.
SALT = 16


class Malformed(ValueError):
    """An archive breaks the format."""


def record(fields: list[tuple[str, str]], block: bytes) -> bytes:
    head = "".join(f"{k}: {v}\r\n" for k, v in [*fields, ("Content-Length", str(len(block)))])
    return VERSION + b"\r\n" + head.encode() + b"\r\n" + block + b"\r\n\r\n"


def parse(raw: bytes) -> tuple[dict[str, str], bytes]:
    """Fields (lower-case names) and block of exactly one record."""
    head, mark, rest = raw.partition(b"\r\n\r\n")
    lines = head.split(b"\r\n")
    if not mark or lines[0] not in (VERSION, b"WARC/1.0"):
        raise Malformed("no version line or no end of the fields")
    fields = {}
    for line in lines[1:]:
        name, colon, value = line.decode().partition(":")
        if not colon or not name.strip():
            raise Malformed(f"field without a name: {line[:80]!r}")
        fields[name.strip().lower()] = value.strip()
    for needed in ("warc-type", "warc-record-id", "warc-date", "content-length"):
        if needed not in fields:
            raise Malformed(f"{needed} is missing")
    if fields["warc-type"] not in TYPES:
        raise Malformed(f"unknown type {fields['warc-type']!r}")
    length = fields["content-length"]
    if not length.isdigit() or len(rest) != int(length) + 4 or not rest.endswith(b"\r\n\r\n"):
        raise Malformed("Content-Length does not fit the record")
    return fields, rest[:-4]


def dictionary_frame(content: bytes) -> bytes:
    return struct.pack("<II", DICTIONARY_MAGIC, len(content)) + content


def train(samples: list[bytes]) -> bytes:
    """A dictionary, or nothing where there is too little to train on."""
    if len(samples) < 16 or sum(map(len, samples)) < 4 * DICTIONARY_BYTES:
        return b""
    try:
        return zstandard.train_dictionary(DICTIONARY_BYTES, samples).as_bytes()
    except zstandard.ZstdError:
        return b""


class Writer:
    def __init__(self, out, dictionary: bytes, level: int = 3):
        self._out = out
        self._pack = zstandard.ZstdCompressor(level=level, dict_data=zstandard.ZstdCompressionDict(dictionary) if dictionary else None, write_checksum=True)
        out.write(dictionary_frame(dictionary))

    def add(self, raw: bytes):
        self._out.write(self._pack.compress(raw))


def records(stream, read_bytes: int = READ_BYTES):
    """Raw records of an archive, one frame at a time; memory holds one record."""
    head = stream.read(8)
    if len(head) < 8 or struct.unpack("<I", head[:4])[0] != DICTIONARY_MAGIC:
        raise Malformed("no dictionary frame in front")
    size = struct.unpack("<I", head[4:])[0]
    content = stream.read(size)
    if len(content) != size:
        raise Malformed("the dictionary is cut short")
    if content[:4] == struct.pack("<I", FRAME_MAGIC):  # a dictionary may itself be compressed
        content = zstandard.ZstdDecompressor().decompressobj().decompress(content)
    unpack = zstandard.ZstdDecompressor(dict_data=zstandard.ZstdCompressionDict(content) if content else None)
    rest = stream.read(read_bytes)
    while rest:
        frame, parts = unpack.decompressobj(), []
        while not frame.eof:
            if not rest:
                raise Malformed("the last frame is cut short")
            try:
                parts.append(frame.decompress(rest))
            except zstandard.ZstdError as e:
                raise Malformed(str(e)) from e
            rest = frame.unused_data if frame.eof else stream.read(read_bytes)
        yield b"".join(parts)
        rest = rest or stream.read(read_bytes)


def page_record(page_id, url, payload: bytes, digest: str, refers_to) -> bytes:
    revisit = refers_to is not None
    fields = [("WARC-Type", "revisit" if revisit else "response"), ("WARC-Record-ID", f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'page:{page_id}')}>"), ("WARC-Date", "1970-01-01T00:00:00Z"), ("WARC-Payload-Digest", f"sha256:{digest}"), ("X-Payload-Bytes", str(len(payload))), ("Content-Type", "application/http; msgtype=response")]
    if url:
        fields.append(("WARC-Target-URI", "".join(c for c in url if c not in "\r\n")))
    if page_id is not None:
        fields.append(("X-Page-Id", str(page_id)))
    if revisit:
        fields += [("WARC-Profile", IDENTICAL), ("WARC-Refers-To", f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'page:{refers_to}')}>"), ("X-Refers-To-Page", str(refers_to))]
    head = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    return record(fields, head + (b"" if revisit else payload))


def page_row(fields: dict[str, str], block: bytes) -> tuple:
    """(page_id, payload_bytes, payload_digest, record_type, refers_to, url, html bytes), checked."""
    kind, digest, size = fields["warc-type"], fields["warc-payload-digest"].removeprefix("sha256:"), int(fields["x-payload-bytes"])
    payload = block.partition(b"\r\n\r\n")[2]
    if kind == "response" and (len(payload) != size or hashlib.sha256(payload).hexdigest() != digest):
        raise Malformed("the payload does not fit its digest or length")
    if kind == "revisit" and payload:
        raise Malformed("a revisit record holds a payload")
    number = lambda name: int(fields[name]) if name in fields else None
    return number("x-page-id"), size, digest, kind, number("x-refers-to-page"), fields.get("warc-target-uri"), payload if kind == "response" else None


def firsts(pages: DataFrame) -> DataFrame:
    """(digest, first) of payloads of ``LEAST`` bytes or more that occur more than once."""
    light = pages.select(F.sha2("payload", 256).alias("digest"), "page_id").where(F.octet_length("payload") >= LEAST)
    return light.groupBy("digest").agg(F.min("page_id").alias("first"), F.count("*").alias("n")).where(F.col("n") > 1).select("digest", "first")


def write(pages: DataFrame, folder: str, key: str = "page_id", url: str = "url", html: str = "html") -> DataFrame:
    """Writes archives under ``folder``; returns the checkpointed manifest (path, records, bytes)."""
    rows = pages.select(F.col(key).cast("long").alias("page_id"), F.col(url).alias("url"), F.coalesce(F.encode(html, "UTF-8"), F.lit(b"")).alias("payload"))
    repeated = written(firsts(rows), "payloads").withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALT - 1))))
    salt = F.pmod(F.xxhash64("page_id", "url"), F.lit(SALT)).cast("int")
    digests = rows.withColumn("digest", F.sha2("payload", 256)).withColumn("salt", salt)
    joined = digests.join(small_side(repeated), ["digest", "salt"], "left")
    refers = F.when(F.octet_length("payload") >= LEAST, F.when(F.col("page_id").isNull() | (F.col("page_id") != F.col("first")), F.col("first")))
    ready = joined.select("page_id", "url", "payload", "digest", refers.alias("refers_to"))

    def run(batches):
        from pyarrow import fs

        held, size, writer, count, out, name = [], 0, None, 0, None, f"pages-{uuid.uuid4().hex}.warc.zst"

        def begin():
            system, base = fs.FileSystem.from_uri(folder)
            system.create_dir(base, recursive=True)
            stream = system.open_output_stream(f"{base}/{name}", compression=None)
            writer = Writer(stream, train(held))
            for raw in held:
                writer.add(raw)
            return stream, writer

        for batch in batches:
            for row in zip(*(batch.column(i) for i in range(5)), strict=True):
                raw = page_record(*(x.as_py() for x in row))
                count += 1
                if writer:
                    writer.add(raw)
                    continue
                held.append(raw)
                size += len(raw)
                if size >= TRAIN_BYTES:
                    out, writer = begin()
                    held.clear()
        if held:
            out, writer = begin()
        if out:
            length = out.tell()
            out.close()
            yield pa.RecordBatch.from_arrays([pa.array([f"{folder}/{name}"]), pa.array([count], pa.int64()), pa.array([length], pa.int64())], ["path", "records", "bytes"])

    shared_dir(pages.sparkSession)
    return ready.mapInArrow(tidied(run), "path string, records long, bytes long").checkpoint()


def read(manifest: DataFrame, content: bool = False) -> DataFrame:
    """One row per record of the archives, each checked; ``content`` adds url and html."""
    names = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", *(["url", "html"] if content else [])]
    kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), *([pa.string(), pa.binary()] if content else [])]

    def run(batches):
        from pyarrow import fs

        for batch in batches:
            for path, expected in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                system, base = fs.FileSystem.from_uri(path)
                rows, count, size = [], 0, 0
                with io.BufferedReader(system.open_input_stream(base, compression=None)) as stream:
                    for raw in records(stream):
                        rows.append(page_row(*parse(raw))[: len(names)])
                        count += 1
                        size += len(raw)
                        if size >= 1 << 22:
                            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names)
                            rows, size = [], 0
                if count != expected:
                    raise Malformed(f"{path} has {count} records, not {expected}")
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names)

    schema = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long" + (", url string, html binary" if content else "")
    # one archive a task, as far as there are slots: archives are much larger than their rows here
    spread = manifest.select("path", "records").repartition(max(1, min(manifest.count(), 10_000)))
    return spread.mapInArrow(tidied(run), schema)


def checked_revisits(records: DataFrame) -> DataFrame:
    """The records, with an error where a revisit's response is not among them with the same digest and length."""
    targets = records.where("record_type = 'response'").select(F.col("page_id").alias("target"), F.col("payload_digest").alias("d"), F.col("payload_bytes").alias("b")).distinct()
    revisits = records.where("record_type = 'revisit'")
    same = (F.col("refers_to") == F.col("target")) & (F.col("payload_digest") == F.col("d")) & (F.col("payload_bytes") == F.col("b"))
    known = revisits.join(targets, same, "left")
    wrong = F.raise_error(F.concat_ws(" ", F.lit("no response with the payload of page"), "page_id")).cast("long")
    fields = [c for c in records.columns if c != "refers_to"]
    known = known.select(*fields, F.when(F.col("target").isNull(), wrong).otherwise(F.col("refers_to")).alias("refers_to"))
    return records.where("record_type <> 'revisit'").unionByName(known)


def round_trip(pages: DataFrame) -> DataFrame:
    archives = write(pages, f"{shared_dir(pages.sparkSession)}/basisflow/warc-{uuid.uuid4().hex}")
    return checked_revisits(written(read(archives), "warc-records"))
