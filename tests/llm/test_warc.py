import io
import struct

import pytest
import zstandard

from basisflow.llm import warc

PAGES = "page_id long, url string, html string"


def test_round_trip_with_copies_nulls_and_ties(spark):
    same = "x" * 150
    rows = [(1, "u", same), (2, None, same), (3, "u", "short"), (4, "u", "short"), (5, "u\r\nX: y", None), (6, "u", ""), (7, "u", "é" * 50), (8, "u", "é" * 50), (None, "u", same), (1, "u", same)]
    rows += [(100 + i, "u", f"<html>{i}</html>" * 40) for i in range(60)]
    out = warc.round_trip(spark.createDataFrame(rows, PAGES)).collect()
    assert len(out) == len(rows)
    got = sorted(((-1 if r.page_id is None else r.page_id), r.record_type, r.refers_to) for r in out)
    assert got[:10] == [(-1, "revisit", 1), (1, "response", None), (1, "response", None), (2, "revisit", 1), (3, "response", None), (4, "response", None), (5, "response", None), (6, "response", None), (7, "response", None), (8, "revisit", 7)]
    assert {r.payload_bytes for r in out if r.page_id in (5, 6)} == {0}


def test_content_comes_back(spark):
    rows = [(i, f"http://h/{i}", f"<p>{i}</p>" * 50) for i in range(300)]
    pages = spark.createDataFrame(rows, PAGES)
    from basisflow.llm.common import shared_dir

    manifest = warc.write(pages, f"{shared_dir(spark)}/warc-test")
    out = {r.page_id: (r.url, bytes(r.html).decode()) for r in warc.read(manifest, content=True).collect()}
    assert out == {i: (u, h) for i, u, h in rows}


def test_columns_of_any_name_and_long_pages(spark):
    names = "payload", "digest", "salt", "first", "n", "record_type", "refers_to", "target"
    long = "<p>é</p>" * 400_000
    rows = [(1, "u", long, *names), (2, "u", long, *names), (3, "u", None, *names), (None, None, None, *names)]
    out = warc.round_trip(spark.createDataFrame(rows, PAGES + ", " + ", ".join(f"{n} string" for n in names))).collect()
    assert sorted(((r.page_id or 0), r.payload_bytes, r.record_type, r.refers_to) for r in out) == [(0, 0, "response", None), (1, 3_600_000, "response", None), (2, 3_600_000, "revisit", 1), (3, 0, "response", None)]


def test_revisits_need_their_response(spark):
    schema = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long"
    good = [(1, 200, "a", "response", None), (2, 200, "a", "revisit", 1)]
    assert len(warc.checked_revisits(spark.createDataFrame(good, schema)).collect()) == 2
    for bad in ((2, 200, "b", "revisit", 1), (2, 201, "a", "revisit", 1), (2, 200, "a", "revisit", 7)):
        with pytest.raises(Exception, match="no response"):
            warc.checked_revisits(spark.createDataFrame([good[0], bad], schema)).collect()


def test_empty_table(spark):
    assert warc.round_trip(spark.createDataFrame([], PAGES)).count() == 0


def archive(raws, dictionary=b""):
    out = io.BytesIO()
    writer = warc.Writer(out, dictionary)
    for raw in raws:
        writer.add(raw)
    return out.getvalue()


def test_frames_and_dictionary():
    raws = [warc.page_record(i, "u", f"<html>page {i} {'lorem ipsum ' * 20}</html>".encode() * 3, "0" * 64, None) for i in range(400)]
    dictionary = warc.train(raws)
    assert dictionary
    data = archive(raws, dictionary)
    assert struct.unpack("<I", data[:4])[0] == 0x184D2A5D
    assert list(warc.records(io.BytesIO(data), 37)) == raws
    compressed = zstandard.ZstdCompressor().compress(dictionary)
    size = struct.unpack("<I", data[4:8])[0]
    assert list(warc.records(io.BytesIO(warc.dictionary_frame(compressed) + data[8 + size :]))) == raws


def test_broken_archives_are_refused():
    good = archive([warc.page_record(1, "u", b"abc", "0" * 64, None)])
    for bad in (b"", good[4:], good[:-3], good[:20]):
        with pytest.raises(warc.Malformed):
            list(warc.records(io.BytesIO(bad))) or warc.parse(b"")
    record = warc.page_record(1, "u", b"abc", "0" * 64, None)
    for bad in (record[:-1], record.replace(b"WARC/1.1", b"WARC/9.9"), record.replace(b"WARC-Type: response", b"WARC-Type: nothing"), record.replace(b"WARC-Date", b"X-Date"), record + b"\r\n"):
        with pytest.raises(warc.Malformed):
            warc.parse(bad)
    with pytest.raises(warc.Malformed):
        warc.page_row(*warc.parse(record))  # the digest is not the payload's
