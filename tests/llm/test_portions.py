import pyarrow as pa
import pytest

from basisflow.llm import common, decontam, langid, packing, similar, tokens

TEXTS = [f"words number {i} of a text that tells little more than this" for i in range(4500)]
BATCH = pa.RecordBatch.from_arrays([pa.array(range(len(TEXTS)), pa.int64()), pa.array(TEXTS)], ["doc_id", "text"])


class Docs:
    """Keeps the function that would run in a task."""

    columns, schema = ["doc_id", "text"], None

    def __init__(self):
        self.sparkSession = self.sparkContext = self
        self.select = lambda *_: self
        self.broadcast = lambda value: type("Shared", (), {"value": value})

    def mapInArrow(self, run, _):  # noqa: N802
        self.run = run
        return self


def cleaned(docs):
    benchmark = type("Items", (), {"select": lambda self, *_: self, "toLocalIterator": lambda self: iter([(1, TEXTS[7])])})()
    decontam.clean(docs, benchmark)


def accepted(docs, monkeypatch):
    monkeypatch.setattr(langid, "training_rows", lambda _: [("en", TEXTS[0])])
    langid.accepted(docs)


@pytest.mark.parametrize("stage", ["accepted", "label", "clean", "sketches", "encoded"])
def test_a_stage_holds_only_a_slice_of_a_batch(spark, monkeypatch, stage):
    docs, model = Docs(), langid.train([("en", TEXTS[0])])
    {"accepted": lambda: accepted(docs, monkeypatch), "label": lambda: langid.label(docs, model), "clean": lambda: cleaned(docs), "sketches": lambda: similar.sketches(docs), "encoded": lambda: packing.encoded(docs, lean=True)}[stage]()
    got = list(docs.run(iter([BATCH])))
    assert max(b.num_rows for b in got) <= 2000
    ids = [i for b in got for i in b.column(0).to_pylist()]
    assert 7 in ids or stage == "clean"
    assert ids == sorted(set(ids)) and (stage == "clean" or len(ids) == len(TEXTS))


def test_slices_follow_bytes_and_lose_no_row():
    long = pa.RecordBatch.from_arrays([pa.array(["x" * 3_000_000] * 5)], ["text"])
    got = list(common.portions([long, BATCH, BATCH.slice(0, 0)]))
    assert [b.num_rows for b in got] == [2, 2, 1, 2000, 2000, 500]
    assert pa.Table.from_batches(got[3:]).equals(pa.Table.from_batches([BATCH]))


def test_a_lean_encoder_keeps_half_and_forgets_the_older_generation(spark):
    docs = Docs()
    packing.encoded(docs, lean=True)
    list(docs.run(iter([BATCH])))
    (encoder,) = tokens._ENCODERS.values()
    assert encoder._most == tokens.CACHE_PIECES // 2 and encoder._young
    encoder._old = {b"word": b""}
    list(docs.run(iter([BATCH])))
    assert not encoder._old
