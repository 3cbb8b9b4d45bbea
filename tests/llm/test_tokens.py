import zlib
from collections import Counter, defaultdict
from itertools import product

import numpy as np
import public_tokenizers
import pytest
from tokenizers import Tokenizer

from basisflow.llm import lengths, packing, tokens
from basisflow.llm.common import table, tidied
from basisflow.llm.tokens import WordEncoder, encoder
from helpers import awkward, empty


@pytest.fixture(scope="module")
def reference():
    t = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    return lambda texts: [e.ids for e in t.encode_batch([x or "" for x in texts], add_special_tokens=False)]


ODD = ["Σίσυφος ΣΑΣ. ΣΑΣ", "İstanbul, Ǆ é! É. don't I'LL, we'RE 'S.,x |a| ... a...b x!!y 12.5, <|endoftext|>. ﬁ KK ÅÅ", "hello <|endoftext|> world, X<|startoftext|>Yz.<|endoftext|>, <|EndOfText|> <|endoftext| |endoftext|>", "<|startoftext|>", "", "  ", "a\x0bb\x0cc\x1cd e f", "é, É. ß? ẞ! 漢字。漢字 a.b.c, 'tis", "́x x́, Å"]


@pytest.mark.parametrize("cache", [600_000, 50])
def test_cached_ids_are_the_tokenizers(small, spark, reference, cache):
    texts = ODD + [r.text for r in table(spark, small, "documents").select("text").collect()]
    got = [np.frombuffer(x, "<u2").tolist() for x in WordEncoder(cache=cache).packed([t.encode() for t in texts])]
    assert got == reference(texts)


def test_words_with_any_marks_are_cut_like_the_tokenizer(reference):
    texts = [f"word{m} Élan{m}{m[::-1]} 1{m} a{m}b <|endoftext|>{m}" for m in ("&&&", "***", "%%%", "$$$", "###", "_", "-", "=+", "~^@", "/", "()", "[]{}", '"', "?!&", "'", "'s", "<", ">")]
    encoder = WordEncoder(cache=50)
    got = [np.frombuffer(x, "<u2").tolist() for x in encoder.packed([t.encode() for t in texts])]
    assert got == reference(texts)
    assert b"***" in WordEncoder(cache=50)._cut(b"word***")


def test_a_task_of_another_kind_frees_the_encoder():
    assert encoder() is encoder()
    list(tidied(lambda batches: iter(batches), "encoders")([]))
    assert tokens._ENCODERS
    list(tidied(lambda batches: iter(batches))([]))
    assert not tokens._ENCODERS


def test_points_on_the_curve_are_exact_means():
    rows = packing.token_vectors()
    ids = np.random.default_rng(5).integers(0, 1 << 16, 70_001).astype("<u2")
    bytes_ = (rows[ids][:, None] >> (np.uint64(16) * np.arange(4, dtype=np.uint64)) & np.uint64(0xFFFF)).astype(np.int64)
    mean = bytes_.sum(0) / 127.5 / len(ids) - 1
    assert packing.curve_key(ids, rows).tolist() == np.minimum((np.clip(mean * 2 + 0.5, 0, 1) * (1 << 15)).astype(np.int64), (1 << 15) - 1).tolist()


def check_packing(docs, reference):
    rows = docs.select("doc_id", "text").collect()
    want = Counter((r.doc_id, tuple([*ids, 1])) for r, ids in zip(rows, reference([r.text for r in rows]), strict=True))
    pieces = packing.pack(docs, with_ids=True).collect()
    seqs, docs_of = defaultdict(list), defaultdict(list)
    for p in pieces:
        assert zlib.crc32(np.array(p.ids, "<u4").tobytes()) == p.ids_crc32 and len(p.ids) == p.length
        seqs[p.sequence_id].append((p.offset, p.length))
        docs_of[p.doc_id, p.doc_tokens].append((p.start, p.ids))
    sizes = []
    for parts in seqs.values():
        parts.sort()
        at = 0
        for offset, length in parts:
            assert offset == at
            at += length
        sizes.append(at)
    assert all(s == 2048 or s & (s - 1) == 0 for s in sizes) and max(sizes, default=0) <= 2048
    assert sum(sizes) == sum(len(k[1]) * n for k, n in want.items())
    assert sum(p.length for p in pieces) == sum(sizes)
    for (doc, tokens), n in want.items():
        if n == 1 and sum(1 for d, t in want if d == doc and len(t) == len(tokens)) == 1:
            assert [i for _, ids in sorted(docs_of[doc, len(tokens)]) for i in ids] == list(tokens)


def test_packing(spark, small, reference):
    check_packing(table(spark, small, "documents"), reference)


def test_packing_awkward(spark, reference):
    check_packing(awkward(spark), reference)
    check_packing(spark.createDataFrame(list(enumerate(ODD)), "doc_id long, text string"), reference)
    assert packing.pack(empty(spark)).count() == 0


def test_neighbours_on_the_curve_share_words(spark, small):
    """Documents that follow each other on the line are more alike than documents at random."""
    docs = {r.doc_id: set((r.text or "").lower().split()) for r in table(spark, "/root/testdata/sf0.01", "documents").collect()}
    order = [r.doc_id for r in packing.pack(table(spark, "/root/testdata/sf0.01", "documents")).where("start = 0").orderBy("sequence_id", "offset").collect()]
    share = lambda pairs: np.mean([len(docs[a] & docs[b]) / max(1, len(docs[a] | docs[b])) for a, b in pairs])
    mixed = np.random.default_rng(0).permutation(order).tolist()
    assert share(zip(order, order[1:])) > 1.5 * share(zip(mixed, mixed[1:]))


def test_sequences_hold_the_pieces(spark, small):
    pieces = packing.pack(table(spark, small, "documents"), with_ids=True)
    out = packing.sequences(pieces).collect()
    assert all(len(r.ids) <= 2048 for r in out)
    assert sum(len(r.ids) for r in out) == sum(r.length for r in pieces.collect())


@pytest.mark.parametrize("dims, bits", [(2, 4), (3, 3), (4, 2)])
def test_hilbert_curve_is_a_path(dims, bits):
    points = np.array(list(product(range(1 << bits), repeat=dims)))
    index = packing.hilbert_index(points, bits)
    assert sorted(index) == list(range(len(points)))
    assert (np.abs(np.diff(points[np.argsort(index)], axis=0)).sum(1) == 1).all()


def test_rest_is_cut_into_powers_of_two():
    assert list(packing.cut(0, 2048 + 11, 2048 + 11)) == [(0, 2048, 0, 0), (2048, 8, 1, 0), (2056, 2, 2, 0), (2058, 1, 3, 0)]


def test_histogram(spark, small, reference):
    for docs in (table(spark, small, "documents"), awkward(spark), spark.createDataFrame(list(enumerate(ODD)), "doc_id long, text string")):
        n = np.array([len(i) for i in reference([r.text for r in docs.select("text").collect()])])
        hist = lengths.histogram(lengths.document_lengths(docs))
        rows = hist.collect()
        assert {r.n_tokens for r in rows} == set(n.tolist())
        for r in rows:
            assert (r.n_docs, r.docs_ge, r.tokens_ge, r.truncated_total) == ((n == r.n_tokens).sum(), (n >= r.n_tokens).sum(), n[n >= r.n_tokens].sum(), np.minimum(n, r.n_tokens).sum())
        some = [0, 1, 100, 10**6]
        assert sorted(tuple(r) for r in lengths.limits(hist, some).collect()) == [(x, (n > x).sum(), np.minimum(n, x).sum()) for x in some]
        for limit in (0, 1, 100, 10**6):
            assert lengths.truncated_total(hist, limit) == np.minimum(n, limit).sum()
        for q in (0.1, 0.5, 0.9, 1.0):
            assert lengths.quantile(hist, q) == np.sort(n)[int(np.ceil(q * len(n))) - 1]
    nothing = lengths.histogram(lengths.document_lengths(empty(spark)))
    assert nothing.count() == 0 and lengths.quantile(nothing, 0.5) is None
