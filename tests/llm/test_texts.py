"""Decontamination, fingerprints, suffix and SimHash deduplication against plain Python."""

import hashlib
import random

import numpy as np
import pyarrow as pa
import pytest

from basisflow.llm import components, decontam, merkle, simhash, suffixes
from basisflow.llm.common import table
from helpers import awkward, empty, removed_bytes


# --- decontamination

def test_local_alignment_equals_the_textbook():
    def slow(a, b):
        h = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
        for i, x in enumerate(a):
            for j, y in enumerate(b):
                h[i + 1][j + 1] = max(0, h[i][j] + (2 if x == y else -1), h[i][j + 1] - 1, h[i + 1][j] - 1)
        return max(map(max, h))

    rnd = random.Random(5)
    pairs = [(np.array([rnd.randint(1, 4) for _ in range(rnd.randint(1, 12))], np.int32), np.array([rnd.randint(1, 4) for _ in range(rnd.randint(0, 30))], np.int32)) for _ in range(200)]
    assert [s for s, _ in decontam.align(pairs, cells=300)] == [slow(a, b) for a, b in pairs]


def test_copies_and_edited_copies_are_found(spark):
    rnd = random.Random(3)
    vocabulary = ["".join(rnd.choice("abcdefghij") for _ in range(5)) for _ in range(800)]
    words = lambda n: [rnd.choice(vocabulary) for _ in range(n)]
    items = [(i, " ".join(words(40))) for i in range(10)] + [(10, None), (11, "too short"), (0, "again " + " ".join(words(30)))]
    rows = []
    for i in range(10):
        own = items[i][1].split()
        rows.append((i, " ".join(words(200) + own + words(200))))
        edited = [w if k % 7 else rnd.choice(vocabulary) for k, w in enumerate(own)]
        rows.append((100 + i, " ".join(words(100) + edited + words(50)).upper()))
        rows.append((200 + i, " ".join(words(300))))
    rows += [(300, None), (301, ""), (None, items[3][1])]
    out = decontam.leaks(spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")).collect()
    assert {(r.doc_id, r.item_id) for r in out} == {(i, i) for i in range(10)} | {(100 + i, i) for i in range(10)} | {(None, 3)}
    assert all(r.score == 1 for r in out if r.doc_id is not None and r.doc_id < 10)
    assert all((r.first_word, r.end_word) == (200, 240) for r in out if r.doc_id is not None and r.doc_id < 10)


def test_a_very_common_passage_is_still_found(spark):
    passage = " ".join(f"w{i}" for i in range(30))
    docs = spark.createDataFrame([(i, f"a b c {passage} d{i}" if i % 2 else f"other text number {i} w1 w2 here") for i in range(200)], "doc_id long, text string")
    items = spark.createDataFrame([(1, passage)], "item_id long, text string")
    assert {r.doc_id for r in decontam.leaks(docs, items).collect()} == set(range(1, 200, 2))
    assert {r.doc_id for r in decontam.clean(docs, items).collect()} == set(range(0, 200, 2))


def test_exact_copies_on_the_tables(spark, small):
    docs, items = table(spark, small, "documents"), table(spark, small, "benchmark")
    found = {(r.doc_id, r.item_id) for r in decontam.leaks(docs, items).collect()}
    texts = {r.doc_id: r.text for r in docs.collect()}
    assert {(d, i.item_id) for i in items.collect() for d, t in texts.items() if i.text in t} <= found


def test_decontamination_awkward(spark):
    items = spark.createDataFrame([(1, "quick brown fox jumps over the lazy dog near the river bank")], "item_id long, text string")
    assert {r.doc_id for r in decontam.leaks(awkward(spark), items).collect()} == {6, 7}
    kept = decontam.clean(awkward(spark), items)
    assert kept.count() == awkward(spark).count() - 2 and kept.columns == awkward(spark).columns
    assert decontam.leaks(empty(spark), items).count() == 0
    assert decontam.leaks(awkward(spark), items.limit(0)).count() == 0


# --- Merkle fingerprints

def merkle_root(written):
    """Root of a written tree, by the documented rule alone."""
    import xxhash

    def above(children, width):
        return xxhash.xxh3_128_intdigest(b"".join(h.to_bytes(width, "little") + n.to_bytes(8, "little") for h, n in children), 20), sum(n for _, n in children)

    return "%032x" % above([above([above(pieces, 8) for pieces in section], 16) for section in written], 16)[0]


def plain_likeness(a, b):
    """Characters under equal branches, from the written trees: sections, then paragraphs, then pieces."""
    if a == b:
        return 1.0
    total, shared = sum(n for t in (a, b) for s in t for p in s for _, n in p), 0
    if not a or not b:
        return 0.0
    left, right = [tuple(map(tuple, s)) for s in a], [tuple(map(tuple, s)) for s in b]
    for level in range(3):
        size = (lambda x: sum(n for p in x for _, n in p)) if level == 0 else (lambda x: sum(n for _, n in x)) if level == 1 else (lambda x: x[1])
        for node in list(left):
            if node in right:
                left.remove(node)
                right.remove(node)
                shared += size(node)
        if level < 2:
            left, right = [x for node in left for x in node], [x for node in right for x in node]
    return 2 * shared / total


def check_merkle(docs):
    import xxhash

    signed = lambda h: h - (1 << 64) if h >> 63 else h
    rows = sorted(((r.doc_id, r.text or "") for r in docs.select("doc_id", "text").collect()), key=lambda r: (r[0] is None, -(r[0] or 0), signed(xxhash.xxh64_intdigest(r[1].encode(), 42)), r[1]))
    want = []
    for i, (doc, text) in enumerate(rows):
        following = rows[(i + 1) % len(rows)][1]
        half = len(text) // 2
        changed = text[: len(text) - half] + following[:half]
        trees = [merkle.tree(x) for x in (text, changed, following)]
        want.append((str(doc), len(text), hashlib.sha256(changed.encode()).hexdigest(), merkle_root(trees[0]), merkle_root(trees[1]), plain_likeness(*trees[:2]), plain_likeness(trees[0], trees[2])))
    got = [(str(r.doc_id), r.n_chars, r.edited_sha256, r.fingerprint[:32], r.edited_fingerprint[:32], r.near_edited, r.near_next) for r in merkle.edited_neighbours(docs).collect()]
    assert sorted(got) == sorted(want)
    for r in merkle.edited_neighbours(docs).collect():
        spans = [tuple(map(int, x.split(":"))) for x in r.edited_spans.split(",") if x]
        assert all(a < b for a, b in spans) and not (spans and r.fingerprint == r.edited_fingerprint)
        pieces = [q for s in merkle.parsed(r.fingerprint) for p in s for q in p]
        gone, at = [], 0
        for q in (q for s in merkle.parsed(r.edited_fingerprint) for p in s for q in p):
            if q in pieces:
                pieces.remove(q)
            else:
                gone += range(at, at + q[1])
            at += q[1]
        assert gone == [i for a, b in spans for i in range(a, b)]


def test_roots_follow_from_what_is_written(spark):
    for r in merkle.fingerprints(awkward(spark)).collect():
        assert merkle_root(merkle.parsed(r.fingerprint)) == r.fingerprint[:32] == merkle.Tree(merkle.parsed(r.fingerprint)).root


def test_one_id_with_a_third_of_the_rows_is_split(spark):
    rows = [(7 if i % 3 == 0 else None if i % 7 == 0 else i, f"text {i} " * 20) for i in range(600)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    check_merkle(docs)
    stretches = merkle.Stretches(docs.selectExpr("doc_id", "xxhash64(text) hash", "text"), 8)
    found = stretches(*(pa.array(c, pa.int64()) for c in zip(*((r.doc_id, r.h) for r in docs.selectExpr("doc_id", "xxhash64(text) h").collect()), strict=True)))
    assert np.unique(found, return_counts=True)[1].max() <= 60


def test_merkle_on_the_tables(spark, small):
    check_merkle(table(spark, small, "documents"))


def test_merkle_awkward(spark):
    check_merkle(awkward(spark))
    check_merkle(spark.createDataFrame([(1, "alone")], "doc_id long, text string"))
    assert merkle.edited_neighbours(empty(spark)).count() == 0


def test_tree_covers_the_text_and_locates_edits():
    text = "One line of words here.\nAnother line of words there, longer.\n\nA second section starts and goes on for a while.\n" * 5
    tree = merkle.Tree(text)
    assert sum(n for s in merkle.tree(text) for p in s for _, n in p) == len(text)
    assert merkle.parsed(tree.fingerprint()) == merkle.tree(text)
    at = len(text) // 2
    other = merkle.Tree(text[:at] + "CHANGED" + text[at:])
    spans = merkle.differences(other, tree)
    assert len(spans) == 1 and spans[0][0] <= at and spans[0][1] >= at + 7
    assert 0.8 < merkle.likeness(tree, other) < 1 and merkle.likeness(tree, merkle.Tree(text)) == 1


# --- suffix arrays

def plain_repeats(texts, least):
    places = {}
    for t, x in enumerate(texts):
        for i in range(len(x)):
            for j in range(i + least, len(x) + 1):
                places.setdefault(x[i:j], []).append((t, i))
    out = set()
    for s, at in places.items():
        left = {texts[t][i - 1 : i] if i else (t, i) for t, i in at}
        right = {texts[t][i + len(s) : i + len(s) + 1] or (t, i) for t, i in at}
        if len(at) > 1 and len(left) > 1 and len(right) > 1:
            out.add((len(s), tuple(sorted(at))))
    return out


@pytest.mark.parametrize("seed", range(40))
def test_maximal_repeats(seed):
    rnd = random.Random(seed)
    texts = [bytes(rnd.choice(b"ab") for _ in range(rnd.randint(0, 14))) for _ in range(rnd.randint(0, 4))]
    assert {(n, tuple(sorted(at))) for n, at in suffixes.maximal_repeats(texts, 2)} == plain_repeats(texts, 2)


def check_removed(docs, **sizes):
    want = removed_bytes([(r.doc_id, r.text) for r in docs.select("doc_id", "text").collect()])
    got = [(str(r.doc_id), r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffixes.removed(docs, **sizes).collect()]
    assert sorted(got) == sorted((str(d), n, g, s, hashlib.sha256(k).hexdigest()) for d, n, g, s, k in want)


def test_removal_on_the_tables(spark, small):
    check_removed(table(spark, small, "documents"))


def test_removal_awkward(spark):
    check_removed(awkward(spark))
    assert suffixes.removed(empty(spark)).count() == 0


def mosaics():
    rnd = random.Random(1)
    parts = ["".join(rnd.choice("abc \x00é") for _ in range(rnd.randint(20, 80))) for _ in range(40)] + ["ab" * 60, "a" * 120]
    return [(i // 2 if i % 9 == 0 else i, "".join(rnd.choice(parts) for _ in range(rnd.randint(0, 12)))) for i in range(150)]


@pytest.mark.parametrize("sizes", [{}, {"chunk": 3000, "held": 9000, "hot": 4000}])
def test_removal_of_mosaics(spark, sizes):
    """Texts put together from shared parts of about the least length, periods and zero bytes; in small chunks and buckets too."""
    check_removed(spark.createDataFrame(mosaics(), "doc_id long, text string"), **sizes)


def test_hot_anchors_are_divided(spark):
    """One phrase in every text among different words: its bucket is dealt out by sides, then by windows."""
    rnd = random.Random(7)
    words = [f"{rnd.randint(0, 30):x}" * 3 for _ in range(40)]
    rows = [(i, " ".join(rnd.choice(words) for _ in range(9)) + " the common phrase is this " + " ".join(rnd.choice(words) for _ in range(9))) for i in range(400)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    for hot in (2000, 300):
        check_removed(docs, held=5000, hot=hot)


def test_equal_hashes_are_compared(monkeypatch):
    """Were all hashes equal, contexts would still be told apart by their bytes."""
    bodies = [b"a" * 60, b"b" * 60, b"a" * 60, b"a" * 61]
    n = len(bodies)
    contexts = suffixes.Contexts(np.arange(n), np.zeros(n, np.int64), np.zeros(n), np.array([len(b) for b in bodies]), np.zeros(n), np.frombuffer(b"".join(bodies), np.uint8))
    monkeypatch.setattr(suffixes, "context_hashes", lambda eights, starts, sizes: np.zeros(len(starts), np.uint64))
    spans, open_ = suffixes.settled_copies(contexts)
    assert open_.tolist() == [0, 1, 3] and [x.tolist() for x in spans] == [[2], [0], [0], [60]]


def test_groups_hold_all_occurrences(spark):
    """Every group is a string of 50 bytes or more with exactly its occurrences; every repeated window lies in one."""
    rows = [(d, t) for d, t in dict(mosaics()).items()] + [(1000 + i, "a passage of more than fifty bytes that stands in many texts, all the same") for i in range(30)]
    groups = {}
    for r in suffixes.repeat_groups(spark.createDataFrame(rows, "doc_id long, text string")).collect():
        groups.setdefault((r.repeat, r.length), set()).add((r.doc_id, r.start))
    bodies = {d: t.encode() for d, t in rows}
    covered = set()
    for (_, length), at in groups.items():
        strings = {bodies[d][p : p + length] for d, p in at}
        assert len(strings) == 1 and length >= 50 and len(at) > 1
        string = strings.pop()
        everywhere = {(d, i) for d, b in bodies.items() for i in range(len(b) - length + 1) if b[i : i + length] == string}
        assert at == everywhere
        covered |= {(d, p + i) for d, p in at for i in range(length - 49)}
    windows = {}
    for d, b in bodies.items():
        for i in range(len(b) - 49):
            windows.setdefault(b[i : i + 50], []).append((d, i))
    assert covered == {x for at in windows.values() if len(at) > 1 for x in at}


# --- SimHash

def test_fingerprint_is_the_contracts():
    import xxhash

    text = "The  quick\tBROWN fox É jumps".encode()
    words = text.lower().split()
    hashes = [xxhash.xxh64_intdigest(b" ".join(words[i : i + 3]), 42) for i in range(len(words) - 2)]
    want = sum(1 << b for b in range(64) if sum(h >> b & 1 for h in hashes) * 2 > len(hashes))
    assert simhash.fingerprint(text) == want
    assert simhash.fingerprint(b"Two words") == xxhash.xxh64_intdigest(b"two words", 42)
    assert simhash.fingerprint(b" \t\n") == 0


def closure(ids, fps, apart=2):
    root = list(range(len(ids)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(ids)):
        for j in np.nonzero(np.bitwise_count(fps[i] ^ fps[i + 1 :]) <= apart)[0]:
            a, b = find(i), find(i + 1 + j)
            root[max(a, b)] = min(a, b)
    return {ids[i]: ids[find(i)] for i in range(len(ids))}


def test_links_lose_nothing(spark):
    rnd = random.Random(2)
    centres = [rnd.getrandbits(64) for _ in range(20)]
    values = sorted({c ^ sum(1 << b for b in rnd.sample(range(64), rnd.randint(0, 3))) for c in centres for _ in range(30)})
    signed = [v - (1 << 64) if v >> 63 else v for v in values]
    got = {frozenset(r) for r in simhash.links(spark.createDataFrame([(v,) for v in signed], "fp long")).collect()}
    assert got == {frozenset((a, b)) for i, a in enumerate(signed) for b in signed[i + 1 :] if bin((a ^ b) & ((1 << 64) - 1)).count("1") <= 2}


def test_groups_on_the_tables(spark, small):
    docs = table(spark, small, "documents")
    rows = sorted((r.doc_id, r.text) for r in docs.collect())
    fps = np.array([simhash.fingerprint(t.encode()) for _, t in rows], np.uint64)
    got = {r.doc_id: (r.fingerprint, r.component_id) for r in simhash.near_groups(docs).collect()}
    roots = closure([d for d, _ in rows], fps)
    assert got == {d: (format(int(f), "016x"), roots[d]) for (d, _), f in zip(rows, fps, strict=True)}


def test_simhash_awkward(spark):
    got = [(r.doc_id, r.fingerprint, r.component_id) for r in simhash.near_groups(awkward(spark)).collect()]
    by_id = {d: (f, c) for d, f, c in got if d is not None}
    assert len(got) == 12 and by_id[1] == by_id[2] and by_id[2][1] == 1
    assert by_id[3] == by_id[4] == by_id[5] == ("0" * 16, 3)
    kept = sorted(str(r.doc_id) for r in simhash.keep_one(awkward(spark)).collect())
    assert kept.count("1") == 1 and "2" not in kept and "4" not in kept and kept.count("None") == 1
    assert simhash.near_groups(empty(spark)).count() == 0


def test_rows_without_id_take_part_in_links(spark, monkeypatch):
    """A chain 1 - null - 2 of fingerprints two bits apart is one group."""
    fps = spark.createDataFrame([(1, 0b0000), (None, 0b0011), (2, 0b1111), (None, 7 << 40)], "doc_id long, fp long")
    monkeypatch.setattr(simhash, "signatures", lambda *_: fps)
    got = {(r.doc_id, r.fingerprint[-1], r.component_id) for r in simhash.near_groups(fps).collect()}
    assert got == {(1, "0", 1), (None, "3", 1), (2, "f", 1), (None, "0", None)}


def test_components_of_paths_stars_and_loops(spark):
    links = [(i, i + 1) for i in range(40)] + [(100, 200 + i) for i in range(30)] + [(500, 500), (None, 3)]
    out = {r.node: r.root for r in components.components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert out == {i: 0 for i in range(1, 41)} | {200 + i: 100 for i in range(30)}
    assert components.components(spark.createDataFrame([], "a long, b long")).count() == 0
