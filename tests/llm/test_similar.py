"""Near-duplicates by shingles against all pairs."""

import random

import pytest

from basisflow.llm import similar, simhash


def similarity(a, b, width=5):
    a, b = ({tuple(t[i : i + width]) for i in range(max(1, len(t) - width + 1))} for t in (a.split(), b.split()))
    return len(a & b) / len(a | b)


def edited(rnd, words, n):
    out = list(words)
    for at in rnd.sample(range(len(out)), n):
        out[at] = f"new{rnd.random()}"
    return " ".join(out)


def test_edited_copies_go_and_others_stay(spark):
    rnd = random.Random(4)
    rows, wanted, links = [], set(), 0
    for i in range(60):
        words = [f"w{rnd.randint(1, 3000)}" for _ in range(rnd.choice((60, 200, 1000)))]
        rows.append((10 * i, " ".join(words)))
        for k in range(1, 4):
            rows.append((10 * i + k, edited(rnd, words, max(1, len(words) * k // 60))))
            close = [j for j in range(10 * i, 10 * i + k) if similarity(dict(rows)[j], rows[-1][1]) >= 0.8]
            links += bool(close)
            wanted |= set() if close else {rows[-1][0]}
        wanted.add(10 * i)
    assert links > 50 and len(wanted) > 80
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert {r.doc_id for r in simhash.keep_one(docs).collect()} == wanted


def test_a_large_star_of_edited_copies_is_one_group(spark):
    rnd = random.Random(6)
    words = [f"w{rnd.randint(1, 3000)}" for _ in range(400)]
    rows = [(500, " ".join(words))] + [(i, edited(rnd, words, 8)) for i in range(300)] + [(900 + i, edited(rnd, words, 200)) for i in range(20)]
    source = dict(rows)[500]
    near = [i for i, t in rows if similarity(source, t) >= 0.8]
    found = {r.doc_id: r.component_id for r in similar.groups(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert len(near) > 250 and sum(found[i] == min(near) for i in near) >= 0.99 * len(near)
    assert all(found[i] == i for i, _ in rows if i >= 900)


@pytest.mark.parametrize("block", [1000, 15])
def test_large_buckets_lose_no_link(spark, monkeypatch, block):
    """Chains of edited copies that share their keys with many others: every link across them counts, as by all pairs."""
    monkeypatch.setattr(similar, "BLOCK_NODES", block)
    rnd = random.Random(9)
    base = [f"w{rnd.randint(1, 3000)}" for _ in range(300)]
    rows, number = [], 0
    for _ in range(12):  # chains: each text is near the one before, further from the others
        words = list(base)
        for at in rnd.sample(range(300), 10):
            words[at] = f"own{rnd.random()}"
        for _ in range(8):
            rows.append((number, " ".join(words)))
            number += 1
            for at in rnd.sample(range(300), 4):
                words[at] = f"new{rnd.random()}"
    root = list(range(number))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(number):
        for j in range(i):
            if similarity(rows[i][1], rows[j][1]) >= 0.8:
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    found = {r.doc_id: r.component_id for r in similar.groups(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert found == {i: find(i) for i in range(number)} and 1 < len(set(found.values())) < number


def test_fingerprint_links_are_candidates_and_verified(spark):
    """Without any key of minima op8's links are still found; those that the shingles refuse join nothing."""
    rnd = random.Random(12)
    words = [f"w{rnd.randint(1, 3000)}" for _ in range(3000)]
    lines = "one two three " * 300
    rows = [(1, " ".join(words)), (2, edited(rnd, words, 1)), (3, lines + " ".join(f"a{i}" for i in range(40))), (4, lines + " ".join(f"b{i}" for i in range(40))), (5, " ".join(words[:500]))]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    nodes = similar.sketches(docs).selectExpr("doc_id AS node", "CAST(array() AS array<long>) AS bands", "sketch", "array(fp) AS fps")
    assert {(r.x, r.y) for r in similar.fingerprint_pairs(nodes).collect()} == {(1, 2), (3, 4)}
    found = similar.links(nodes, docs.withColumnRenamed("doc_id", "node"))
    assert {(r.node, r.root) for r in found.collect()} == {(2, 1)}


def test_keep_one_of_repeated_and_null_ids(spark):
    text = " ".join(f"w{i}" for i in range(60))
    rows = [(5, text, "a"), (5, "another text with words of its own", "b"), (None, text + " more", "c"), (None, "only here and nowhere else", "d"), (None, "only here and nowhere else", "e"), (7, text, "f")]
    out = simhash.keep_one(spark.createDataFrame(rows, "doc_id long, text string, row string"))
    got = sorted(r.row for r in out.collect())
    assert out.columns == ["doc_id", "text", "row"] and got[:2] == ["a", "b"] and len(got) == 3
