"""Edited copies of benchmark items against Smith-Waterman on all pairs."""

import random

import numpy as np

from basisflow.llm import decontam


def test_edits_at_every_step_are_found_as_by_all_pairs(spark):
    rnd = random.Random(8)
    words = lambda n, v=400: [f"w{rnd.randint(1, v)}" for _ in range(n)]
    items = [(i, words(n)) for i, n in enumerate((3, 4, 5, 7, 16, 16, 30, 60, 120, 200))]
    rows = []
    for _, own in items:
        for step in (3, 4, 5):
            for shift in range(step):
                rows.append(words(30) + [w if (k + shift) % step else f"new{rnd.random()}" for k, w in enumerate(own)] + words(30))
        rows.append(words(30) + [x for w in own for x in (w, "between")] + words(30))
        rows.append(words(30) + [w if rnd.random() < 0.7 else rnd.choice(("", "other", f"{w} more")) for w in own] + words(30))
        rows.append(words(200, 60) + own[: len(own) * 6 // 10] + words(200, 60))
        rows.append(own + words(10) + own)
    rows = [" ".join(r).split() for r in rows]
    number: dict[str, int] = {}
    numbered = lambda text: np.array([number.setdefault(w, len(number) + 1) for w in text], np.int32)
    pairs = [(d, i) for d in range(len(rows)) for i, _ in items]
    scores = decontam.align([(numbered(items[i][1]), numbered(rows[d])) for d, i in pairs])
    want = {p: s / (2 * len(items[p[1]][1])) for p, (s, _) in zip(pairs, scores, strict=True) if s >= len(items[p[1]][1])}
    docs = spark.createDataFrame([(d, " ".join(r)) for d, r in enumerate(rows)], "doc_id long, text string")
    out = decontam.leaks(docs, spark.createDataFrame([(i, " ".join(x)) for i, x in items], "item_id long, text string")).collect()
    assert {(r.doc_id, r.item_id): r.score for r in out} == want and len(want) > 120
