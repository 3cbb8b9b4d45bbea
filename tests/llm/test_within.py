"""Which texts are shuffled follows from counts of rows, and drops or keeps none wrongly."""

import random

import pytest

from basisflow.llm import common, similar, simhash


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("most", [500_000, 20])
def test_texts_to_verify_are_picked_without_a_shuffle_of_all(spark, monkeypatch, most):
    """However large Spark takes the table of pairs to be; before, beyond its threshold every text was shuffled."""
    monkeypatch.setattr(common, "BROADCAST_ROWS", most)
    seen = {}
    monkeypatch.setattr(similar, "written", lambda df, label: common.written(seen.setdefault(label, df), label))
    words = " ".join(f"w{i}" for i in range(100))
    texts = spark.createDataFrame([(i, f"{words} end{i}" if i % 10 else f"{i} alone") for i in range(300)], "node long, text string")
    texts = common.written(texts, "given")
    pairs = spark.createDataFrame([(i, i + 1) for i in range(1, 200, 2)], "x long, y long")
    threshold = "spark.sql.autoBroadcastJoinThreshold"
    spark.conf.set(threshold, -1)
    try:
        found = {(r.x, r.y) for r in similar.verified(pairs, texts, 0.8).collect()}
    finally:
        spark.conf.unset(threshold)
    assert found == {(i, i + 1) for i in range(1, 200, 2) if (i + 1) % 10}
    assert "BroadcastHashJoin" in plan(seen["similar-texts"]) and "SortMergeJoin" not in plan(seen["similar-texts"])


@pytest.mark.parametrize("most", [500_000, 40])
def test_rows_within_and_without(spark, monkeypatch, most):
    monkeypatch.setattr(common, "BROADCAST_ROWS", most)
    rnd = random.Random(3)
    numbers = [None, -(1 << 63), (1 << 63) - 1, 0, *(rnd.randrange(-(1 << 63), 1 << 63) for _ in range(3000))]
    some = set(numbers[1:3] + numbers[10:400])
    rows = spark.createDataFrame([(n, "a text") for n in numbers], "number long, text string")
    keys = common.written(spark.createDataFrame([(n,) for n in some], "number long"), "keys")
    inner = [r.number for r in common.within(rows, keys, "number").collect()]
    assert some <= set(inner) and len(inner) == len(set(inner)) < 1500 and (most == 40 or set(inner) == some)
    outer = common.without(rows, keys, "number")
    assert outer.columns == rows.columns
    assert sorted((r.number for r in outer.collect()), key=str) == sorted((n for n in numbers if n not in some), key=str)


def test_keep_one_with_more_rows_than_are_broadcast(spark, monkeypatch, small):
    docs = common.table(spark, small, "documents")
    copies = docs.union(docs.selectExpr("doc_id + 1000000", *docs.columns[1:]))
    wanted = sorted(simhash.keep_one(copies).collect())
    monkeypatch.setattr(common, "BROADCAST_ROWS", 30)
    assert sorted(simhash.keep_one(copies).collect()) == wanted and 0 < len(wanted) <= docs.count() > 60
