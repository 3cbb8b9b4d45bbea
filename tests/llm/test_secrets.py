import hashlib
import re
import time

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from basisflow.llm import secrets, trigrams
from basisflow.llm.common import table
from helpers import awkward, base_spans, empty


def joined(spans):
    return ",".join(f"{kind}:{a}:{b}" for a, _, kind, b in spans)


def check(docs):
    want = sorted((d, hashlib.sha256(joined(base_spans(t)).encode()).hexdigest()) for d, t in ((-1 if r.doc_id is None else r.doc_id, r.text) for r in docs.select("doc_id", "text").collect()))
    got = sorted((-1 if r.doc_id is None else r.doc_id, r.base_sha256) for r in secrets.scan(docs).collect())
    assert got == want


def test_base_spans_equal_plain_python(spark, small):
    check(table(spark, small, "documents"))


def test_awkward_rows(spark):
    check(awkward(spark))
    assert secrets.scan(empty(spark)).count() == 0


def test_matches_that_fail_still_consume(spark):
    rows = [(1, "password=token: abcdefghij"), (2, 'API_KEY="abcdefgh" apikey : 12345678'), (3, "tokEN==abcdefg"), (4, "AKIAAKIA0123456789"), (5, "f" * 31 + "g" + "e" * 32)]
    check(spark.createDataFrame(rows, "doc_id long, text string"))


def test_many_matches(spark):
    text = " ".join("%032x" % i for i in range(900))
    check(spark.createDataFrame([(1, text)], "doc_id long, text string"))


def test_redaction_merges_overlaps_and_keeps_the_rest(spark):
    key = "0123456789abcdef" * 3
    docs = spark.createDataFrame([(1, f"a token = {key} b", "x"), (2, "clean", "y"), (3, None, "z")], "doc_id long, text string, spans string")
    out = {r.doc_id: (r.text, r.spans) for r in secrets.redact(docs).collect()}
    assert out == {1: ("a [SECRET] b", "x"), 2: ("clean", "y"), 3: (None, "z")}


def redacted(text):
    """Plain version: spans of all rules, merged where they overlap."""
    found = sorted({(m.start(), m.end()) for rule in secrets.RULES for m in re.finditer(rule.pattern, text, re.ASCII) if len(m[rule.group]) >= rule.least})
    out, at = [], 0
    for a, b in found:
        if a >= at:
            out += [text[at:a], "[SECRET]"]
        at = max(at, b)
    return "".join(out) + text[at:]


def test_redaction_equals_plain_python(spark, small):
    edge = "z" * (secrets.STRETCH - 10)
    texts = [edge + "password=abcdefgh0123", edge + "z" * 10 + "0123456789abcdef" * 600 + " end", "é😀" * 3000 + " token: abcdefghijkl " + "漢" * 5000, "f" * 64, "a" * secrets.STRETCH * 2, ""]
    docs = table(spark, small, "documents").select("doc_id", "text").union(spark.createDataFrame([(-1 - i, t) for i, t in enumerate(texts)], "doc_id long, text string"))
    got = {r.doc_id: r.text for r in secrets.redact(docs).collect()}
    assert got == {r.doc_id: redacted(r.text) for r in docs.collect()}


def test_redaction_of_very_many_spans_is_linear(spark):
    text = " ".join("%032x" % i for i in range(32_000))
    began = time.time()
    out = secrets.redact(spark.createDataFrame([(1, text)], "doc_id long, text string")).first().text
    assert out == " ".join(["[SECRET]"] * 32_000) and time.time() - began < 30


def test_redaction_keeps_columns_of_any_name(spark):
    names = "__key", "__kinds", "__text", "__spans", "key", "kinds", "spans", "secret_spans", "present"
    docs = spark.createDataFrame([(1, "a token = abcdefgh12345678", *names)], "doc_id long, text string, " + ", ".join(f"{n} string" for n in names))
    out = secrets.redact(docs)
    assert out.columns == docs.columns and out.collect() == [(1, "a [SECRET]", *names)]


def test_plan_has_no_python(spark, small):
    plan = secrets.scan(table(spark, small, "documents"))._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Pandas|Arrow", plan)


@pytest.mark.parametrize("pattern, text", [("ab+c", "xabbbc"), ("(foo|bar)baz", "barbaz"), ("a?bcd", "bcd"), ("[xy]abc", "yabc"), ("(abc){2}", "abcabc"), ("abc.*def", "abc--def")])
def test_query_holds_for_matches(pattern, text):
    grams = {text[i : i + 3] for i in range(len(text) - 2)}
    assert trigrams.satisfied(trigrams.derive(pattern), grams)


def test_queries_are_selective():
    assert trigrams.derive("[0-9a-f]{32,}") is True
    assert not trigrams.satisfied(trigrams.derive("hello|world"), {"hel", "ell"})
    assert trigrams.derive("abcd") == ("all", [("tri", "abc"), ("tri", "bcd")])


@settings(max_examples=200, deadline=None)
@given(st.lists(st.sampled_from(["a", "b", "(ab|ba)", "a+", "b?", "[ab]", ".", "(aab)*", "abb"]), min_size=1, max_size=6), st.text("ab", max_size=12))
def test_queries_never_lose_a_match(parts, text):
    pattern = "".join(parts)
    grams = {text[i : i + 3] for i in range(len(text) - 2)}
    if re.search(pattern, text):
        assert trigrams.satisfied(trigrams.derive(pattern), grams)
        assert trigrams.satisfied(trigrams.thinned(trigrams.derive(pattern)), grams)
