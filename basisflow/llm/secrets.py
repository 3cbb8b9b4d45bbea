"""Secret scans over a trigram inverted index, in DataFrame functions only.

Each rule's regex gives a Boolean trigram query (``trigrams.derive``). The index
holds a posting (trigram, document) for every trigram that some query names.
Postings are intersected per document; a rule's regex then runs only on
its candidates. Rules whose query is ``True`` run on every document.

Defined results: null text counts as empty; empty texts have no spans; rows with
equal or null ids are each scanned and returned once; an empty table gives no
rows; columns besides id and text are ignored by ``scan`` and kept by ``redact``.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import trigrams
from .common import fresh, small_side, written

#: Steps put together in one piece by the two-level running sum, and characters of one block of a text that is cut up.
BLOCK, STRETCH = 256, 4096


@dataclass(frozen=True)
class Rule:
    """A match counts if its ``group`` has ``least`` characters or more."""

    kind: str
    pattern: str
    group: int = 0
    least: int = 1

    @property
    def query(self):
        """Two trigrams of each conjunction are enough to be selective here, and cost less to index."""
        return trigrams.thinned(trigrams.derive(self.pattern))


#: The kinds of the contract, in its order. For ``access`` and
#: ``hex`` the least length stands in the pattern: their matches are maximal runs,
#: so a shorter match never hides a longer one.
BASE_RULES = (
    Rule("assign", r"""(?i:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 8),
    Rule("access", r"AKIA[A-Z0-9]{12,}"),
    Rule("hex", r"[0-9a-f]{32,}"),
)
#: Well-known public token formats, reported besides the base kinds.
EXTRA_RULES = (
    Rule("github", r"gh[pousr]_[A-Za-z0-9]{36,}"),
    Rule("slack", r"xox[abprs]-[A-Za-z0-9-]{10,}"),
    Rule("google", r"AIza[0-9A-Za-z_-]{35}"),
    Rule("pem", r"-----BEGIN [A-Z ]*PRIVATE KEY-----"),
    Rule("jwt", r"eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]+"),
)
RULES = BASE_RULES + EXTRA_RULES


def postings(docs: DataFrame, rules=RULES, key: str = "doc_id", text: str = "text") -> DataFrame:
    """The index, as rows (key, trigram), for the trigrams that the rules name."""
    needed = sorted(set().union(*(trigrams.trigrams_of(r.query) for r in rules)))
    low = docs.select(F.col(key).alias("key"), F.lower(F.col(text)).alias("low"))
    present = F.array_compact(F.array(*(F.when(F.contains("low", F.lit(t)), F.lit(t)) for t in needed))) if needed else F.array().cast("array<string>")
    return low.select("key", F.explode(present).alias("trigram"))


def candidates(index: DataFrame, rules=RULES) -> DataFrame:
    """Intersects postings: (key, kinds) of documents that satisfy some rule's query."""
    lists = index.groupBy("key").agg(F.collect_set("trigram").alias("present"))
    kinds = [F.when(_holds(r.query), F.lit(r.kind)) for r in rules if r.query is not True]
    found = lists.select("key", F.array_compact(F.array(*kinds)).alias("kinds")) if kinds else lists.select("key", F.array().cast("array<string>").alias("kinds"))
    return found.where(F.size("kinds") > 0)


def _holds(query) -> Column:
    if query[0] == "tri":
        return F.array_contains("present", query[1])
    parts = [_holds(q) for q in query[1]]
    out = parts[0]
    for part in parts[1:]:
        out = out & part if query[0] == "all" else out | part
    return out


def _let(value: Column, body) -> Column:
    """``body`` of a value that is worked out once."""
    return F.element_at(F.transform(F.array(value), body), 1)


def _running(steps: Column, put=lambda acc, x: acc + x) -> Column:
    """Inclusive running sums (or maxima) of non-negative numbers, in blocks, so that long lists stay cheap."""
    blocks = F.transform(F.sequence(F.lit(0), F.ceil(F.size(steps) / BLOCK).cast("int") - 1), lambda b: F.slice(steps, b * BLOCK + 1, F.lit(BLOCK)))
    whole = lambda part: F.aggregate(part, F.lit(0).cast("long"), lambda acc, x: put(acc, x.cast("long")))
    before = lambda sums: F.transform(sums, lambda _, i: whole(F.slice(sums, F.lit(1), i)))
    within = lambda block, first: F.transform(block, lambda _, i: put(first, whole(F.slice(block, F.lit(1), i + 1))))
    return _let(blocks, lambda bs: F.flatten(F.zip_with(bs, _let(F.transform(bs, whole), before), within)))


def rule_matches(text: Column, rule: Rule) -> Column:
    """Of the leftmost non-overlapping matches: lengths, lengths of the checked group, and the gap before each; null if there are none."""
    sizes = lambda parts: F.transform(parts, lambda p: F.char_length(p))
    found = lambda group: sizes(F.regexp_extract_all(text, F.lit(rule.pattern), F.lit(group)))
    fields = F.struct(found(0).alias("n"), found(rule.group).alias("checked"), sizes(F.split(text, rule.pattern, -1)).alias("gaps"))
    return F.when(text.rlike(rule.pattern), fields)


def rule_spans(matches: Column, rule: Rule, order: int) -> Column:
    """Matches that are long enough, as structs (start, rank, kind, end) in code points."""
    steps = F.zip_with(F.slice(matches["gaps"], F.lit(1), F.size(matches["n"])), F.slice(F.concat(F.array(F.lit(0)), matches["n"]), F.lit(1), F.size(matches["n"])), lambda gap, last: gap + last)
    ends = F.zip_with(_let(steps, lambda s: _running(s)), matches["n"], lambda start, n: F.struct(start.alias("start"), (start + n).alias("end")))
    spans = F.zip_with(ends, matches["checked"], lambda x, n: F.struct(x["start"].cast("long").alias("start"), F.lit(order).alias("rank"), F.lit(rule.kind).alias("kind"), x["end"].cast("long").alias("end"), (n >= rule.least).alias("ok")))
    return F.when(matches.isNotNull(), F.transform(F.filter(spans, lambda s: s["ok"]), lambda s: s.dropFields("ok")))


def with_spans(docs: DataFrame, rules=RULES, key: str = "doc_id", text: str = "text", out: str = "secret_spans") -> DataFrame:
    """Adds the sorted array of spans to every row."""
    name, kinds, whole = fresh("key"), fresh("kinds"), fresh("text")
    found = small_side(written(candidates(postings(docs, rules, key, text), rules), "secret-candidates"))
    found = found.select(F.col("key").alias(name), F.col("kinds").alias(kinds))
    joined = docs.withColumn(whole, F.coalesce(F.col(text), F.lit(""))).join(found, F.col(key).eqNullSafe(F.col(name)), "left")
    found = {}
    for rule in rules:
        matches = rule_matches(F.col(whole), rule)
        found[fresh(rule.kind)] = matches if rule.query is True else F.when(F.array_contains(kinds, rule.kind), matches)
    lists = [rule_spans(F.col(column), rule, order) for order, (column, rule) in enumerate(zip(found, rules, strict=True))]
    spans = F.array_sort(F.flatten(F.array_compact(F.array(*lists))))
    return joined.withColumns(found).withColumn(out, spans).drop(name, kinds, whole, *found)


def _of_rank(rank: int):
    return lambda span: span["rank"] == rank


def joined_spans(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")


def scan(docs: DataFrame, rules=RULES, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per document: counts of the base kinds, their digest, all spans."""
    found = with_spans(docs.select(key, text), rules, key, text).select(key, "secret_spans")
    base = F.filter("secret_spans", lambda s: s["rank"] < len(BASE_RULES))
    counts = [F.size(F.filter("secret_spans", _of_rank(i))).cast("long").alias(f"n_{r.kind}") for i, r in enumerate(BASE_RULES)]
    return found.select(key, *counts, F.sha2(joined_spans(base), 256).alias("base_sha256"), joined_spans(F.col("secret_spans")).alias("spans"))


def between(blocks: Column, start: Column, end: Column) -> Column:
    """The characters from ``start`` to ``end`` of a text that is given as blocks of ``STRETCH`` characters."""
    first, last = F.floor(start / STRETCH).cast("int"), F.floor(end / STRETCH).cast("int")
    at, stop = (start % STRETCH).cast("int"), (end % STRETCH).cast("int")
    block = lambda i: F.coalesce(F.get(blocks, i), F.lit(""))
    within = F.substr(block(first), at + 1, stop - at)
    across = F.concat(F.substr(block(first), at + 1), F.array_join(F.slice(blocks, first + 2, last - first - 1), ""), F.substr(block(last), F.lit(1), stop))
    return F.when(start >= end, "").when(first == last, within).otherwise(across)


def redact(docs: DataFrame, rules=RULES, key: str = "doc_id", text: str = "text", mark: str = "[SECRET]") -> DataFrame:
    """Replaces every span by ``mark``; overlapping spans become one. Other columns stay.

    In time proportional to the text and to the spans: texts are cut into blocks once,
    and what lies before each span is put together from them.
    """
    name = fresh("spans")
    found = with_spans(docs, rules, key, text, name)
    spans, size = F.col(name), F.char_length(text).cast("long")
    starts, ends = F.transform(spans, lambda s: s["start"]), F.transform(spans, lambda s: s["end"])
    reached = lambda tops: F.concat(F.array(F.lit(0).cast("long")), tops)

    def pieces(blocks: Column, tops: Column) -> Column:
        parts = F.zip_with(starts, F.slice(tops, F.lit(1), F.size(starts)), lambda start, top: F.when(start >= top, F.concat(between(blocks, top, start), F.lit(mark))).otherwise(""))
        return F.concat(F.array_join(parts, ""), between(blocks, F.element_at(tops, -1), size))

    blocks = F.regexp_extract_all(F.col(text), F.lit(f"(?s).{{1,{STRETCH}}}"), F.lit(0))
    clean = _let(blocks, lambda b: _let(reached(_running(ends, F.greatest)), lambda tops: pieces(b, tops)))
    return found.withColumn(text, F.when(F.size(spans) > 0, clean).otherwise(F.col(text))).drop(name)
