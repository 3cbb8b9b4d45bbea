"""Document fingerprints: Merkle trees over sections, paragraphs and pieces.

Sections end at blank lines, paragraphs at line ends; a paragraph is cut into pieces
after words that end in one of a few characters, so that an edit moves cuts only
near itself. A piece's 64-bit hash covers its text; a paragraph's, a section's and the
root's 128-bit hash cover the hashes and lengths of those below, and nothing else. Equal
roots mean equal texts. The fingerprint writes the tree out: root, then sections,
paragraphs and pieces with hashes and lengths, so the root can be worked out again
from it, and two fingerprints alone tell where texts differ.

Likeness is the share of characters under branches that both trees have: equal
branches are matched from the top (sections, then paragraphs, then pieces), each once.

Defined results: null text counts as empty; the empty text has one fixed
fingerprint, like 1 to itself and 0 to others; repeated rows and rows with null id are
separate documents, ordered after their id (descending, nulls last) by the text's hash
and then by text; an empty table gives no rows; further columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from collections import Counter

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import tidied

#: A piece: up to ``PIECE`` characters, ended early after a word with one of these last characters.
PIECE = 96
_PIECES = re.compile(r".{10,%d}?[dtnsm.,;:!?|)。！？]\s{1,64}|.{1,%d}" % (PIECE - 1, PIECE), re.S)
_SECTIONS = re.compile(r".*?\n[^\S\n]*\n+|.+", re.S)
#: Seed of all hashes.
SEED = 20
#: Bytes of text in a stretch of ids that one task reads at a time, and most partitions of the exchange.
STRETCH_BYTES, PARTITIONS = 32 << 20, 50_000


def tree(text: str) -> list[list[list[tuple[int, int]]]]:
    """Sections of paragraphs of pieces (64-bit hash, characters)."""
    digest = xxhash.xxh3_64_intdigest
    return [[[(digest(p.encode("utf-8", "surrogatepass"), SEED), len(p)) for p in _PIECES.findall(paragraph)] for paragraph in section.splitlines(True)] for section in _SECTIONS.findall(text)]


def _above(children: list[tuple[int, int]], width: int) -> tuple[int, int]:
    """(128-bit hash, characters) of a node over its children (hash of ``width`` bytes, characters)."""
    return xxhash.xxh3_128_intdigest(b"".join(h.to_bytes(width, "little") + n.to_bytes(8, "little") for h, n in children), SEED), sum(n for _, n in children)


class Tree:
    """A text's tree with the hashes of its inner nodes, from the text or from what ``parsed`` returns."""

    __slots__ = ("root", "sections", "size")

    def __init__(self, text: str | list):
        self.sections = []
        for section in tree(text) if isinstance(text, str) else text:
            paragraphs = [(*_above(pieces, 8), pieces) for pieces in section]
            self.sections.append((*_above([p[:2] for p in paragraphs], 16), paragraphs))
        root, self.size = _above([s[:2] for s in self.sections], 16)
        self.root = "%032x" % root

    def fingerprint(self) -> str:
        """``root`` and, per section, ``/`` its paragraphs, each ``:`` its pieces as hash and length in hex."""
        return self.root + "".join("/" + "".join(":" + "".join(["%016x%02x" % piece for piece in pieces]) for _, _, pieces in paragraphs) for _, _, paragraphs in self.sections)


def parsed(fingerprint: str) -> list[list[list[tuple[int, int]]]]:
    """The tree that a fingerprint writes out."""
    return [[[(int(p[i : i + 16], 16), int(p[i + 16 : i + 18], 16)) for i in range(0, len(p), 18)] for p in section.split(":")[1:]] for section in fingerprint.split("/")[1:]]


def _matched(left: list, right: list):
    """Characters under nodes (hash, characters) that both lists have, and the nodes left over on each side."""
    open_ = Counter(node[:2] for node in right)
    shared, rest, gone = 0, [], Counter()
    for node in left:
        own = node[:2]
        if open_[own] > 0:
            open_[own] -= 1
            gone[own] += 1
            shared += node[1]
        else:
            rest.append(node)
    remain = []
    for node in right:
        own = node[:2]
        if gone[own] > 0:
            gone[own] -= 1
        else:
            remain.append(node)
    return shared, rest, remain


def likeness(a: Tree, b: Tree) -> float:
    if a.root == b.root:
        return 1.0
    if not a.size or not b.size:
        return 0.0
    same, left, right = _matched(a.sections, b.sections)
    more, left, right = _matched([p for s in left for p in s[2]], [p for s in right for p in s[2]])
    last, _, _ = _matched([x for p in left for x in p[2]], [x for p in right for x in p[2]])
    return 2 * (same + more + last) / (a.size + b.size)


def differences(a: Tree, b: Tree) -> list[tuple[int, int]]:
    """(start, end) in ``a`` of the pieces that ``b`` does not have, next to each other merged: where edits are."""
    if a.root == b.root:
        return []
    theirs = Counter(x for s in b.sections for p in s[2] for x in p[2])
    out, at = [], 0
    for piece in (x for s in a.sections for p in s[2] for x in p[2]):
        if theirs[piece] > 0:
            theirs[piece] -= 1
        elif out and out[-1][1] == at:
            out[-1] = (out[-1][0], at + piece[1])
        else:
            out.append((at, at + piece[1]))
        at += piece[1]
    return out


def edited(text: str, following: str) -> str:
    """The last half (rounded down) replaced by as many first characters of the following text, or all of it."""
    half = len(text) // 2
    return text[: len(text) - half] + following[:half]


def fingerprints(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, n_chars, fingerprint)."""

    def run(batches):
        for batch in batches:
            texts = [t or "" for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([len(t) for t in texts], pa.int64()), pa.array([Tree(t).fingerprint() for t in texts], pa.string())], ["doc_id", "n_chars", "fingerprint"])

    return docs.select(F.col(key).cast("long"), text).mapInArrow(tidied(run), "doc_id long, n_chars long, fingerprint string")


class Stretches:
    """Numbers of stretches of the corpus, in descending order of ids: cuts between ids, and hash ranges of ids with very many rows."""

    def __init__(self, rows: DataFrame, partitions: int):
        sums = rows.agg(F.count("*"), F.sum(F.octet_length("text"))).first()
        count, size = sums[0], sums[1] or 0
        wanted = max(4 * partitions, min(-(-size // STRETCH_BYTES), 4 * PARTITIONS))
        most = max(1, 2 * count // wanted)
        # fewer than ``wanted`` ids have so many rows
        hot = rows.groupBy("doc_id").agg(F.count("*").alias("n")).where(F.col("n") > max(most, 1)).collect()
        self.parts = {r["doc_id"]: -(-r["n"] // most) for r in hot}
        found = rows.agg(F.percentile_approx("doc_id", [i / wanted for i in range(1, wanted)], 100_000)).first()[0] or []
        alone = {x for d in self.parts if d is not None for x in (d - 1, d)}  # a hot id has stretches of its own
        self.cuts = np.array(sorted({*found, *alone}), np.int64)
        self.partitions = wanted // 4
        self._hot = np.array(sorted(d for d in self.parts if d is not None), np.int64)
        self._share = np.array([self.parts[d] for d in self._hot.tolist()], np.int64)
        self._most = max([1, *self.parts.values()])

    def __call__(self, ids: pa.Array, hashes: pa.Array) -> np.ndarray:
        """The higher the id, the earlier its stretch; nulls come last."""
        null = ids.is_null().to_numpy(zero_copy_only=False)
        values = ids.fill_null(0).to_numpy(zero_copy_only=False)
        out = np.where(null, len(self.cuts) + 1, len(self.cuts) - np.searchsorted(self.cuts, values, side="left")) * self._most
        shares = np.where(null, self.parts.get(None, 1), 1)
        if len(self._hot):
            at = np.minimum(np.searchsorted(self._hot, values), len(self._hot) - 1)
            shares = np.where(~null & (self._hot[at] == values), self._share[at], shares)
        place = (hashes.to_numpy(zero_copy_only=False).astype(np.float64) + 2.0**63) / 2.0**64
        return out + np.minimum((place * shares).astype(np.int64), shares - 1)


def edited_neighbours(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Each document against its edited text and the next document, in descending order of ids;
    ``edited_spans`` (start:end in the edited text, comma-joined) is what of it lies under branches that the document does not have (nothing, where something only went).

    Texts move once, to stretches of ids that are sorted and read as a stream. The
    first document of a stretch is also sent to the stretch before it, whose last one needs it.
    """
    spark = docs.sparkSession
    rows = docs.select(F.col(key).cast("long").alias("doc_id"), F.xxhash64(F.coalesce(F.col(text), F.lit(""))).alias("hash"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    stretches = Stretches(rows, max(2, int(spark.conf.get("spark.sql.shuffle.partitions"))))

    def light(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array(stretches(batch.column(0), batch.column(1))), batch.column(0), batch.column(1)], ["stretch", "doc_id", "hash"])

    first = F.max(F.struct("doc_id", F.bitwise_not("hash").alias("down")))
    heads = rows.select("doc_id", "hash").mapInArrow(tidied(light), "stretch long, doc_id long, hash long").groupBy("stretch").agg(first.alias("head")).orderBy("stretch").collect()  # one row for each stretch
    before = {(row["head"]["doc_id"], ~row["head"]["down"]): heads[i - 1]["stretch"] for i, row in enumerate(heads)}

    def spread(batches):
        for batch in batches:
            own = pa.array(stretches(batch.column(0), batch.column(1)))
            yield pa.RecordBatch.from_arrays([own, pa.array(np.zeros(len(own), bool)), *batch.columns], ["stretch", "sent", "doc_id", "hash", "text"])
            names = list(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True))
            ahead = [i for i, x in enumerate(names) if x in before]
            if ahead:
                some = batch.take(pa.array(ahead))
                yield pa.RecordBatch.from_arrays([pa.array([before[names[i]] for i in ahead], pa.int64()), pa.array([True] * len(ahead)), *some.columns], ["stretch", "sent", "doc_id", "hash", "text"])

    placed = rows.mapInArrow(tidied(spread), "stretch long, sent boolean, doc_id long, hash long, text string").repartition(stretches.partitions, "stretch")
    ordered = placed.sortWithinPartitions("stretch", "sent", F.desc_nulls_last("doc_id"), "hash", "text").drop("hash")
    return ordered.mapInArrow(tidied(_compare), "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double, edited_spans string")


def _compare(batches):
    names = ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next", "edited_spans"]
    kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64(), pa.string()]
    last = None  # (stretch, id, text, tree), waiting for its next document
    out: list = []

    def close(following: str, theirs: Tree):
        _, doc, text, own = last
        changed = edited(text, following)
        other = Tree(changed)
        out.append((doc, own.size, hashlib.sha256(changed.encode()).hexdigest(), own.fingerprint(), other.fingerprint(), likeness(own, other), likeness(own, theirs), ",".join(f"{a}:{b}" for a, b in differences(other, own))))

    for batch in batches:
        for stretch, sent, doc, text in zip(*(batch.column(i) for i in range(4)), strict=True):
            stretch, sent, doc, text = stretch.as_py(), sent.as_py(), doc.as_py(), text.as_py()
            if sent and last is None:
                continue
            own = Tree(text)
            if last is not None:
                close(text, own)
            last = None if sent else (stretch, doc, text, own)
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)], names)
            out.clear()
