"""Near-duplicate groups by the Jaccard similarity of word shingles.

SimHash bits cannot tell a similarity of 0.8 from chance (two such sets of shingles differ in
about 10 of 64 bits), so the signature here has minima of hash functions as its symbols.
Texts with equal sets of shingles are one node. Of every node's set, ``BANDS`` keys are
made of ``ROWS`` minima each; nodes that share a key are candidates (two of similarity s
with probability 1 - (1 - s ** ROWS) ** BANDS: 0.999 at 0.8), and every candidate pair is
verified on the shingles themselves.

Beside them, the steps of op8 give candidates too: every text has its SimHash fingerprint, and fingerprints that
share a one-wildcard segment variant and differ in two bits or fewer are linked (``simhash.links``). Nodes with one fingerprint meet
the least of them, nodes of linked fingerprints meet through their least; these pairs are verified like the others.

Of all candidate pairs one for each node is verified first, the one with the node that has most candidates; of the rest only
those that then still join different components. So copies of one text are not compared each with each.

In a bucket of up to ``ALL_PAIRS`` nodes all pairs are candidates. In a larger one every node is
first held against the node that meets most others over all its keys, which in a star of edited
copies is their source. Large buckets that are then still of more than one component make up families
(nodes joined by such buckets). A family is dealt into blocks of about ``BLOCK_NODES`` nodes, and every two blocks
meet once, in numpy: nodes of different components are compared by one byte of each minimum and by their
numbers of shingles (at 0.8, a pair passes with probability over 0.9999), then by the shingles
themselves; only links that join something leave the task. So no link is lost to a bucket's
size, and no pair of a large bucket ever becomes a row.

Defined results: ids must be unique and not null (``simhash.keep_one`` numbers rows where they are not); null, empty and blank texts share the
empty set; a text of fewer words than a shingle is one shingle; an empty table gives no rows;
further columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import simhash
from .common import portions, small_side, tidied, within, written
from .components import components

#: Words of a shingle, and the similarity from which two texts are near-duplicates.
SHINGLE, LEAST = 5, 0.8
#: Keys of a set and minima of a key; largest bucket whose pairs are all candidates.
BANDS, ROWS, ALL_PAIRS = 24, 6, 16
#: Nodes of a block of a family, and the share of equal minima (by one byte) that a pair needs to be compared.
BLOCK_NODES, NEAR = 1000, 0.66
#: Shingles put through the hash functions at once.
BLOCK = 1 << 11
_MASKS, _FACTORS = np.random.default_rng(42).integers(0, 1 << 64, (2, BANDS * ROWS), np.uint64) | np.array([[0], [1]], np.uint64)


def shingles(text: bytes, width: int = SHINGLE) -> np.ndarray:
    """Sorted distinct XXH64 of the shingles; empty for a text without words."""
    words = text.lower().split()
    digest = xxhash.xxh64_intdigest
    if len(words) < width:
        return np.array([digest(b" ".join(words))] if words else [], np.uint64)
    lists = [words[i:] for i in range(width)]
    return np.unique(np.fromiter((digest(b" ".join(s)) for s in zip(*lists, strict=False)), np.uint64, len(words) - width + 1))


def minima(found: np.ndarray) -> np.ndarray:
    """Least value of each hash function over the set."""
    least = np.full(BANDS * ROWS, (1 << 64) - 1, np.uint64)
    for at in range(0, len(found), BLOCK):
        np.minimum(least, ((found[at : at + BLOCK, None] ^ _MASKS) * _FACTORS).min(0), out=least)
    return least


def keys(least: np.ndarray) -> list[int]:
    """One signed key for each band of minima."""
    return np.array([xxhash.xxh64_intdigest(row.tobytes(), band) for band, row in enumerate(least.reshape(BANDS, ROWS))], np.uint64).view(np.int64).tolist()


def jaccard(a: np.ndarray, b: np.ndarray) -> float:
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both / max(1, len(a) + len(b) - both)


def sketches(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, shingle_set, bands, sketch, fp) of every row; ``fp`` is op8's fingerprint as a signed integer."""

    def run(batches):
        for batch in portions(batches):
            texts = [t.as_py() or b"" for t in batch.column(1).cast(pa.binary())]
            sets = [shingles(t) for t in texts]
            fps = np.array([simhash.fingerprint(t) for t in texts], np.uint64).view(np.int64)
            least = [minima(s) for s in sets]
            names = pa.array([xxhash.xxh3_128_digest(s.tobytes()) for s in sets], pa.binary())
            bands = pa.array([keys(m) if len(s) else [] for s, m in zip(sets, least, strict=True)], pa.list_(pa.int64()))
            bytes_ = pa.array([(m >> np.uint64(40)).astype(np.uint8).tobytes() for m in least], pa.binary())
            yield pa.RecordBatch.from_arrays([batch.column(0), names, bands, bytes_, pa.array(fps)], ["doc_id", "shingle_set", "bands", "sketch", "fp"])

    return docs.select(F.col(key).cast("long"), text).mapInArrow(tidied(run), "doc_id long, shingle_set binary, bands array<long>, sketch binary, fp long")


def buckets(nodes: DataFrame) -> DataFrame:
    """(band, node, n): the keys that more than one node has, with their numbers of nodes."""
    placed = nodes.select("node", F.explode("bands").alias("band"))
    shared = placed.groupBy("band").agg(F.count("*").alias("n")).where("n > 1")
    return placed.hint("merge").join(shared, "band")


def first_pairs(placed: DataFrame) -> DataFrame:
    """Distinct pairs (x, y), x < y: all of small buckets, those with the hub of large ones."""
    few = placed.where(F.col("n") <= ALL_PAIRS)
    pairs = few.select("band", F.col("node").alias("x")).hint("merge").join(few.select("band", F.col("node").alias("y")), "band").where("x < y").select("x", "y")
    many = placed.where(F.col("n") > ALL_PAIRS)
    weighed = many.join(many.groupBy("node").agg(F.sum("n").alias("met")), "node")
    hubs = written(weighed.groupBy("band").agg(F.min(F.struct((-F.col("met")).alias("met"), "node")).alias("hub")).select("band", "hub.node"), "similar-hubs")
    near = many.join(small_side(hubs.withColumnRenamed("node", "hub")), "band").where("node <> hub")
    return pairs.unionByName(near.select(F.least("node", "hub").alias("x"), F.greatest("node", "hub").alias("y"))).distinct()


def fingerprint_pairs(nodes: DataFrame) -> DataFrame:
    """Pairs (x, y), x < y, of op8's links: nodes with the least of their fingerprint, and the least of two linked fingerprints. ``nodes`` has node and fps."""
    marked = written(nodes.select("node", F.explode("fps").alias("fp")), "similar-marked")
    least = written(marked.groupBy("fp").agg(F.min("node").alias("least"), F.count("*").alias("n")), "similar-fps")
    same = marked.join(small_side(least.where("n > 1").select("fp", "least")), "fp").where("node <> least").select(F.col("least").alias("x"), F.col("node").alias("y"))
    linked = written(simhash.links(least.select("fp")), "similar-fp-links")
    side = lambda name: least.select(F.col("fp").alias(name), F.col("least").alias(f"{name}_least"))
    across = linked.hint("merge").join(side("x"), "x").hint("merge").join(side("y"), "y").where("x_least <> y_least")
    return same.unionByName(across.select(F.least("x_least", "y_least").alias("x"), F.greatest("x_least", "y_least").alias("y")))


def chosen(pairs: DataFrame) -> DataFrame:
    """One pair for each node: with the one of its candidates that has most candidates, then the smallest."""
    both = pairs.union(pairs.select("y", "x"))
    weight = both.groupBy("x").agg(F.count("*").alias("met"))
    weighed = both.hint("merge").join(weight.withColumnRenamed("x", "y"), "y")
    best = weighed.groupBy("x").agg(F.min(F.struct((-F.col("met")).alias("met"), "y")).alias("best"))
    return best.select(F.least("x", "best.y").alias("x"), F.greatest("x", "best.y").alias("y")).distinct()


def apart(pairs: DataFrame, roots: DataFrame) -> DataFrame:
    """The pairs whose nodes are of different components."""
    side = lambda name: roots.select(F.col("node").alias(name), F.col("root").alias(f"{name}_root"))
    both = pairs.join(side("x"), "x", "left").join(side("y"), "y", "left")
    return both.where(F.coalesce("x_root", "x") != F.coalesce("y_root", "y")).select("x", "y")


def families(large: DataFrame, roots: DataFrame) -> DataFrame:
    """(node, root, family) of the nodes of large buckets that are of more than one component."""
    labelled = large.join(roots, "node", "left").select("band", "node", F.coalesce("root", "node").alias("root"))
    mixed = labelled.groupBy("band").agg(F.min("root").alias("low"), F.max("root").alias("high"), F.min("node").alias("least")).where("low < high")
    met = written(labelled.join(mixed.select("band", "least"), "band").select("node", "root", "least").distinct(), "similar-mixed")
    named = components(met, "node", "least")
    family = F.coalesce(F.col("named.root"), F.col("n.node"))
    return met.select("node", "root").distinct().alias("n").join(named.alias("named"), F.col("n.node") == F.col("named.node"), "left").select("n.node", "n.root", family.alias("family"))


def family_links(members: DataFrame, nodes: DataFrame, texts: DataFrame, least: float) -> DataFrame:
    """Links (x, y) between components of each family: enough of them to join all that are linked."""

    def sets(batches):
        for batch in portions(batches):
            found = [shingles(t.as_py() or b"").tobytes() for t in batch.column(1).cast(pa.binary())]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(found, pa.binary())], ["node", "shingles"])

    own = within(texts, members.select("node"), "node").select("node", "text").mapInArrow(tidied(sets), "node long, shingles binary")
    sizes = members.groupBy("family").agg(F.ceil(F.count("*") / BLOCK_NODES).alias("blocks"))
    placed = members.join(sizes, "family").withColumn("block", F.pmod(F.xxhash64("node"), "blocks"))
    whole = placed.join(nodes.select("node", "sketch"), "node").join(own, "node")
    packed = whole.groupBy("family", "block").agg(F.first("blocks").alias("blocks"), F.array_sort(F.collect_list(F.struct("node", "root", "sketch", "shingles"))).alias("rows"))
    packed = written(packed, "similar-blocks")
    left = packed.select("family", F.explode(F.sequence("block", F.col("blocks") - 1)).alias("block"), F.col("block").alias("own"), F.col("rows").alias("left"))
    both = left.hint("merge").join(packed.select("family", "block", F.col("rows").alias("right")), ["family", "block"])
    field = lambda side, name: F.col(f"{side}.{name}").alias(f"{side}_{name}")
    both = both.select(*(field(side, name) for side in ("left", "right") for name in ("node", "root", "sketch", "shingles")))

    def run(batches):
        for batch in batches:
            for row in zip(*batch.columns, strict=True):
                links = list(linked(*(x.as_py() for x in row), least))
                yield pa.RecordBatch.from_arrays([pa.array([x for x, _ in links], pa.int64()), pa.array([y for _, y in links], pa.int64())], ["x", "y"])

    return both.mapInArrow(tidied(run), "x long, y long")


def linked(nodes_a, roots_a, sketches_a, sets_a, nodes_b, roots_b, sketches_b, sets_b, least: float):
    """Links between the nodes of two blocks that join different components, as known and as found on the way."""
    at: dict[int, int] = {}

    def top(x):
        while (up := at.get(x, x)) != x:
            x = up
        return x

    a, b = (np.frombuffer(b"".join(s), np.uint8).reshape(-1, BANDS * ROWS) for s in (sketches_a, sketches_b))
    roots = np.array(roots_b)
    sizes = np.array([len(s) // 8 for s in sets_b])
    for i, (node, root, raw) in enumerate(zip(nodes_a, roots_a, sets_a, strict=True)):
        size = len(raw) // 8
        others = np.nonzero((roots != root) & (sizes >= least * size) & (size >= least * sizes))[0]
        alike = (b[others] == a[i]).mean(1)
        mine = np.frombuffer(raw, np.uint64)
        for j in others[alike >= NEAR][np.argsort(-alike[alike >= NEAR], kind="stable")].tolist():
            if top(root) != top(roots_b[j]) and jaccard(mine, np.frombuffer(sets_b[j], np.uint64)) >= least:
                at[top(root)] = top(roots_b[j])
                yield min(node, nodes_b[j]), max(node, nodes_b[j])


def verified(pairs: DataFrame, texts: DataFrame, least: float) -> DataFrame:
    """The pairs whose texts reach ``least``; ``texts`` has node and text."""
    # whether all texts are shuffled must not hang on how large a file of pairs happens to be
    wanted = written(pairs.select(F.col("x").alias("node")).union(pairs.select("y")).distinct(), "similar-wanted")
    texts = written(within(texts, wanted, "node"), "similar-texts")
    # texts are never broadcast: they grow with the input
    both = pairs.hint("merge").join(texts.select(F.col("node").alias("x"), F.col("text").alias("left")), "x")
    both = both.hint("merge").join(texts.select(F.col("node").alias("y"), F.col("text").alias("right")), "y")

    def run(batches):
        for batch in portions(batches):
            left, right = ([shingles(t.as_py() or b"") for t in batch.column(i).cast(pa.binary())] for i in (2, 3))
            yield batch.select([0, 1]).filter(pa.array([jaccard(a, b) >= least for a, b in zip(left, right, strict=True)], pa.bool_()))

    return both.select("x", "y", "left", "right").mapInArrow(tidied(run), "x long, y long")


def links(nodes: DataFrame, texts: DataFrame, least: float = LEAST) -> DataFrame:
    """(node, root) of the nodes (node, bands, sketch, fps) that are linked to others."""
    placed = written(buckets(nodes), "similar-buckets")
    pairs = written(first_pairs(placed).unionByName(fingerprint_pairs(nodes)).distinct(), "similar-pairs")
    found = written(verified(written(chosen(pairs), "similar-chosen"), texts, least), "similar-links")
    roots = written(components(found, "x", "y"), "similar-roots")
    rest = written(apart(pairs, roots), "similar-apart")
    if rest.limit(1).count():
        found = written(found.unionByName(verified(rest, texts, least)), "similar-links")
        roots = written(components(found, "x", "y"), "similar-roots")
    members = written(families(placed.where(F.col("n") > ALL_PAIRS), roots), "similar-families")
    if not members.limit(1).count():
        return roots
    more = written(family_links(members, nodes, texts, least), "similar-links")
    return written(components(found.unionByName(more), "x", "y"), "similar-roots")


def groups(docs: DataFrame, least: float = LEAST, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, component_id) for every row; ids are unique and not null. The component is the smallest id of the group."""
    sketched = written(sketches(docs, key, text), "similar")
    nodes = sketched.groupBy("shingle_set").agg(F.min("doc_id").alias("node"), F.first("bands").alias("bands"), F.first("sketch").alias("sketch"), F.collect_set("fp").alias("fps"))
    nodes = written(nodes, "similar-nodes")
    roots = links(nodes, docs.select(F.col(key).cast("long").alias("node"), F.col(text).alias("text")), least)
    named = nodes.select("shingle_set", "node").join(roots.withColumnRenamed("node", "n"), F.col("node") == F.col("n"), "left")
    classes = written(named.select("shingle_set", F.coalesce("root", "node").alias("component_id")), "similar-classes")
    return sketched.select("doc_id", "shingle_set").join(classes, "shingle_set").select("doc_id", "component_id")
