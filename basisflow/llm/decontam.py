"""Benchmark decontamination: word-pair seeds, counted, then Smith-Waterman alignment.

Test items are a query set, taken in blocks of bounded size against all documents.
Seeds are an item's pairs of neighbouring words; in a text the two may have one word
between them. A local alignment that reaches a share of an item's own score holds a least
number of seeds (``needed``), close together. Of each item the commonest half of that
number are not looked up; a passage with fewer of the others than what is left of the
number cannot reach the share, and all other passages are aligned. So no alignment of ``LEAST``
or more is lost, wherever the edits are. Reported are pairs whose alignment reaches
``LEAST`` of the item's own score.

Defined results: null texts and items count as empty; items of fewer than ``SHORTEST`` words
give no rows; repeated documents, repeated items and null ids are each
reported; passages longer than any window are aligned whole; empty tables give no rows;
further columns are ignored by ``leaks`` and kept by ``clean``.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import portions, tidied

#: Words of the shortest item that is looked for.
SHORTEST = 3
#: Alignment scores of a match, a replaced word and a skipped word.
MATCH, MISMATCH, SKIP = 2, -1, -1
#: Share of an item's own score from which a passage counts as a copy.
LEAST = 0.5
#: Words of the items in one block, and cached pieces of text per worker.
BLOCK_WORDS, CACHE_PIECES = 2_000_000, 300_000
_EDGES = re.compile(r"^[\W_]+|[\W_]+$")


def word(piece: str) -> str:
    return piece if piece.isalnum() else _EDGES.sub("", piece)


class Block:
    """Items as word numbers (from 1; 0 is any other word), and the index of their word pairs."""

    def __init__(self, items: list[tuple[int | None, str | None]]):
        self.vocabulary: dict[str, int] = {}
        self.ids, self.items = [], []
        for item, text in items:
            words = [w for w in map(word, (text or "").lower().split()) if w]
            self.ids.append(item)
            self.items.append(np.array([self.vocabulary.setdefault(w, len(self.vocabulary) + 1) for w in words], np.int32))
        self.lengths = np.array([len(x) for x in self.items], np.int64)
        lists = [(pairs(x), np.arange(len(x) - 1)) for x in self.items]
        for i, x in enumerate(self.items):
            if len(x) < SHORTEST:
                lists[i] = lists[i][0][:0], lists[i][1][:0]
            elif len(x) == SHORTEST:  # its outer words alone reach half of its score
                lists[i] = np.append(lists[i][0], pairs(x[::2])), np.append(lists[i][1], 0)
        self.owner = np.repeat(np.arange(len(lists)), [len(x) for x, _ in lists])
        self.place = np.concatenate([x for _, x in lists]) if lists else np.zeros(0, np.int64)
        self.keys = np.concatenate([x for x, _ in lists]) if lists else np.zeros(0, np.int64)
        self.least = np.ones(len(lists), np.int64)

    def keep_seeds(self, least: float):
        """Leaves out the commonest pairs of each item, as many as the count allows, and sorts the others by key."""
        need = needed(self.lengths, least)
        spare = need // 2
        self.least = need - spare
        _, kind, counts = np.unique(self.keys, return_inverse=True, return_counts=True)
        order = np.lexsort((self.place, -counts[kind], self.owner))
        rank = np.arange(len(order)) - np.searchsorted(self.owner[order], self.owner[order])
        kept = order[rank >= spare[self.owner[order]]]
        kept = kept[np.argsort(self.keys[kept], kind="stable")]
        self.owner, self.place = self.owner[kept], self.place[kept]
        self.keys, self.starts = np.unique(self.keys[kept], return_index=True)
        self.starts = np.append(self.starts, len(kept))


def needed(n: np.ndarray, least: float) -> np.ndarray:
    """Neighbouring words of an item of ``n`` words that an alignment of share ``least`` holds, with at most one word between.

    From one matched word to the next the score grows by 2 at most where they are neighbours in the item and at most
    one word apart in the text, else by half of the item's words passed at most. Whole for ``least`` from 0.5.
    """
    return np.maximum(1, np.ceil((2 * n * least - n / 2 - 1.5) / 1.5 - 1e-9)).astype(np.int64)


def pairs(numbers: np.ndarray, apart: int = 1) -> np.ndarray:
    """One number for each two words that are ``apart``."""
    x = numbers.astype(np.int64)
    return (x[:-apart] << 32) | x[apart:]


class Reader:
    """Word numbers of texts, through a cache of pieces."""

    def __init__(self, block: Block):
        self.block, self._known = block, {}

    def numbers(self, text: str | None) -> np.ndarray:
        pieces, known, vocabulary = (text or "").lower().split(), self._known, self.block.vocabulary
        if len(known) > CACHE_PIECES:
            known.clear()
        try:
            return np.fromiter(map(known.__getitem__, pieces), np.int32, len(pieces))
        except KeyError:
            known.update((p, vocabulary.get(word(p), 0)) for p in pieces if p not in known)
        return np.fromiter(map(known.__getitem__, pieces), np.int32, len(pieces))

    def hits(self, numbers: np.ndarray):
        """(seeds, positions) of the word pairs that are seeds."""
        block, seeds, places = self.block, [], []
        for apart in (1, 2):
            at = np.nonzero((numbers[:-apart] > 0) & (numbers[apart:] > 0))[0]
            if not len(at) or not len(block.keys):
                continue
            wanted = pairs(numbers, apart)[at]
            kind = np.minimum(np.searchsorted(block.keys, wanted), len(block.keys) - 1)
            good = block.keys[kind] == wanted
            at, kind = at[good], kind[good]
            first, counts = block.starts[kind], block.starts[kind + 1] - block.starts[kind]
            seeds.append(np.repeat(first - np.cumsum(counts) + counts, counts) + np.arange(counts.sum()))
            places.append(np.repeat(at, counts))
        none = np.zeros(0, np.int64)
        return np.concatenate([none, *seeds]), np.concatenate([none, *places])


def windows(reader: Reader, numbers: np.ndarray):
    """(item number, start, end) around enough seeds; windows of an item that touch are one."""
    block = reader.block
    seeds, at = reader.hits(numbers)
    if not len(at):
        return []
    items = block.owner[seeds]
    enough = np.bincount(items, minlength=len(block.items)) >= block.least  # with repeats: never too few
    some = enough[items]
    if not some.any():
        return []
    distinct = np.bincount(block.owner[np.unique(seeds[some])], minlength=len(block.items)) >= block.least
    some = distinct[items]
    seeds, at, items = seeds[some], at[some], items[some]
    order = np.lexsort((at, items))
    seeds, at, items = seeds[order], at[order], items[order]
    # a passage that reaches half of the score is at most twice as long as the item
    line = items * (4 * len(numbers) + 4 * int(block.lengths.max()) + 8) + at
    count = np.searchsorted(line, line + 2 * block.lengths[items], side="right") - np.arange(len(line))
    out: list[list[int]] = []
    for i in np.nonzero(count >= block.least[items])[0]:
        item, n = int(items[i]), int(block.lengths[items[i]])
        offset = int(at[i] - block.place[seeds[i]])
        start, end = max(0, offset - n), min(len(numbers), offset + 2 * n + 2)
        if out and out[-1][0] == item and start <= out[-1][2]:
            out[-1][1], out[-1][2] = min(out[-1][1], start), max(out[-1][2], end)
        else:
            out.append([item, start, end])
    return out


def align(pairs: list[tuple[np.ndarray, np.ndarray]], cells: int = 2_000_000):
    """(best score, end in the text) of the local alignment of each (item, text), many at a time."""
    out: list = [None] * len(pairs)
    order = sorted(range(len(pairs)), key=lambda i: len(pairs[i][1]))
    while order:
        width = len(pairs[order[0]][1])
        n = 0
        while n < len(order) and (n + 1) * (len(pairs[order[n]][1]) + 1) <= max(cells, len(pairs[order[n]][1]) + 1):
            width = len(pairs[order[n]][1])
            n += 1
        some, order = order[:n], order[n:]
        depth = max(len(pairs[i][0]) for i in some)
        texts = np.full((n, width), -1, np.int32)
        items = np.full((n, depth), -2, np.int32)
        for r, i in enumerate(some):
            items[r, : len(pairs[i][0])] = pairs[i][0]
            texts[r, : len(pairs[i][1])] = pairs[i][1]
        ramp = (-SKIP) * np.arange(width + 1, dtype=np.int32)
        row = np.zeros((n, width + 1), np.int32)
        best, end = np.zeros(n, np.int32), np.zeros(n, np.int64)
        for step in range(depth):
            now = np.zeros_like(row)
            now[:, 1:] = np.maximum(row[:, :-1] + np.where(texts == items[:, step, None], MATCH, MISMATCH), row[:, 1:] + SKIP)
            np.maximum(now, 0, out=now)
            now = np.maximum.accumulate(now + ramp, axis=1) - ramp
            row = np.maximum(now, 0)
            peak = row.argmax(1)
            top = row[np.arange(n), peak]
            better = top > best
            best[better], end[better] = top[better], peak[better]
        for r, i in enumerate(some):
            out[i] = (int(best[r]), int(end[r]))
    return out


def copies(reader: Reader, texts: list[str | None], least: float):
    """(text number, item number, score, first word, end word): the best passage of each pair that reaches ``least``."""
    found, passages = [], []
    for t, text in enumerate(texts):
        numbers = reader.numbers(text)
        for item, start, stop in windows(reader, numbers):
            found.append((t, item, start))
            passages.append((reader.block.items[item], numbers[start:stop]))
    best: dict[tuple[int, int], tuple] = {}
    kept = []
    for i, (score, end) in enumerate(align(passages)):
        t, item, start = found[i]
        share = score / (MATCH * len(reader.block.items[item]))
        if share >= least and share > best.get((t, item), (0.0,))[0]:
            best[t, item] = (share, start, end, i)
    kept = list(best.items())
    back = align([(passages[i][0][::-1], passages[i][1][:end][::-1]) for _, (_, _, end, i) in kept])
    for ((t, item), (share, start, end, _)), (_, length) in zip(kept, back, strict=True):
        yield t, item, share, start + end - length, start + end


def blocks(benchmark: DataFrame, item: str = "item_id", text: str = "text"):
    """The items, a bounded number of words at a time."""
    held, words = [], 0
    for row in benchmark.select(item, text).toLocalIterator():
        held.append((row[0], row[1]))
        words += len((row[1] or "").split())
        if words >= BLOCK_WORDS:
            yield Block(held)
            held, words = [], 0
    if held:
        yield Block(held)


def seeded(docs: DataFrame, block: Block, least: float):
    """The broadcast block with its seeds."""
    block.keep_seeds(least)
    return docs.sparkSession.sparkContext.broadcast(block)  # bounded by BLOCK_WORDS


def leaks(docs: DataFrame, benchmark: DataFrame, least: float = LEAST, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, item_id, score, first_word, end_word) of every document that holds a copy of an item."""
    schema = "doc_id long, item_id long, score double, first_word long, end_word long"
    out = None
    for block in blocks(benchmark):
        part = docs.select(F.col(key).cast("long"), text).mapInArrow(tidied(_finder(seeded(docs, block, least), least)), schema)
        out = part if out is None else out.unionByName(part)
    return docs.sparkSession.createDataFrame([], schema) if out is None else out


def _finder(shared, least):
    def run(batches):
        reader = Reader(shared.value)
        for batch in portions(batches):
            rows = list(copies(reader, batch.column(1).to_pylist(), least))
            ids = batch.column(0).take(pa.array([r[0] for r in rows], pa.int64()))
            items = pa.array([shared.value.ids[r[1]] for r in rows], pa.int64())
            yield pa.RecordBatch.from_arrays([ids, items, pa.array([r[2] for r in rows], pa.float64()), pa.array([r[3] for r in rows], pa.int64()), pa.array([r[4] for r in rows], pa.int64())], ["doc_id", "item_id", "score", "first_word", "end_word"])

    return run


def clean(docs: DataFrame, benchmark: DataFrame, least: float = LEAST, text: str = "text") -> DataFrame:
    """The documents that hold no copy of any item; columns as given."""
    at = docs.columns.index(text)
    for block in blocks(benchmark):
        shared = seeded(docs, block, least)

        def run(batches, shared=shared):
            reader = Reader(shared.value)
            for batch in portions(batches):
                bad = {r[0] for r in copies(reader, batch.column(at).to_pylist(), least)}
                yield batch.filter(pa.array([i not in bad for i in range(batch.num_rows)], pa.bool_()))

        docs = docs.mapInArrow(tidied(run), docs.schema)
    return docs
