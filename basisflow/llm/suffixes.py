"""Suffix-array deduplication: maximal repeats, and the removal of repeated bytes.

A repeat of ``LEAST`` bytes contains an anchor: of its 12-byte grams, the leftmost
one with the smallest hash. The anchor depends on the repeat alone, so all its
occurrences meet where texts are dealt out by anchor. Each anchor travels once, with
its context, the bytes of all windows that it is the anchor of. Equal contexts (compared
byte by byte) are one class. Over the windows of a bucket's classes that occur more than
once an enhanced suffix array is built (suffixes in order, common-prefix lengths, left
neighbours); a class with copies stands in it twice. A stack scan lists its common-prefix
intervals; those with more than one left extension are the maximal repeats, each with
all its occurrences, and whatever a smaller document also has is removed.

What a task's contexts repeat among themselves is settled there in the same way and not
sent, so a passage that very many documents share sends one copy per ``HELD`` bytes. A bucket
that holds more than ``HOT`` bytes of different contexts is dealt out once more, by the
anchor with the bytes on one side, and at last by whole windows: no bucket is ever larger.

``repeat_groups`` returns the maximal repeats themselves. A repeat longer than a context comes
as the maximal repeats of its contexts, which overlap.

Defined results: null text counts as empty; rows with equal ids never remove each other's
bytes, but each is judged against smaller ids; rows with null id come after all others;
texts under ``LEAST`` bytes keep all; an empty table gives no rows; further columns
are ignored.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import BROADCAST_ROWS, tidied, written

#: Fixed value of the contract: bytes of a repeat.
LEAST = 50
#: Bytes of an anchor, and anchors to choose from in a window.
GRAM = 12
CHOICES = LEAST - GRAM + 1
#: Most bytes around one anchor.
WIDTH = 2 * LEAST - GRAM
#: Bytes of text handled at once, bytes of contexts held before they are sent, bytes of text per bucket.
CHUNK, HELD, BUCKET = 1 << 20, 32 << 20, 2 << 20
#: Bytes of contexts of one bucket that a task holds.
HOT = 24 << 20
#: A bucket that is too large is dealt out by the anchor and this many bytes on one side: a window has them on one.
HALF = (LEAST - GRAM) // 2
#: Most partitions of the exchange; buckets beyond it share partitions and are read one after the other.
PARTITIONS = 10_000
LAST_ID = (1 << 63) - 1
_M = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0xBF58476D1CE4E5B9)]


# --- enhanced suffix arrays -------------------------------------------------


def lcp_intervals(lcp, least: int):
    """(first, last, depth) of all intervals of suffixes whose common prefix is ``depth`` >= ``least``, inner ones first.

    ``lcp[i]`` is the common-prefix length of suffixes i - 1 and i; ``lcp[0]`` is not read.
    """
    values = np.append(np.where(lcp < least, 0, lcp), 0)
    values[0] = 0
    found, firsts, depths = [], [], []  # open intervals: where they begin, and their depths, deeper ones on top
    # between changes the depth on top is the common prefix: nothing opens or closes
    for i in (np.nonzero(np.diff(values))[0] + 1).tolist():
        now, first = int(values[i]), i - 1
        while depths and depths[-1] > now:
            first = firsts.pop()
            found.append((first, i - 1, depths.pop()))
        if now and (not depths or depths[-1] < now):
            firsts.append(first)
            depths.append(now)
    return np.array(found, np.int64).reshape(-1, 3).T


def left_diverse(left: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """Whether the suffixes of each interval have more than one byte before them; -1 stands for none and differs from all."""
    change = np.zeros(len(left), np.int64)
    change[1:] = (left[1:] != left[:-1]) | (left[1:] < 0)
    summed = np.cumsum(change)
    return (summed[high] - summed[low] > 0) | (left[low] < 0)


def suffix_array(text: np.ndarray) -> np.ndarray:
    """Order of all suffixes of an integer sequence, by prefix doubling."""
    n = len(text)
    rank = np.unique(text, return_inverse=True)[1].astype(np.int64) if n else np.zeros(0, np.int64)
    step = 1
    while True:
        second = np.full(n, -1, np.int64)
        second[: max(0, n - step)] = rank[step:]
        order = np.lexsort((second, rank))
        fresh = np.zeros(n, np.int64)
        if n:
            fresh[order[1:]] = np.cumsum((rank[order[1:]] != rank[order[:-1]]) | (second[order[1:]] != second[order[:-1]]))
        rank = fresh
        if n == 0 or rank.max() == n - 1:
            return order
        step *= 2


def common_prefixes(text, order) -> np.ndarray:
    """Common-prefix lengths of neighbours in the suffix array."""
    n = len(order)
    place = np.empty(n, np.int64)
    place[order] = np.arange(n)
    lcp, h, values = np.zeros(n, np.int64), 0, text.tolist()
    for i in range(n):
        if place[i] == 0:
            h = 0
            continue
        j = int(order[place[i] - 1])
        while i + h < n and j + h < n and values[i + h] == values[j + h]:
            h += 1
        lcp[place[i]] = h
        h = max(0, h - 1)
    return lcp


def maximal_repeats(texts: list[bytes], least: int = LEAST):
    """(length, [(text, offset), ...]) of every maximal repeat of ``least`` bytes or more, with all its occurrences.

    Repeats never cross texts: each text ends in a symbol of its own.
    """
    joined = np.concatenate([np.append(np.frombuffer(t, np.uint8).astype(np.int64), 256 + i) for i, t in enumerate(texts)]) if texts else np.zeros(0, np.int64)
    starts = np.cumsum([0, *(len(t) + 1 for t in texts)])[:-1]
    order = suffix_array(joined)
    lcp = common_prefixes(joined, order)
    before = np.where(order > 0, joined[order - 1], -1)
    before[before >= 256] = -1
    low, high, depth = lcp_intervals(lcp, least)
    for a, b, n in zip(*(x[left_diverse(before, low, high)] for x in (low, high, depth)), strict=True):
        at = np.sort(order[a : b + 1])
        owner = np.searchsorted(starts, at, side="right") - 1
        yield int(n), [(int(t), int(p - starts[t])) for t, p in zip(owner, at, strict=True)]


# --- anchors ----------------------------------------------------------------


def _eights(data: np.ndarray) -> np.ndarray:
    """The eight bytes at every offset as one number, without a copy; ``data`` has seven spare bytes at its end."""
    return np.ndarray((len(data) - 7,), "<u8", np.ascontiguousarray(data), 0, (1,))


def _mix(a, b):
    x = (a * _M[0]) ^ (b * _M[1])
    x ^= x >> np.uint64(31)
    return x * _M[2]


def context_hashes(eights: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Hashes of byte strings of ``LEAST`` to ``WIDTH`` bytes, from reads that cover them."""
    out = sizes.astype(np.uint64)
    for offset in (0, 8, 16, 24, 32, 40, LEAST - 8):
        out = _mix(out, eights[starts + offset])
    for offset in (8, 16, 24, 32, 40):
        out = _mix(out, eights[starts + sizes - offset])
    return out


def anchors(data: np.ndarray, firsts: np.ndarray, ends: np.ndarray):
    """(text number, context start, context size, anchor place in it, anchor hash, context hash) of concatenated texts.

    A context is the bytes of all consecutive windows with one anchor.
    """
    eights = _eights(data).copy()
    n = len(data) - 7 - LEAST + 1
    grams = _mix(eights[: len(eights) - 4], eights[4:])
    ranked = (grams & ~np.uint64(0xFFFFFF)) | np.arange(len(grams), dtype=np.uint64)
    span = 1
    while 2 * span <= CHOICES:
        ranked = np.minimum(ranked[:-span], ranked[span:])
        span *= 2
    rest = CHOICES - span
    ranked = np.minimum(ranked[: len(ranked) - rest], ranked[rest:]) if rest else ranked
    place = (ranked[: max(0, n)] & np.uint64(0xFFFFFF)).astype(np.int64)
    # windows must lie within a text
    owner = np.full(len(place) + LEAST, -1, np.int32)
    for i, (a, b) in enumerate(zip(firsts.tolist(), ends.tolist(), strict=True)):
        if b - a >= LEAST:
            owner[a : b - LEAST + 1] = i
    owner = owner[: len(place)]
    change = np.ones(len(place) + 1, bool)
    change[1:-1] = (place[1:] != place[:-1]) | (owner[1:] != owner[:-1])
    cuts = np.nonzero(change)[0]
    starts, stops = cuts[:-1], cuts[1:]
    good = owner[starts] >= 0
    starts, stops = starts[good], stops[good]
    at = place[starts]
    sizes = stops - starts + LEAST - 1
    return owner[starts], starts, sizes, at - starts, grams[at], context_hashes(eights, starts, sizes)


def _gathered(data: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Stretches of bytes one after the other, put together a bounded number at a time."""
    ends = np.cumsum(sizes)
    begins = ends - sizes
    out = np.empty(ends[-1] if len(ends) else 0, np.uint8)
    cuts = np.unique(np.append(np.searchsorted(ends, np.arange(0, len(out), 1 << 20)), len(ends)))
    for a, b in zip(cuts[:-1], cuts[1:], strict=True):
        out[begins[a] : ends[b - 1]] = data[np.repeat(starts[a:b] - begins[a:b], sizes[a:b]) + np.arange(begins[a], ends[b - 1])]
    return out


def merged(starts: np.ndarray, ends: np.ndarray):
    """Union of intervals as maximal ones, in order."""
    if not len(starts):
        return starts, ends
    order = np.argsort(starts, kind="stable")
    starts, ends = starts[order], np.maximum.accumulate(ends[order])
    new = np.ones(len(starts), bool)
    new[1:] = starts[1:] > ends[:-1]
    at = np.nonzero(new)[0]
    return starts[at], ends[np.append(at[1:], len(starts)) - 1]


def _pack(*columns: np.ndarray) -> bytes:
    return zstandard.ZstdCompressor(level=6).compress(b"".join([len(columns[0]).to_bytes(8, "little"), *(c.tobytes() for c in columns)]))


def _unpack(blob: bytes, kinds):
    raw = zstandard.ZstdDecompressor().decompress(blob)
    n, at, out = int.from_bytes(raw[:8], "little"), 8, []
    for kind in kinds:
        out.append(np.frombuffer(raw, kind, n, at))
        at += n * np.dtype(kind).itemsize
    return [*out, np.frombuffer(raw, np.uint8, -1, at)]


_SPANS, _CONTEXTS = ("<i8", "<i8", "<u4", "<u4"), ("<i8", "<i8", "<u4", "u1", "u1")


class Contexts:
    """Columns of contexts: document, tag, place in the text, size, place of the anchor, and the bytes one after the other."""

    def __init__(self, doc, tag, at, sizes, place, body):
        self.doc, self.tag, self.at, self.sizes, self.place, self.body = doc, tag, at.astype(np.int64), sizes.astype(np.int64), place.astype(np.int64), body
        self.starts = np.cumsum(self.sizes) - self.sizes

    def __len__(self):
        return len(self.doc)

    def take(self, rows: np.ndarray) -> Contexts:
        return Contexts(self.doc[rows], self.tag[rows], self.at[rows], self.sizes[rows], self.place[rows], _gathered(self.body, self.starts[rows], self.sizes[rows]))

    def parts(self, rows: np.ndarray, offsets: np.ndarray, sizes: np.ndarray) -> Contexts:
        """Parts of contexts as contexts."""
        return Contexts(self.doc[rows], self.tag[rows], self.at[rows] + offsets, sizes, self.place[rows] - offsets, _gathered(self.body, self.starts[rows] + offsets, sizes))

    @staticmethod
    def joined(some: list[Contexts]) -> Contexts:
        return Contexts(*(np.concatenate([getattr(c, n) for c in some]) for n in ("doc", "tag", "at", "sizes", "place", "body")))

    def packed(self) -> bytes:
        at = self.at.astype("<u4")
        return _pack(np.diff(self.doc, prepend=0), np.diff(self.tag, prepend=0), np.diff(at, prepend=at[:1] * 0), self.sizes.astype("u1"), self.place.astype("u1"), self.body)

    @staticmethod
    def unpacked(blob: bytes) -> Contexts:
        doc, tag, at, sizes, place, body = _unpack(blob, _CONTEXTS)
        return Contexts(np.cumsum(doc), np.cumsum(tag), np.cumsum(at, dtype=np.uint32), sizes, place, body)

    def by_bucket(self, buckets: np.ndarray, rows: np.ndarray | None = None):
        """(bucket, packed contexts) of each bucket; ``buckets`` are those of the given rows, or of all."""
        rows = np.arange(len(self)) if rows is None else rows
        order = np.lexsort((self.at[rows], self.doc[rows], buckets))
        if not len(order):
            return
        rows, buckets = rows[order], buckets[order]
        cuts = np.concatenate([[0], np.nonzero(np.diff(buckets))[0] + 1, [len(buckets)]])
        for a, b in zip(cuts[:-1], cuts[1:], strict=True):
            yield int(buckets[a]), self.take(rows[a:b]).packed()


def _row(bucket: int, kind: int, data: bytes) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([bucket], pa.int64()), pa.array([kind], pa.int32()), pa.array([data], pa.binary())], ["bucket", "kind", "data"])


def contexts_of(batches, chunk: int = CHUNK):
    """(contexts, anchor hashes, context hashes) of about ``chunk`` bytes of text at a time."""
    for docs, tags, data, firsts, ends, offsets in _chunks(batches, chunk):
        text, starts, sizes, place, grams, same = anchors(data, firsts, ends)
        if len(text):
            yield Contexts(docs[text], tags[text], starts - firsts[text] + offsets[text], sizes, place, _gathered(data, starts, sizes)), grams, same


def _deal(batches, buckets: int, chunk: int, most: int):
    """Rows (bucket, kind, data): contexts for buckets (kind 1), and spans that are settled already (kind 0)."""
    held: list = []
    size = 0

    def send():
        contexts = Contexts.joined([c for c, *_ in held])
        grams, same = (np.concatenate([h[i] for h in held]) for i in (1, 2))
        held.clear()
        spans, open_ = settled_copies(contexts, same)
        if len(spans[0]):
            yield _row(int(grams[0] % np.uint64(buckets)), 0, _pack(*_by_document(*spans)))
        for bucket, blob in contexts.by_bucket(((grams[open_] >> np.uint64(20)) % np.uint64(buckets)).astype(np.int64), open_):
            yield _row(bucket, 1, blob)

    for part in contexts_of(batches, chunk):
        held.append(part)
        size += len(part[0].body)
        if size >= most:
            yield from send()
            size = 0
    if held:
        yield from send()


def _by_document(ids, tags, starts, ends):
    """Intervals of each (id, tag), merged, as four columns."""
    order = np.lexsort((starts, tags, ids))
    ids, tags, starts, ends = ids[order], tags[order], starts[order].astype(np.int64), ends[order].astype(np.int64)
    new = np.ones(len(ids), bool)
    new[1:] = (ids[1:] != ids[:-1]) | (tags[1:] != tags[:-1])
    shift = (np.cumsum(new) - 1) * (1 << 33)  # keeps documents apart
    a, b = merged(starts + shift, ends + shift)
    first = np.searchsorted(starts + shift, a)
    return ids[first], tags[first], (a - shift[first]).astype("<u4"), (b - shift[first]).astype("<u4")


def _chunks(batches, chunk: int):
    """(ids, tags, bytes with spare ones, text starts, text ends, offsets) of about ``chunk`` bytes; longer texts come in overlapping parts."""
    ids, tags, parts, offsets, size = [], [], [], [], 0

    def out():
        sizes = np.array([len(p) for p in parts], np.int64)
        ends = np.cumsum(sizes)
        data = np.concatenate([*(np.frombuffer(p, np.uint8) for p in parts), np.zeros(LEAST + 16, np.uint8)])
        return np.array(ids, np.int64), np.array(tags, np.int64), data, ends - sizes, ends, np.array(offsets, np.int64)

    for batch in batches:
        texts = batch.column(2).cast(pa.binary())
        for doc, tag, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), texts, strict=True):
            text = memoryview(text.as_buffer()) if text.is_valid else b""
            if len(text) < LEAST:
                continue
            for at in range(0, max(1, len(text) - LEAST + 1), chunk):
                ids.append(LAST_ID if doc is None else doc)
                tags.append(tag)
                parts.append(text[at : at + chunk + LEAST - 1])
                offsets.append(at)
                size += len(parts[-1])
                if size >= chunk:
                    yield out()
                    ids, tags, parts, offsets, size = [], [], [], [], 0
    if parts:
        yield out()


# --- buckets ----------------------------------------------------------------


def _padded(contexts: Contexts):
    """Bytes with spare ones, and the eight bytes at every offset."""
    data = np.concatenate([contexts.body, np.zeros(WIDTH + 16, np.uint8)])
    return data, _eights(data)


def classes(contexts: Contexts, data: np.ndarray, same: np.ndarray) -> np.ndarray:
    """For every context, the first one (by document) that has the same bytes; those of equal hashes are compared byte by byte."""
    order = np.lexsort((contexts.at, contexts.doc, same))
    new = np.ones(len(order), bool)
    new[1:] = same[order[1:]] != same[order[:-1]]
    leader = np.empty(len(order), np.int64)
    leader[order] = order[np.maximum.accumulate(np.where(new, np.arange(len(order)), 0))]
    rows = np.nonzero(leader != np.arange(len(leader)))[0]
    eights, starts, sizes = _eights(data), contexts.starts, contexts.sizes
    differ = sizes[rows] != sizes[leader[rows]]
    for offset in range(0, WIDTH, 8):  # the last eight bytes again where fewer are left
        at = np.minimum(offset, sizes[rows] - 8)
        differ |= eights[starts[rows] + at] != eights[starts[leader[rows]] + at]
    leader[rows[differ]] = rows[differ]
    return leader


def _copies(contexts: Contexts, leader: np.ndarray):
    """(followers in the order of their leaders, leaders that have some, first follower of each): contexts that a smaller document has."""
    follower = np.nonzero(contexts.doc > contexts.doc[leader])[0]
    follower = follower[np.argsort(leader[follower], kind="stable")]
    own, first = np.unique(leader[follower], return_index=True)
    return follower, own, np.append(first, len(follower))


def settled_copies(contexts: Contexts, same: np.ndarray | None = None):
    """(spans of contexts that a smaller document has, numbers of all others), by the intervals over the classes with copies alone."""
    data, eights = _padded(contexts)
    same = context_hashes(eights, contexts.starts, contexts.sizes) if same is None else same
    copies = _copies(contexts, classes(contexts, data, same))
    none = np.zeros(0, np.int64)
    spans = removed_spans(contexts, data, none, none, copies)
    open_ = np.ones(len(contexts), bool)
    open_[copies[0]] = False
    return spans, np.nonzero(open_)[0]


def repeated_windows(contexts: Contexts, eights: np.ndarray, rest: np.ndarray):
    """(context, offset) of the windows of the given contexts that may occur more than once."""
    # of a shared window, the anchor and half of the rest on one side agree: contexts that share neither half are done
    starts, sizes, place = contexts.starts, contexts.sizes, contexts.place
    anchor = starts[rest] + place[rest]
    left = np.where(place[rest] >= HALF, _reads(eights, np.maximum(anchor - HALF, 0), HALF + GRAM), 0)
    right = np.where(place[rest] + GRAM + HALF <= sizes[rest], _reads(eights, anchor, HALF + GRAM), 0)
    rest = rest[_repeated(left) | _repeated(right)]
    counts = sizes[rest] - LEAST + 1
    owner = np.repeat(rest, counts)
    offset = np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts)
    kept = _repeated(_reads(eights, starts[owner] + offset, LEAST))
    return owner[kept], offset[kept]


def bucket_spans(contexts: Contexts):
    """Spans (doc, tag, start, end) that a smaller document also has, of the contexts of one bucket."""
    data, eights = _padded(contexts)
    copies = _copies(contexts, classes(contexts, data, context_hashes(eights, contexts.starts, contexts.sizes)))
    rest = np.ones(len(contexts), bool)
    rest[copies[0]] = False
    return removed_spans(contexts, data, *repeated_windows(contexts, eights, np.nonzero(rest)[0]), copies)


def _reads(eights: np.ndarray, at: np.ndarray, size: int) -> np.ndarray:
    out = np.full(len(at), size, np.uint64)
    for offset in [*range(0, size - 7, 8), size - 8]:
        out = _mix(out, eights[at + offset])
    return out


def _repeated(hashes: np.ndarray) -> np.ndarray:
    """Which values occur more than once; 0 never counts."""
    order = np.argsort(hashes)
    ordered = hashes[order]
    equal = np.zeros(len(ordered) + 1, bool)
    equal[1:-1] = (ordered[1:] == ordered[:-1]) & (ordered[1:] != 0)
    out = np.empty(len(ordered), bool)
    out[order] = equal[1:] | equal[:-1]
    return out


def intervals(contexts: Contexts, data: np.ndarray, owner: np.ndarray, offset: np.ndarray, twice: np.ndarray):
    """(context, offset, whether it stands for copies, first, last, depth): the enhanced suffix array of the given
    windows and of the contexts ``twice`` and their copies, and its left-diverse common-prefix intervals."""
    zeros = np.zeros(len(twice), np.int64)
    stands = np.repeat([False, True], [len(owner) + len(twice), len(twice)])
    owner, offset = np.concatenate([owner, twice, twice]), np.concatenate([offset, zeros, zeros])
    length = contexts.sizes[owner] - offset
    table = np.empty((len(owner), WIDTH + 1), np.uint8)
    table[:, :WIDTH] = np.lib.stride_tricks.sliding_window_view(data, WIDTH)[contexts.starts[owner] + offset]
    table[:, :WIDTH][np.arange(WIDTH) >= length[:, None]] = 0
    table[:, WIDTH] = length  # a text's zero bytes come after the end of a shorter one
    order = np.argsort(table.view(f"S{WIDTH + 1}").ravel(), kind="stable")
    table, length, owner, offset, stands = table[order], length[order], owner[order], offset[order], stands[order]
    lcp = np.zeros(len(order), np.int64)
    differ = table[1:, :WIDTH] != table[:-1, :WIDTH]
    lcp[1:] = np.minimum(np.where(differ.any(1), differ.argmax(1), WIDTH), np.minimum(length[1:], length[:-1]))
    left = np.where(offset > 0, data[contexts.starts[owner] + offset - 1].astype(np.int64), -1)
    low, high, depth = lcp_intervals(lcp, LEAST)
    wide = left_diverse(left, low, high) if len(low) else np.zeros(0, bool)
    return owner, offset, stands, low[wide], high[wide], depth[wide]


def _members(low: np.ndarray, high: np.ndarray):
    """(interval, place in the suffix array) of all members of intervals."""
    counts = high - low + 1
    number = np.repeat(np.arange(len(low)), counts)
    return number, np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts) + low[number]


def removed_spans(contexts: Contexts, data: np.ndarray, owner: np.ndarray, offset: np.ndarray, copies):
    """Spans (doc, tag, start, end) of occurrences of maximal repeats that a smaller document has too; copies follow their class."""
    follower, twice, first = copies
    owner, offset, stands, low, high, depth = intervals(contexts, data, owner, offset, twice)
    if not len(low):
        none = np.zeros(0, np.int64)
        return none, none, none, none
    ids = np.append(contexts.doc[owner], LAST_ID)
    least = np.minimum.reduceat(ids, np.stack([low, high + 1], 1).ravel())[::2]
    number, member = _members(low, high)
    mine, depth = owner[member], depth[number]
    alone = ~stands[member] & (contexts.doc[mine] > least[number])
    whole = np.nonzero(stands[member] & (depth == contexts.sizes[mine]))[0]  # the class's own interval
    number_of = np.searchsorted(twice, mine[whole])
    counts = first[number_of + 1] - first[number_of]
    theirs = follower[np.repeat(first[number_of] - np.cumsum(counts) + counts, counts) + np.arange(counts.sum())]
    rows = np.concatenate([mine[alone], theirs])
    begin = contexts.at[rows] + np.concatenate([offset[member][alone], np.zeros(len(theirs), np.int64)])
    return contexts.doc[rows], contexts.tag[rows], begin, begin + np.concatenate([depth[alone], contexts.sizes[theirs]])


def divided(contexts: Contexts, level: int):
    """(contexts, bucket hashes) of the next level: by the anchor with the bytes on each side, then by whole windows."""
    data, eights = _padded(contexts)
    starts, sizes, place = contexts.starts, contexts.sizes, contexts.place
    if level == 1:
        left, right = np.nonzero(place >= HALF)[0], np.nonzero(place + GRAM + HALF <= sizes)[0]
        hashes = np.concatenate([_reads(eights, starts[left] + place[left] - HALF, HALF + GRAM), ~_reads(eights, starts[right] + place[right], HALF + GRAM)])
        return contexts.take(np.concatenate([left, right])), hashes
    counts = sizes - LEAST + 1
    rows = np.repeat(np.arange(len(contexts)), counts)
    offsets = np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts)
    return contexts.parts(rows, offsets, np.full(len(rows), LEAST)), _reads(eights, starts[rows] + offsets, LEAST)


def _settle(batches, level: int, most: int):
    """Reads the sorted rows of one partition, bucket after bucket; yields spans by document, and rows for the next level."""
    current, contexts, spans, size, over = None, [], [], 0, False

    def rows(found):
        parts = [tuple(c.astype(np.int64) for c in s) for s in found]
        ids, tags, starts, ends = _by_document(*(np.concatenate(c) for c in zip(*parts, strict=True))) if parts else [np.zeros(0, np.int64)] * 4
        if not len(ids):
            return
        cuts = np.concatenate([[0], np.nonzero((ids[1:] != ids[:-1]) | (tags[1:] != tags[:-1]))[0] + 1, [len(ids)]])
        both = np.stack([starts, ends], 1).astype("<u4")
        blobs = [both[a:b].tobytes() for a, b in zip(cuts[:-1], cuts[1:], strict=True)]
        yield pa.RecordBatch.from_arrays([pa.nulls(len(blobs), pa.int64()), pa.array(ids[cuts[:-1]]), pa.array(tags[cuts[:-1]]), pa.array(blobs, pa.binary())], ["bucket", "doc", "tag", "spans"])

    def send():
        """Passes the contexts of a bucket that is too large on to the next level."""
        whole = Contexts.joined(contexts)
        step = max(1, (most // 64) // (1 if level == 1 else LEAST))
        for at in range(0, len(whole), step):
            part, hashes = divided(whole.take(np.arange(at, min(at + step, len(whole)))), level)
            for bucket, blob in part.by_bucket((hashes >> np.uint64(1)).astype(np.int64)):
                yield pa.RecordBatch.from_arrays([pa.array([bucket]), pa.nulls(1, pa.int64()), pa.nulls(1, pa.int64()), pa.array([blob], pa.binary())], ["bucket", "doc", "tag", "spans"])
        contexts.clear()

    def close():
        nonlocal over, size
        if over and contexts:
            yield from send()
        elif contexts:
            spans.append(bucket_spans(Contexts.joined(contexts)))
        yield from rows(spans)
        contexts.clear()
        spans.clear()
        size, over = 0, False

    for batch in batches:
        for bucket, kind, blob in zip(*(batch.column(i) for i in range(3)), strict=True):
            if bucket.as_py() != current:
                yield from close()
                current = bucket.as_py()
            if kind.as_py() == 0:
                spans.append(_unpack(blob.as_py(), _SPANS)[:4])
                continue
            contexts.append(Contexts.unpacked(blob.as_py()))
            size += len(contexts[-1].body)
            if size > most:  # copies go first; if that is not enough, so does the bucket
                whole = Contexts.joined(contexts)
                found, open_ = settled_copies(whole)
                contexts[:] = [whole.take(open_)]
                size = len(contexts[0].body)
                yield from rows([*spans, found])
                spans.clear()
                if size > most // 2 and level < LEVELS:
                    over = True
                    yield from send()
                    size = 0
    yield from close()


#: Levels of buckets: by anchor, by the anchor with one side, by window (where a bucket holds one class, and no more is needed).
LEVELS = 3


def _buckets(docs: DataFrame) -> tuple[int, int]:
    """(buckets, partitions) that fit the bytes of text."""
    total = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    buckets = max(1, -(-total // BUCKET))
    return buckets, max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), min(buckets, PARTITIONS))


def repeated_spans(docs: DataFrame, chunk: int = CHUNK, held: int = HELD, hot: int = HOT) -> DataFrame:
    """(doc, tag, spans): byte spans (packed starts and ends) that smaller documents have; ``docs`` has doc_id, tag, text."""
    buckets, parts = _buckets(docs)
    rows = docs.select("doc_id", "tag", "text").mapInArrow(tidied(lambda b: _deal(b, buckets, chunk, held)), "bucket long, kind int, data binary")
    out = None
    for level in range(1, LEVELS + 1):
        ordered = rows.repartition(parts, "bucket").sortWithinPartitions("bucket")
        found = written(ordered.mapInArrow(tidied(lambda b, level=level: _settle(b, level, hot)), "bucket long, doc long, tag long, spans binary"), "repeats")
        spans, rows = found.where(F.col("bucket").isNull()), found.where(F.col("bucket").isNotNull())
        out = spans if out is None else out.unionByName(spans)
        if not rows.limit(1).count():
            break
        rows = rows.select("bucket", F.lit(1).alias("kind"), F.col("spans").alias("data"))
    return out.groupBy("doc", "tag").agg(F.collect_list("spans").alias("spans"))


def repeat_groups(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(repeat, length, doc_id, start): every maximal repeat within contexts, a row for each occurrence in bytes.

    Equal contexts are counted first and stand for each other, so a bucket holds every context once, however
    many copies it has; the occurrences follow by a join on the context. Rows with null id have the last id.
    """
    rows = docs.select(F.col(key).cast("long").alias("doc_id"), F.lit(0).cast("long").alias("tag"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    buckets, parts = _buckets(rows)

    def spread(batches):
        for contexts, grams, _ in contexts_of(batches):
            body = contexts.body.tobytes()
            blobs = [body[a : a + n] for a, n in zip(contexts.starts.tolist(), contexts.sizes.tolist(), strict=True)]
            bucket = ((grams >> np.uint64(20)) % np.uint64(buckets)).astype(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(bucket), pa.array(blobs, pa.binary()), pa.array(contexts.place.astype(np.int32)), pa.array(contexts.doc), pa.array(contexts.at)], ["bucket", "context", "place", "doc_id", "at"])

    def find(batches):
        current, held = None, []

        def close():
            if held:
                yield _groups(held)

        for batch in batches:
            for row in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                if row[0] != current:
                    yield from close()
                    current, held = row[0], []
                held.append(row)
        yield from close()

    places = rows.mapInArrow(tidied(spread), "bucket long, context binary, place int, doc_id long, at long")
    kinds = places.groupBy("bucket", "context", "place").agg(F.count("*").alias("n")).repartition(parts, "bucket").sortWithinPartitions("bucket")
    found = written(kinds.mapInArrow(tidied(find), "repeat binary, length long, context binary, place int, offset long"), "repeat-groups")
    met = places.select("context", "place", "doc_id", "at").join(found, ["context", "place"])
    return met.select(F.lower(F.hex("repeat")).alias("repeat"), "length", "doc_id", (F.col("at") + F.col("offset")).alias("start"))


def _groups(held) -> pa.RecordBatch:
    """(repeat, length, context, place, offset) of the maximal repeats of one bucket's contexts (bucket, bytes, place of the anchor, copies)."""
    sizes = np.array([len(c) for _, c, _, _ in held])
    zeros = np.zeros(len(held), np.int64)
    contexts = Contexts(zeros, zeros, zeros, sizes, np.array([p for _, _, p, _ in held]), np.frombuffer(b"".join(c for _, c, _, _ in held), np.uint8))
    data, eights = _padded(contexts)
    twice = np.nonzero(np.array([n for *_, n in held]) > 1)[0]
    owner, offset = repeated_windows(contexts, eights, np.arange(len(held)))
    owner, offset, stands, low, high, depth = intervals(contexts, data, owner, offset, twice)
    number, member = _members(low, high)
    own = np.unique(np.stack([number, owner[member], offset[member]], 1), axis=0)
    names = [xxhash.xxh3_128_digest(data[contexts.starts[owner[a]] + offset[a] :][:n].tobytes()) for a, n in zip(low.tolist(), depth.tolist(), strict=True)]
    return pa.RecordBatch.from_arrays([pa.array([names[i] for i in own[:, 0]], pa.binary()), pa.array(depth[own[:, 0]]), pa.array([held[i][1] for i in own[:, 1]], pa.binary()), pa.array([held[i][2] for i in own[:, 1]], pa.int32()), pa.array(own[:, 2])], ["repeat", "length", "context", "place", "offset"])


def removed(docs: DataFrame, key: str = "doc_id", text: str = "text", with_text: bool = False, **sizes: int) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256) of every row; ``with_text`` adds the bytes kept, ``sizes`` are those of ``repeated_spans``."""
    rows = docs.select(F.col(key).cast("long").alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    repeated = rows.groupBy("doc_id").count().where(F.col("count") > 1).limit(1).count() > 0
    tag = F.xxhash64("text") if repeated else F.lit(0).cast("long")  # tells rows with equal ids apart
    rows = rows.withColumn("tag", tag)
    spans = written(repeated_spans(rows, **sizes), "repeats")
    few = spans.count() <= BROADCAST_ROWS
    size = spans.agg(F.sum(F.aggregate("spans", F.lit(0), lambda n, s: n + F.octet_length(s)))).first()[0] or 0
    side = F.broadcast(spans) if few and size <= 64 << 20 else spans
    joined = rows.withColumn("doc", F.coalesce("doc_id", F.lit(LAST_ID))).join(side, ["doc", "tag"], "left").select("doc_id", "text", "spans")

    def run(batches):
        for batch in batches:
            sizes, gone, runs, digests, kept = [], [], [], [], []
            for text, packed in zip(batch.column(1).cast(pa.binary()), batch.column(2), strict=True):
                body = text.as_py() or b""
                both = np.frombuffer(b"".join(packed.as_py() or []), "<u4").astype(np.int64).reshape(-1, 2)
                starts, ends = merged(both[:, 0], both[:, 1])
                edges = [0, *np.stack([starts, ends], 1).ravel().tolist(), len(body)]
                left = b"".join([body[a:b] for a, b in zip(edges[::2], edges[1::2], strict=True)])
                sizes.append(len(body))
                gone.append(len(body) - len(left))
                runs.append(len(starts))
                digests.append(hashlib.sha256(left).hexdigest())
                kept.append(left if with_text else None)
            columns = [batch.column(0), pa.array(sizes, pa.int64()), pa.array(gone, pa.int64()), pa.array(runs, pa.int64()), pa.array(digests, pa.string())]
            yield pa.RecordBatch.from_arrays(columns + ([pa.array(kept, pa.binary())] if with_text else []), ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", *(["kept"] if with_text else [])])

    schema = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + (", kept binary" if with_text else "")
    return joined.mapInArrow(tidied(run), schema)
