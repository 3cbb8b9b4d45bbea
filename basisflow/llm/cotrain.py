"""Quality classifier by co-training of a text view and a metadata view.

Two targets are learned: whether a document is of quality, and whether it is toxic.
For each, a logistic regression sees only the text (chosen words and shape of the
writing), another only what a page's record says (source, language, length). In every
round each view hands to the other the documents of an unlabelled pool that it is surest
of, so many of each class as the labels have of it, with its calibrated probability as
the label; the pool is filled up from round to round. Labelled rows kept apart calibrate
both views and weigh them against each other, and the combined score is given to every document.

Fitting uses bounded samples (``LABELLED`` rows, every combination of labels well represented and
weighted by its share, and a pool of ``POOL`` rows, those with the smallest id hashes);
scoring reads all documents whole.

Defined results: null texts count as empty and other null columns as a value of their own;
repeated rows are scored one by one; of repeated labels the lower quality and the
higher toxicity hold; without labels of both kinds a target's score is the share of
its positive labels (0.5 without any); an empty table gives no rows; further columns
are ignored.
"""

from __future__ import annotations

import math
import re
import zlib
from collections import Counter
from dataclasses import dataclass
from functools import reduce
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import tidied

#: Bounds of the samples used for fitting.
LABELLED, POOL = 6000, 4000
#: Rounds of exchange, share of the pool that a view hands over in each, and the weight of a pseudo-label.
ROUNDS, GROW, PSEUDO = 3, 0.1, 0.3
#: Gradient steps of a first fit and of one that goes on from it.
STEPS, MORE_STEPS = 250, 80
#: Words that the text view may use, fewest labelled documents of one, and buckets of the metadata view.
WORDS, LEAST_DOCS, BUCKETS = 8000, 4, 4096
#: Lengths of word beginnings that count as features.
PREFIXES = (4, 5, 6)
#: One labelled row in so many is kept apart for calibration.
APART = 4
CACHE_PIECES = 300_000
TARGETS = ("quality", "toxic")
_EDGES = re.compile(r"^[\W_]+|[\W_]+$")


def word(piece: str) -> str:
    piece = piece.lower()
    return piece if piece.isalnum() else _EDGES.sub("", piece)


def marks(piece: str) -> list[str]:
    """Text features of one piece: its word and the word's beginnings."""
    w = word(piece)
    return [w, *(w[:n] + "-" for n in PREFIXES if len(w) > n)] if w else []


def shape(text: str, pieces: list[str]) -> np.ndarray:
    """Dense features of the writing, about -1 to 1 each."""
    n, chars = len(pieces) + 1, len(text) + 1
    upper = sum(map(str.isupper, pieces)) / n
    counts = [text.count(c) for c in "!|#*=<>{}%&$"]
    distinct = len(set(pieces)) / n
    lines = text.count("\n")
    return np.array([upper, min(1, 20 * counts[0] / chars), min(1, 20 * counts[1] / chars), min(1, 20 * sum(counts[2:]) / chars), distinct, min(1, chars / n / 20), min(1, 100 * lines / chars), min(1, np.log1p(n) / 10), float(n < 12)])


def metadata(source, lang, n_chars: int) -> list[int]:
    """Hashed features of a page's record."""
    size = (n_chars + 1).bit_length()
    return [zlib.crc32(x.encode()) % BUCKETS for x in (f"s:{source}", f"l:{lang}", f"n:{size}", f"m:{int(4 * math.log2(n_chars + 1))}", f"sl:{source}:{lang}", f"ln:{lang}:{size}", f"sn:{source}:{size}")]


class Sparse:
    """Rows of active columns, and a few dense columns."""

    def __init__(self, rows: list, dense: np.ndarray, width: int):
        self.sizes = np.array([len(r) for r in rows], np.int64)
        self.columns = np.concatenate([np.asarray(r, np.int64) for r in rows]) if rows else np.zeros(0, np.int64)
        self.row_of = np.repeat(np.arange(len(rows)), self.sizes)
        self.dense, self.width = dense, width

    def __len__(self):
        return len(self.sizes)

    def times(self, weights: np.ndarray) -> np.ndarray:
        return np.bincount(self.row_of, weights[self.columns], len(self)) + self.dense @ weights[self.width :]

    def gathered(self, values: np.ndarray) -> np.ndarray:
        return np.concatenate([np.bincount(self.columns, values[self.row_of], self.width), self.dense.T @ values])


def sigmoid(z):
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def fit(x: Sparse, y: np.ndarray, weight: np.ndarray, start: np.ndarray | None = None, penalty: float = 0.003) -> np.ndarray:
    """Logistic regression on labels from 0 to 1 by accelerated gradient steps of per-column size; the last dense column is the constant."""
    total = max(weight.sum(), 1e-9)
    scale = np.concatenate([np.bincount(x.columns, weight[x.row_of], x.width), (x.dense**2 * weight[:, None]).sum(0)]) / total
    rate = 1 / (0.25 * scale * max(1.0, x.sizes.mean() ** 0.5 if len(x) else 1.0) + penalty + 0.02)
    w = v = np.zeros(x.width + x.dense.shape[1]) if start is None else start
    ridge = np.append(np.ones(len(w) - 1), 0.0)
    ridge[x.width :] *= 0.1
    best, best_loss = w, np.inf
    for step in range(STEPS if start is None else MORE_STEPS):
        z = x.times(v)
        loss = (weight * (np.logaddexp(0, z) - y * z)).sum() / total
        if loss < best_loss:
            best, best_loss = v, loss
        elif loss > 2 * best_loss + 0.1:
            rate, v, w = rate / 2, best, best
            continue
        fresh = v - rate * (x.gathered(weight * (sigmoid(z) - y)) / total + penalty * ridge * v)
        v, w = fresh + step / (step + 3) * 0.8 * (fresh - w), fresh
    return best


def calibrated(z: np.ndarray, y: np.ndarray, weight: np.ndarray) -> tuple[float, float]:
    """(slope, constant), slope not negative, that make the scores ``z`` log-odds of ``y``."""
    c = np.array([1.0, 0.0])
    x = np.stack([z, np.ones(len(z))], 1)
    for _ in range(30):
        p = sigmoid(x @ c)
        bend = (x * (weight * p * (1 - p))[:, None]).T @ x + 0.1 * np.eye(2)
        c = c - np.linalg.solve(bend, x.T @ (weight * (p - y)) + 0.1 * (c - [1.0, 0.0]))
        c[0] = max(c[0], 0.0)
    return float(c[0]), float(c[1])


@dataclass
class Model:
    words: dict[str, int]
    views: list  # for each target: (text weights, metadata weights, combining weights) or a constant
    exchanged: list  # for each target and round: numbers of documents that the text view and the metadata view handed over

    def score(self, target: int, text: Sparse, meta: Sparse) -> np.ndarray:
        view = self.views[target]
        if isinstance(view, float):
            return np.full(len(text), view)
        a, b, (bias, wa, wb) = view
        return sigmoid(bias + wa * text.times(a) + wb * meta.times(b))


class Features:
    """Features of rows (text, source, lang), through a cache of pieces."""

    def __init__(self, words: dict[str, int]):
        self.words, self._known = words, {}

    def __call__(self, rows) -> tuple[Sparse, Sparse]:
        lists, shapes, metas = [], [], []
        for text, source, lang in rows:
            text = text or ""
            pieces, known = text.split(), self._known
            if len(known) > CACHE_PIECES:
                known.clear()
            distinct = set(pieces)
            for p in distinct:
                if p not in known:
                    known[p] = tuple(self.words[m] for m in marks(p) if m in self.words)
            lists.append(list(set(chain.from_iterable(map(known.__getitem__, distinct)))))
            shapes.append(np.append(shape(text, pieces), 1.0))
            metas.append(metadata(source, lang, len(text)))
        ones = np.ones((len(lists), 1))
        return Sparse(lists, np.array(shapes) if shapes else np.zeros((0, 10)), len(self.words)), Sparse(metas, ones, BUCKETS)


def chosen_words(texts, labels: np.ndarray) -> dict[str, int]:
    """Words whose presence tells most about some target, by the size of their log-likelihood ratio."""
    total, given = Counter(), [Counter() for _ in TARGETS]
    for text, given_marks in zip(texts, labels, strict=True):
        present = {m for p in set((text or "").split()) for m in marks(p)}
        total.update(present)
        for t, counter in enumerate(given):
            if given_marks[t] > 0.5:
                counter.update(present)
    names = [w for w, n in total.items() if n >= LEAST_DOCS]
    if not names:
        return {}
    n = np.array([total[w] for w in names], float)
    best = np.zeros(len(names))
    for t, counter in enumerate(given):
        share = (labels[:, t].sum() + 0.5) / (len(labels) + 1)
        seen = np.array([counter[w] for w in names], float)
        p = (seen + share) / (n + 1)
        best = np.maximum(best, n * (p * np.log(p / share + 1e-12) + (1 - p) * np.log((1 - p) / (1 - share) + 1e-12)))
    return {names[i]: k for k, i in enumerate(np.argsort(-best, kind="stable")[:WORDS])}


def train(labelled: list[tuple], pool: list[tuple]) -> Model:
    """From rows (text, source, lang, quality, toxic, weight) and rows (text, source, lang)."""
    truth = np.array([[r[3], r[4]] for r in labelled], float).reshape(-1, 2)
    weight = np.array([r[5] for r in labelled], float)
    apart = np.arange(len(labelled)) % APART == 0
    rows = [[r[:3] for r, a in zip(labelled, apart, strict=True) if a == side] for side in (False, True)]
    words = chosen_words([r[0] for r in rows[0]], truth[~apart])
    features = Features(words)
    fitted, kept, drawn = features(rows[0]), features(rows[1]), features(pool)
    views, exchanged = [], []
    for t in range(len(TARGETS)):
        y, y_apart = truth[~apart, t], truth[apart, t]
        exchanged.append([])
        if min(y.sum(), len(y) - y.sum()) < 2 or min(y_apart.sum(), len(y_apart) - y_apart.sum()) < 1:
            views.append(float(np.average(truth[:, t], weights=weight)) if len(truth) else 0.5)
            continue
        views.append(_cotrain(fitted, y, weight[~apart], kept, y_apart, weight[apart], drawn, exchanged[-1]))
    return Model(words, views, exchanged)


def _stack(a: Sparse, b: Sparse) -> Sparse:
    out = Sparse([], np.concatenate([a.dense, b.dense]), a.width)
    out.sizes, out.columns = np.concatenate([a.sizes, b.sizes]), np.concatenate([a.columns, b.columns])
    out.row_of = np.concatenate([a.row_of, b.row_of + len(a)])
    return out


def surest(z: np.ndarray, free: np.ndarray, prior: float, count: int) -> np.ndarray:
    """Of the free rows, those with the highest and the lowest score: ``count`` in all, of each class its share."""
    rows = np.nonzero(free)[0]
    rows = rows[np.argsort(-z[rows], kind="stable")]
    count = min(count, len(rows))
    high = min(max(1, round(count * prior)), max(1, count - 1), count)
    return np.concatenate([rows[:high], rows[len(rows) - (count - high) :]])


def _cotrain(fitted, y, weight, kept, y_apart, weight_apart, drawn, exchanged):
    prior, size = float(np.average(y, weights=weight)), len(drawn[0])
    told = [np.full(size, -1.0), np.full(size, -1.0)]  # labels that each view has got
    joined = [_stack(fitted[v], drawn[v]) for v in (0, 1)]
    weights, scale = [None, None], [(1.0, 0.0), (1.0, 0.0)]
    for round_ in range(ROUNDS + 1):
        for v in (0, 1):
            weights[v] = fit(joined[v], np.concatenate([y, np.maximum(told[v], 0)]), np.concatenate([weight, PSEUDO * (told[v] >= 0)]), weights[v])
            scale[v] = calibrated(kept[v].times(weights[v]), y_apart, weight_apart)
        if round_ == ROUNDS or not size:
            break
        open_ = np.arange(size) < -(-size * (round_ + 2) // (ROUNDS + 1))  # the pool is filled up
        given = []
        for v in (0, 1):
            z = scale[v][0] * drawn[v].times(weights[v]) + scale[v][1]
            given.append((found := surest(z, open_ & (told[1 - v] < 0), prior, max(2, int(GROW * size))), sigmoid(z[found])))
        for v in (0, 1):
            told[1 - v][given[v][0]] = given[v][1]
        exchanged.append(tuple(len(rows) for rows, _ in given))
    # a share of each calibrated view, the one that explains the rows kept apart best, calibrated as a whole
    z = [scale[v][0] * kept[v].times(weights[v]) + scale[v][1] for v in (0, 1)]
    loss = lambda share: (weight_apart * (np.logaddexp(0, mix := (1 - share) * z[0] + share * z[1]) - y_apart * mix)).sum()
    share = min(np.linspace(0.0, 1.0, 21), key=loss)
    slope, constant = calibrated((1 - share) * z[0] + share * z[1], y_apart, weight_apart)
    parts = [slope * (1 - share), slope * share]
    return weights[0], weights[1], (constant + sum(parts[v] * scale[v][1] for v in (0, 1)), parts[0] * scale[0][0], parts[1] * scale[1][0])


def quotas(counts: dict, most: int) -> dict:
    """How many labelled rows of each combination of labels are fitted on: all where they fit, else at least an eighth of ``most`` of each that has them."""
    total = sum(counts.values())
    least = {k: min(n, most // (2 * max(1, len(counts)))) for k, n in counts.items()}
    spare, more = most - sum(least.values()), total - sum(least.values())
    return {k: n if total <= most else least[k] + (spare * (n - least[k])) // max(1, more) for k, n in counts.items()}


def _hash_cut(share: float) -> int:
    """Bound on a signed 64-bit hash that about this share of hashes does not exceed."""
    return min(int(-(1 << 63) + min(1.0, share) * ((1 << 64) - 1)), (1 << 63) - 1)


def samples(docs: DataFrame, labels: DataFrame):
    """Bounded samples (labelled rows, pool rows) for ``train``, chosen by hashes of ids."""
    order = F.xxhash64("doc_id")
    sure = labels.where(F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.min("quality").alias("quality"), F.max("toxic").alias("toxic")).where(F.col("quality").isNotNull() & F.col("toxic").isNotNull())
    counts = {(r["quality"], r["toxic"]): r["count"] for r in sure.groupBy("quality", "toxic").count().collect()}
    wanted = quotas(counts, LABELLED)
    parts = []
    for (quality, toxic), n in wanted.items():
        # hashes are near uniform: a cut at twice the share wanted leaves a bounded number of rows
        near = sure.where((F.col("quality") == quality) & (F.col("toxic") == toxic) & (order <= F.lit(_hash_cut((2 * n + 50) / counts[quality, toxic]))))
        parts.append(near.orderBy(order, "doc_id").limit(n))
    marked = reduce(DataFrame.unionByName, parts, sure.limit(0))
    fields = docs.select("doc_id", "text", "source", "lang")
    rows = fields.join(F.broadcast(marked), "doc_id").orderBy(order, "doc_id", "text").limit(LABELLED).collect()
    taken = Counter((r["quality"], r["toxic"]) for r in rows)
    share = {k: counts[k] / n * sum(taken.values()) / sum(counts[x] for x in taken) for k, n in taken.items()}
    count = docs.count()
    near = fields.where(F.xxhash64("doc_id", F.lit("pool")) <= F.lit(_hash_cut(2 * POOL / max(count, 1) + 0.001)))
    pool = near.orderBy(F.xxhash64("doc_id", F.lit("pool")), "doc_id", "text").limit(POOL).collect()
    known = {r["doc_id"] for r in rows}
    return [(r["text"], r["source"], r["lang"], r["quality"], r["toxic"], share[r["quality"], r["toxic"]]) for r in rows], [(r["text"], r["source"], r["lang"]) for r in pool if r["doc_id"] not in known]


def score(docs: DataFrame, model: Model) -> DataFrame:
    """(doc_id, quality_score, toxic_score, keep) of every row."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # bounded by WORDS and BUCKETS

    def run(batches):
        features = Features(shared.value.words)
        for batch in batches:
            text, meta = features(zip(*(batch.column(i).to_pylist() for i in (1, 2, 3)), strict=True))
            quality, toxic = (shared.value.score(t, text, meta) for t in range(2))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(quality), pa.array(toxic), pa.array((quality >= 0.5) & (toxic < 0.5))], ["doc_id", "quality_score", "toxic_score", "keep"])

    return docs.select(F.col("doc_id").cast("long"), "text", "source", "lang").mapInArrow(tidied(run), "doc_id long, quality_score double, toxic_score double, keep boolean")


def classify(docs: DataFrame, labels: DataFrame) -> DataFrame:
    return score(docs, train(*samples(docs, labels)))
