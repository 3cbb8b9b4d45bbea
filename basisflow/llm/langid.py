"""Language identification with spans for mixed-language text.

A model has, for every language, smoothed log-frequencies of whole words and of
character n-grams within words, and the scripts its letters come from. Words end at white
space and where letters of another script begin; scripts written without spaces are cut
into single characters or short stretches. Of a text, each word's scripts narrow the
languages that may have written it; each word is scored in those; Viterbi with a penalty
for each change of language labels the words, and runs of equal labels are the spans. The
text's language is the one whose spans hold most letters.

Defined results: null texts and texts without a letter get ``und`` with score 0; of
languages with equal letters the one with the better word scores wins, then the first by
name; of paths with equal scores a word stays with its predecessor's language;
repeated rows and null ids are labelled one by one; texts are read whole; an empty
table gives no rows; training without labelled rows gives ``und`` for all; further
columns are ignored by ``label`` and kept by ``accepted``.
"""

from __future__ import annotations

import bisect
import math
import re
from collections import Counter
from dataclasses import dataclass, field
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from basisflow.sources.payloads import dealt

from .common import portions, tidied

UNKNOWN = "und"
#: First code points of public Unicode blocks, and the script of each stretch.
SCRIPT_STARTS = (0x0000, 0x0370, 0x0400, 0x0530, 0x0590, 0x0600, 0x0700, 0x0900, 0x0980, 0x0E00, 0x0E80, 0x10A0, 0x1100, 0x1200, 0x1E00, 0x1F00, 0x2000, 0x3040, 0x3100, 0x3400, 0xAC00, 0xD7B0, 0xF900, 0xFB00, 0xFB50)
SCRIPT_NAMES = ("latin", "greek", "cyrillic", "armenian", "hebrew", "arabic", "other", "devanagari", "other", "thai", "other", "georgian", "hangul", "other", "latin", "greek", "other", "kana", "other", "han", "hangul", "other", "han", "latin", "other")
#: Most labelled documents learned from, for each language.
TRAIN_DOCS = 800
#: Scripts written without spaces, and the characters of one word of theirs.
UNSPACED = {"han": 1, "kana": 2, "thai": 4}
#: Length of n-grams, and the log-probability cost of a change of language.
GRAM, SWITCH = 3, 8.0
#: Share of a script's letters that a language must have had in training to be a candidate.
SCRIPT_SHARE = 0.01
#: Word scores kept per Python worker.
CACHE_WORDS = 300_000
_BEYOND_LATIN = re.compile(r"[^\x00-\u024f]")


def script(char: str) -> str:
    return SCRIPT_NAMES[bisect.bisect_right(SCRIPT_STARTS, ord(char)) - 1]


def letters(piece: str) -> str:
    return piece if piece.isalpha() else "".join(filter(str.isalpha, piece))


def cut(piece: str) -> list[str]:
    """A piece between spaces as words; what is not a letter stays with the word before it."""
    out, current, size, began = [], None, 0, 0
    for i, char in enumerate(piece):
        if not char.isalpha():
            continue
        own = script(char)
        if current is not None and (own != current or size >= UNSPACED.get(own, len(piece))):
            out.append(piece[began:i])
            began, size = i, 0
        current, size = own, size + 1
    return [*out, piece[began:]]


class Words:
    """The words of texts; how a piece is cut is remembered."""

    def __init__(self):
        self._cuts: dict[str, tuple[str, ...]] = {}

    def __call__(self, text: str | None) -> list[str]:
        text = (text or "").lower()
        pieces = text.split()
        if text.isascii() or not _BEYOND_LATIN.search(text):
            return pieces
        if len(self._cuts) > CACHE_WORDS:
            self._cuts.clear()
        out = []
        for piece in pieces:
            if piece.isascii():
                out.append(piece)
                continue
            words = self._cuts.get(piece)
            if words is None:
                words = tuple(cut(piece))
                if len(piece) <= 64:
                    self._cuts[piece] = words
            out += words
        return out


def grams(word: str) -> list[str]:
    padded = f" {word} "
    return [padded[i : i + GRAM] for i in range(len(padded) - GRAM + 1)]


@dataclass
class Model:
    """Score rows are log-shares by language; the last row of ``grams`` is for unseen n-grams."""

    langs: list[str]
    gram_rows: dict[str, int]
    grams: np.ndarray
    words: dict[str, np.ndarray]
    scripts: dict[str, np.ndarray] = field(default_factory=dict)

    def candidates(self, word: str) -> np.ndarray:
        """Languages whose training text used the scripts of the word; all, where that leaves none."""
        allowed = np.ones(len(self.langs), bool)
        for name in ("latin",) if word.isascii() else set(map(script, word)):
            allowed &= self.scripts.get(name, np.zeros(len(self.langs), bool))
        return allowed if allowed.any() else np.ones(len(self.langs), bool)

    def score(self, words: list[str]) -> np.ndarray:
        """Log-likelihood ratios of lower-case words (not empty), 0 in the best language, far below outside its scripts."""
        lists = [grams(w) for w in words]
        sizes = np.fromiter(map(len, lists), np.int64, len(lists))
        known, unseen = self.gram_rows.get, len(self.grams) - 1
        rows = np.fromiter((known(g, unseen) for g in chain.from_iterable(lists)), np.int64, int(sizes.sum()))
        starts = np.concatenate([[0], np.cumsum(sizes)[:-1]])
        out = np.add.reduceat(self.grams[rows], starts, axis=0) / np.sqrt(sizes)[:, None]
        for i, word in enumerate(words):
            if (own := self.words.get(word)) is not None:
                out[i] += own
        masks = {w: self.candidates(w) for w in words if not w.isascii()}
        latin = self.candidates("a")
        out[~np.array([masks.get(w, latin) for w in words])] = -1e4
        return out - out.max(1, keepdims=True)


def train(texts) -> Model:
    """From pairs (language, text)."""
    words: dict[str, Counter] = {}
    pieces = Words()
    for lang, text in texts:
        words.setdefault(lang, Counter()).update(filter(None, map(letters, pieces(text))))
    langs = sorted(words)
    totals: dict[str, dict[str, np.ndarray]] = {"grams": {}, "words": {}, "scripts": {}}
    for at, lang in enumerate(langs):
        counts: dict[str, Counter] = {"grams": Counter(), "words": words[lang], "scripts": Counter()}
        for word, n in words[lang].items():
            for gram in grams(word):
                counts["grams"][gram] += n
            counts["scripts"][script(word[0])] += n
        for kind, counter in counts.items():
            for item, n in counter.items():
                totals[kind].setdefault(item, np.zeros(len(langs)))[at] += n
    gram_names = list(totals["grams"])
    gram_scores = _log_shares([*totals["grams"].values(), np.zeros(len(langs))])
    kept = {w: c for w, c in totals["words"].items() if c.sum() >= 3}
    word_scores = _log_shares([*kept.values(), np.zeros(len(langs))])
    own = {w: (s - s.max()) / 2 for w, s in zip(kept, word_scores, strict=False)}
    volume = sum(totals["scripts"].values()) if totals["scripts"] else np.ones(len(langs))
    scripts = {name: counts >= SCRIPT_SHARE * volume for name, counts in totals["scripts"].items()}
    return Model(langs, {g: i for i, g in enumerate(gram_names)}, gram_scores, own, scripts)


def _log_shares(counts: list[np.ndarray]) -> np.ndarray:
    table = np.array(counts) + 0.5
    return np.log(table / table.sum(axis=0))


def training_rows(docs: DataFrame, per_lang: int = TRAIN_DOCS) -> list:
    """A bounded sample: for each language, the ``per_lang`` labelled rows whose id hash is smallest.

    Held-out rows (crc32 of the id as text, mod 4, equal to 2) never enter. The number of
    languages is found by a count over all rows.
    """
    usable = docs.where(F.col("lang").isNotNull() & F.col("doc_id").isNotNull() & (F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 != 2))
    order = F.xxhash64("doc_id")
    counted = {r["lang"]: r["count"] for r in usable.groupBy("lang").count().collect()}
    if not counted:
        return []
    # id hashes are near uniform: a cut at twice the share wanted leaves few rows, of which the first of each language are taken
    rows, share = [], {lang: (2 * per_lang + 50) / count for lang, count in counted.items()}
    while share:
        cuts = docs.sparkSession.createDataFrame([(lang, min(int(-(1 << 63) + min(1.0, part) * ((1 << 64) - 1)), (1 << 63) - 1)) for lang, part in share.items()], "lang string, cut long")
        rank = F.row_number().over(Window.partitionBy("lang").orderBy("o", "text"))
        near = usable.join(F.broadcast(cuts), "lang").where(order <= F.col("cut")).select("lang", "text", order.alias("o")).withColumn("rank", rank).where(F.col("rank") <= per_lang).collect()
        found = Counter(r["lang"] for r in near)
        short = {lang for lang, part in share.items() if found[lang] < per_lang and part < 1}  # ids repeated so often that the cut left too few
        rows += [r for r in near if r["lang"] not in short]
        share = {lang: 4 * share[lang] for lang in short}
    return [(r["lang"], r["text"]) for r in sorted(rows, key=lambda r: (r["o"], r["lang"]))]


class Labeller:
    """Scores words through a cache and decodes batches of texts."""

    def __init__(self, model: Model, switch: float = SWITCH):
        self.model, self.switch = model, switch
        self._index: dict[str, int] = {}
        self.words = Words()
        self._scores = np.zeros((1 << 12, max(1, len(model.langs))), np.float32)
        self._letters = np.zeros(1 << 12, np.int32)

    def _learn(self, pieces: list[str]):
        at = len(self._index)
        while at + len(pieces) > len(self._scores):
            self._scores, self._letters = np.concatenate([self._scores, np.zeros_like(self._scores)]), np.concatenate([self._letters, np.zeros_like(self._letters)])
        found = [letters(p) for p in pieces]
        spelled = [i for i, w in enumerate(found) if w]
        self._scores[at : at + len(pieces)] = 0
        self._letters[at : at + len(pieces)] = [len(w) for w in found]
        if spelled and self.model.langs:
            self._scores[at + np.array(spelled)] = self.model.score([found[i] for i in spelled])
        self._index.update(zip(pieces, range(at, at + len(pieces)), strict=True))

    def indices(self, text: str | None) -> np.ndarray:
        pieces, index = self.words(text), self._index
        fresh = list({p for p in pieces if p not in index})
        for at in range(0, len(fresh), 100_000):
            self._learn(fresh[at : at + 100_000])
        return np.fromiter(map(index.__getitem__, pieces), np.int32, len(pieces))

    def decode(self, texts: list[str | None]):
        """For each text: (labels of its words, letters of its words, summed word scores by language)."""
        out: list = [None] * len(texts)
        for some in self._runs(texts):
            lists = []
            for i in some:
                if len(self._index) > CACHE_WORDS:
                    self._flush(lists, out)
                    lists = []
                    self._index.clear()
                lists.append((i, self.indices(texts[i])))
            self._flush(lists, out)
        return out

    @staticmethod
    def _runs(texts, cells: int = 4_000_000):
        """Texts of like length together, a bounded number of characters at a time."""
        order = sorted(range(len(texts)), key=lambda i: len(texts[i] or ""))
        run: list[int] = []
        for i in order:
            if run and (len(run) + 1) * (len(texts[i] or "") + 1) > cells:
                yield run
                run = []
            run.append(i)
        if run:
            yield run

    def _flush(self, lists, out):
        lists.sort(key=lambda x: -len(x[1]))
        if not lists:
            return
        k, longest = len(self.model.langs), len(lists[0][1])
        if not k:
            for i, ix in lists:
                out[i] = np.zeros(len(ix), np.int32), self._letters[ix], np.zeros(0)
            return
        sizes = np.array([len(ix) for _, ix in lists])
        live = np.searchsorted(-sizes, -np.arange(longest), side="left")  # texts that still have a word there
        padded = np.zeros((longest, len(lists)), np.int32)
        for column, (_, ix) in enumerate(lists):
            padded[: len(ix), column] = ix
        best = np.zeros((len(lists), k), np.float32)
        # where each state came from: itself where its bit is set, else the best state before
        stayed = np.zeros((longest, len(lists), -(-k // 8)), np.uint8)
        tops = np.zeros((longest, len(lists)), np.int32)
        for t in range(longest):
            n = live[t]
            part = best[:n]
            top = part.argmax(1)
            jump = part[np.arange(n), top] - self.switch
            stay = part >= jump[:, None]
            stayed[t, :n], tops[t, :n] = np.packbits(stay, axis=1), top
            best[:n] = np.where(stay, part, jump[:, None]) + self._scores[padded[t, :n]]
        state = best.argmax(1) if k else np.zeros(len(lists), np.int64)
        labels = np.zeros((longest, len(lists)), np.int32)
        rows = np.arange(len(lists))
        for t in range(longest - 1, -1, -1) if k else ():
            n = live[t]
            now = labels[t, :n] = state[:n]
            held = stayed[t, rows[:n], now >> 3] >> (7 - (now & 7)) & 1
            state[:n] = np.where(held, now, tops[t, :n])
        for column, (i, ix) in enumerate(lists):
            weights = self._letters[ix]
            sums = (np.maximum(self._scores[ix], -20) * (weights[:, None] > 0)).sum(0) if len(ix) else np.zeros(k)
            out[i] = (labels[: len(ix), column], weights, sums)

    def languages(self, texts):
        """For each text: (language, score)."""
        for labels, weights, sums in self.decode(texts):
            held = np.bincount(labels, weights, max(1, len(self.model.langs))) if len(labels) else np.zeros(1)
            if not held.sum() or not self.model.langs:
                yield UNKNOWN, 0.0
                continue
            at = int(max(range(len(held)), key=lambda i: (held[i], sums[i])))
            rate = np.exp((sums - sums[at]) / math.sqrt(1 + np.count_nonzero(weights)))
            yield self.model.langs[at], float(held[at] / held.sum() * (1 / max(1.0, rate.sum())) ** 0.5)


def spans(labeller: Labeller, text: str | None):
    """(language, first word, words) of every run of equal labels; words are those of ``Words``."""
    return runs(labeller, labeller.decode([text])[0][0])


def runs(labeller: Labeller, labels: np.ndarray):
    """The same from the labels of a text's words."""
    cuts = [0, *(np.nonzero(np.diff(labels))[0] + 1).tolist(), len(labels)]
    return [(labeller.model.langs[labels[a]], a, b - a) for a, b in zip(cuts, cuts[1:], strict=False) if b > a]


def label(docs: DataFrame, model: Model, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, lang_pred, score) of every row; the model is sent to the executors once."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # bounded: TRAIN_DOCS texts a language

    def run(batches):
        labeller = Labeller(shared.value)
        for batch in portions(batches):
            found = list(labeller.languages(batch.column(1).to_pylist()))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([x for x, _ in found], pa.string()), pa.array([x for _, x in found], pa.float64())], ["doc_id", "lang_pred", "score"])

    return docs.select(F.col(key).cast("long"), text).mapInArrow(tidied(run), "doc_id long, lang_pred string, score double")


def label_spans(docs: DataFrame, model: Model, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, span, lang, first_word, n_words): the languages of every text in order; texts without words have no rows."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # bounded: TRAIN_DOCS texts a language

    def run(batches):
        labeller = Labeller(shared.value)
        for batch in portions(batches):
            texts = batch.column(1).to_pylist()  # decoded together: a step of Viterbi serves all texts that have a word there
            rows = [(i, n, *span) for i, (labels, _, _) in enumerate(labeller.decode(texts) if model_langs else ()) for n, span in enumerate(runs(labeller, labels))]
            ids = batch.column(0).take(pa.array([r[0] for r in rows], pa.int64()))
            yield pa.RecordBatch.from_arrays([ids, pa.array([r[1] for r in rows], pa.int64()), pa.array([r[2] for r in rows], pa.string()), pa.array([r[3] for r in rows], pa.int64()), pa.array([r[4] for r in rows], pa.int64())], ["doc_id", "span", "lang", "first_word", "n_words"])

    model_langs = bool(model.langs)
    return dealt(docs.select(F.col(key).cast("long").alias("id"), F.col(text).alias("text")), "id").mapInArrow(tidied(run), "doc_id long, span long, lang string, first_word long, n_words long")


def identify(docs: DataFrame) -> DataFrame:
    """Learns from the rows that are not held out and labels all."""
    out = label(docs, train(training_rows(docs)))
    held = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 2
    return out.select("doc_id", F.coalesce(held, F.lit(False)).alias("held_out"), "lang_pred", "score")


def accepted(docs: DataFrame, least: float = 0.01) -> DataFrame:
    """Documents with a known language and at least ``least`` score; columns as given."""
    shared = docs.sparkSession.sparkContext.broadcast(train(training_rows(docs)))
    names = docs.columns

    def run(batches):
        labeller = Labeller(shared.value)
        for batch in portions(batches):
            texts = batch.column(names.index("text")).to_pylist()
            yield batch.filter(pa.array([lang != UNKNOWN and score >= least for lang, score in labeller.languages(texts)], pa.bool_()))

    return docs.mapInArrow(tidied(run), docs.schema)
