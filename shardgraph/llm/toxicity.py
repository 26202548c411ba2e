"""Toxicity: gradient-boosted trees over dense features of whole texts, calibrated by isotonic regression."""

from __future__ import annotations

import heapq
import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shardgraph.llm.words import WordTable, part_of, sampled

#: Labelled documents that lexicon, trees and calibration are fitted on at most; words of the lexicon; share kept for calibration.
SAMPLE, LEXICON, CALIBRATION = 10_000, 2000, 0.3
#: A lexicon key is in so many toxic documents at least, and so many times likelier there than elsewhere; hints need less.
LEAST_DOCS, LEAST_ODDS, HINT_ODDS = 4, 30.0, 4.0
#: What a document still counts for with each key it has, and the documents a key must count for.
FADE, LEAST_GAIN = 0.7, 1.0
#: Words that address the reader, in the languages of the corpus.
SECOND_PERSON = frozenset("you your yours yourself u ur tu te ti tus tuyo usted ustedes vosotros du dich dir dein deine deiner euch ihr euer toi vous votre vos ton ta tes".split())
#: Characters that stand for letters in disguised words.
DISGUISES = str.maketrans("013457@$!|", "oieastasil")
_LETTERS = re.compile(r"[^\W\d_]+")
FEATURES = ("log_words", "hints", "hint_density", "hits", "hit_density", "distinct_hits", "strongest", "sum", "second_person", "near_second_person", "capitals", "exclamations", "questions", "disguised", "disguised_hits", "digits", "marks", "word_length", "repeats", "longest_gap")


def keys(word: str) -> list[str]:
    """What a word is looked up by: itself in letters, and its starts of 4 to 8 letters, which catch compounds."""
    w = "".join(_LETTERS.findall(word.lower()))
    return [w, *(f"{w[:k]}*" for k in range(4, min(9, len(w))))] if len(w) >= 3 else []


def text_keys(text: str) -> set[str]:
    return {k for w in set(text.split()) for k in keys(w)}


def disguised(word: str) -> bool:
    """Whether marks or digits stand between letters."""
    inner = word.strip(".,;:!?\"'()[]{}-…")
    return len(inner) > 2 and any(map(str.isalpha, inner)) and any(c in "013457@$!|*#" for c in inner)


class Reader:
    """Texts to features, given a lexicon of key weights."""

    def __init__(self, lexicon: dict[str, float]):
        self.lexicon = lexicon
        self.table = WordTable(10, self.describe)

    def weight(self, word: str) -> float:
        return max((self.lexicon.get(k, 0.0) for k in keys(word)), default=0.0)

    def describe(self, word: str) -> tuple:
        low, hidden = word.lower().strip(".,;:!?\"'()"), disguised(word)
        plain = self.weight(word)
        found = max(plain, self.weight(word.translate(DISGUISES)), self.weight(re.sub(r"[^\w]|_", "", word))) if hidden else plain
        return found, hidden and found > 0, low in SECOND_PERSON, len(word) > 1 and word.isupper(), word.count("!"), word.count("?"), hidden, sum(map(str.isdigit, word)), sum(not c.isalnum() for c in word), len(word)

    def features(self, text: str) -> np.ndarray:
        words = text.split()
        n = len(words)
        if not n:
            return np.zeros(len(FEATURES))
        at = self.table.look_up(words)
        rows = self.table.rows[at]
        total = rows.sum(0, dtype=np.float64)
        hint = rows[:, 0] > 0
        hit = np.flatnonzero(rows[:, 0] >= np.log(LEAST_ODDS))
        you = np.flatnonzero(rows[:, 2] > 0)
        near = 0.0
        if len(hit) and len(you):
            k = np.searchsorted(you, hit)
            gap = np.minimum(np.abs(hit - you[np.minimum(k, len(you) - 1)]), np.abs(hit - you[np.maximum(k - 1, 0)]))
            near = float(np.exp(-gap / 5.0).sum())
        longest = float(np.diff(hit).max()) / n if len(hit) > 1 else 0.0
        return np.array([np.log1p(n), hint.sum(), hint.mean(), len(hit), len(hit) / n, len(set(at[hit].tolist())), rows[:, 0].max(), total[0], total[2] / n, near, total[3] / n, total[4] / n, total[5] / n, total[6] / n, total[1], total[7] / n, total[8] / n, total[9] / n, (at[1:] == at[:-1]).mean() if n > 1 else 0.0, longest])


def choose_lexicon(docs: list[tuple[str, int]], most: int = LEXICON) -> dict[str, float]:
    """Keys that tell toxic documents, with log-odds weights: pure ones first, then hints.

    The key is taken next that most toxic documents have, a document counting less with each key
    it already has (so words that merely stand in copies of one toxic text soon stay out).
    """
    n_bad = sum(t for _, t in docs) or 1
    n_good = len(docs) - n_bad or 1
    bad: dict[str, list[int]] = {}
    for k, (text, toxic) in enumerate(docs):
        if toxic:
            for key in text_keys(text):
                bad.setdefault(key, []).append(k)
    bad = {key: at for key, at in bad.items() if len(at) >= LEAST_DOCS}
    good = dict.fromkeys(bad, 0)
    for text, toxic in docs:
        if not toxic:
            for key in text_keys(text) & good.keys():
                good[key] += 1
    odds = {k: (len(at) / n_bad) / ((good[k] + 0.5) / n_good) for k, at in bad.items()}
    lexicon: dict[str, float] = {}
    worth = np.ones(len(docs))
    for low, high in ((LEAST_ODDS, np.inf), (HINT_ODDS, LEAST_ODDS)):
        # gains only fall, so the top of the heap is right once it has been worked out anew
        heap = [(-worth[at].sum(), -len(k), k) for k, at in bad.items() if low <= odds[k] < high]
        heapq.heapify(heap)
        while heap and len(lexicon) < most and -heap[0][0] >= LEAST_GAIN:
            _, length, key = heapq.heappop(heap)
            gain = -worth[bad[key]].sum()
            if heap and gain > heap[0][0]:
                heapq.heappush(heap, (gain, length, key))
            elif -gain >= LEAST_GAIN:
                lexicon[key] = float(np.log(odds[key]))
                worth[bad[key]] *= FADE
    return lexicon


class Trees:
    """Boosted regression trees of a fixed depth for the logistic loss, over quantile bins."""

    def __init__(self, trees: int = 60, depth: int = 3, rate: float = 0.2, bins: int = 32, shrink: float = 1.0):
        self.trees, self.depth, self.rate, self.bins, self.shrink = trees, depth, rate, bins, shrink

    def fit(self, x: np.ndarray, y: np.ndarray) -> Trees:
        self.edges = [np.unique(np.quantile(c, np.linspace(0, 1, self.bins + 1)[1:-1])) for c in x.T]
        b = np.stack([np.searchsorted(e, c, "left") for e, c in zip(self.edges, x.T, strict=True)], 1)
        p = np.clip(y.mean(), 1e-3, 1 - 1e-3)
        self.base, self.model = float(np.log(p / (1 - p))), []
        f = np.full(len(y), self.base)
        for _ in range(self.trees):
            p = 1 / (1 + np.exp(-f))
            g, h = p - y, p * (1 - p)
            node, splits = np.zeros(len(y), np.int64), []
            for level in range(self.depth):
                width = 1 << level
                best = np.full(width, 1e-6), np.zeros(width, np.int64), np.full(width, self.bins + 1)  # without gain all go left
                for k in range(x.shape[1]):
                    cell = node * (self.bins + 1) + b[:, k]
                    gs, hs = (np.bincount(cell, v, width * (self.bins + 1)).reshape(width, -1).cumsum(1) for v in (g, h))
                    gt, ht = gs[:, -1:], hs[:, -1:]
                    gain = gs**2 / (hs + self.shrink) + (gt - gs) ** 2 / (ht - hs + self.shrink) - gt**2 / (ht + self.shrink)
                    at = gain.argmax(1)
                    top = gain[np.arange(width), at]
                    better = top > best[0]
                    best[0][better], best[1][better], best[2][better] = top[better], k, at[better]
                splits.append((best[1], best[2]))
                node = 2 * node + (b[np.arange(len(y)), best[1][node]] > best[2][node])
            gs, hs = np.bincount(node, g, 1 << self.depth), np.bincount(node, h, 1 << self.depth)
            leaf = -self.rate * gs / (hs + self.shrink)
            self.model.append((splits, leaf))
            f += leaf[node]
        return self

    def margin(self, x: np.ndarray) -> np.ndarray:
        b = np.stack([np.searchsorted(e, c, "left") for e, c in zip(self.edges, x.T, strict=True)], 1)
        f, rows = np.full(len(x), self.base), np.arange(len(x))
        for splits, leaf in self.model:
            node = np.zeros(len(x), np.int64)
            for feature, cut in splits:
                node = 2 * node + (b[rows, feature[node]] > cut[node])
            f += leaf[node]
        return f


def isotonic(margin: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(margins, probabilities), rising: pool adjacent violators; interpolate between the blocks' means."""
    order = np.argsort(margin, kind="stable")
    blocks: list[list[float]] = []  # sum of labels, count, sum of margins
    for m, t in zip(margin[order].tolist(), y[order].tolist(), strict=True):
        blocks.append([t, 1.0, m])
        while len(blocks) > 1 and blocks[-2][0] * blocks[-1][1] >= blocks[-1][0] * blocks[-2][1]:
            t2, n2, m2 = blocks.pop()
            blocks[-1] = [blocks[-1][0] + t2, blocks[-1][1] + n2, blocks[-1][2] + m2]
    a = np.array(blocks)
    return a[:, 2] / a[:, 1], a[:, 0] / a[:, 1]


class Model:
    """A lexicon, trees and a calibration; scores are probabilities of label 1."""

    def __init__(self, docs: list[tuple[str, int]]):
        toxic = np.array([t for _, t in docs], float)
        kept = np.arange(len(docs)) % 10 >= 10 * CALIBRATION
        self.lexicon = choose_lexicon([d for d, k in zip(docs, kept, strict=True) if k])
        self.reader = None
        self.trees = None
        if 0 < toxic.sum() < len(docs):
            reader = Reader(self.lexicon)
            x = np.stack([reader.features(t) for t, _ in docs])
            own = kept if 0 < toxic[~kept].sum() < (~kept).sum() else np.ones(len(docs), bool)
            self.trees = Trees().fit(x[own], toxic[own])
            other = ~own if (~own).any() else own
            self.knots, self.share = isotonic(self.trees.margin(x[other]), toxic[other])
        else:
            self.constant = float(toxic.mean()) if len(docs) else 0.0

    def scores(self, texts) -> np.ndarray:
        if self.trees is None:
            return np.full(len(texts), self.constant)
        self.reader = self.reader or Reader(self.lexicon)
        if not len(texts):
            return np.zeros(0)
        m = self.trees.margin(np.stack([self.reader.features(t or "") for t in texts]))
        return 0.998 * np.interp(m, self.knots, self.share) + 0.002 / (1 + np.exp(-m))  # the second part orders ties

    def __getstate__(self):
        return self.__dict__ | {"reader": None}


def training_rows(docs: DataFrame, labels: DataFrame, most: int = SAMPLE) -> list[tuple[str, int]]:
    """(text, toxic) of up to `most` labelled documents of the training folds, a sample by hash; one a doc_id."""
    known = labels.where("doc_id is not null and toxic in (0, 1)").where(part_of(F.col("doc_id"), 3) != 1)
    known = known.join(F.broadcast(sampled(known, most)), "doc_id", "left_semi").groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    met = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(known), "doc_id")
    return [(r["text"], r["toxic"]) for r in met.groupBy("doc_id").agg(F.min("text").alias("text"), F.first("toxic").alias("toxic")).orderBy("doc_id").toLocalIterator()]


def classify(docs: DataFrame, model: Model, threshold: float = 0.7) -> DataFrame:
    """doc_id, held_out, score, predicted for each row of docs.

    A null or empty text is scored by its features, all zero. held_out follows the id alone: false
    for a null one. Repeated rows are scored alike; an empty table gives no rows; other columns, a
    label among them, are not read.
    """

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            s = model.scores(b["text"].tolist())
            yield pd.DataFrame({"doc_id": b["doc_id"], "held_out": b["held_out"], "score": s, "predicted": (s >= threshold).astype(np.int32)})

    own = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), (part_of(F.col("doc_id"), 3) == 1).alias("held_out"), "text")
    return own.mapInPandas(run, "doc_id long, held_out boolean, score double, predicted int")


def query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", "toxic")
    return classify(docs, Model(training_rows(docs, labels)))
