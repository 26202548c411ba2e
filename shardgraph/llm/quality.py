"""Quality classifier: a weak-label model over heuristic labellers, and a hashed linear scorer trained on its posteriors."""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from itertools import groupby

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shardgraph.llm.common import own, packed, saved
from shardgraph.llm.words import WordTable, sampled

#: Documents that the linear scorer is trained on at most, hashed features, and the least score of a kept document.
SAMPLE, DIMS, KEEP = 6000, 1 << 12, 0.5
#: The labellers' measures and the bounds of their votes (good at or below the first, bad at or above the second).
LABELLERS = {
    "repeats": (0.06, 0.25), "capitals": (0.12, 0.4), "shouts": (0.06, 0.3), "symbol_tails": (0.04, 0.25),
    "lone_symbols": (0.05, 0.18), "sameness": (0.5, 0.75), "off_letters": (0.08, 0.16), "line_repeats": (0.3, 0.6),
}


def shape(word: str) -> str:
    """The word with runs of capitals, small letters and digits written as one A, a or 0, and repeats of other marks as one."""
    if word.isalpha():
        if word.islower():
            return "a"
        if word[0].isupper() and word[1:].islower():
            return "Aa"
    elif len(word) > 1 and word[:-1].isalpha() and not word[-1].isalnum():
        return shape(word[:-1]) + word[-1]
    return "".join(k for k, _ in groupby("A" if c.isupper() else "a" if c.isalpha() else "0" if c.isdigit() else c for c in word))


def describe(word: str) -> tuple:
    """(shape's hash, capitals, shout, symbol tail, lone symbol, letters, length) of a word."""
    n = len(word)
    code = zlib.crc32(shape(word).encode("utf-8", "surrogatepass")) % (DIMS - 64)
    if word.isalpha():
        return code, n > 1 and word.isupper(), False, False, False, n, n
    tail = n > 3 and word[-1] == word[-2] == word[-3] and not word[-1].isalnum()
    return code, n > 1 and word.isupper(), word.endswith("!!"), tail, not any(map(str.isalnum, word)), sum(map(str.isalpha, word)), n


_TABLE: list[WordTable] = []


def _read(text: str) -> tuple[np.ndarray, np.ndarray]:
    """(shape hashes, measures) of a text; a text without words has none of the first."""
    if not _TABLE:
        _TABLE.append(WordTable(7, describe))
    table, words = _TABLE[0], text.split()
    n = len(words)
    if not n:
        return np.zeros(0, np.int64), np.full(len(LABELLERS), np.nan)
    at = table.look_up(words)
    rows = table.rows[at]
    caps, shouts, tails, lone, letters, inked = rows[:, 1:].mean(0, dtype=np.float64)
    repeats = (at[1:] == at[:-1]).sum() / n
    sameness = 1 - len(set(words)) / n if n >= 50 else np.nan  # too few words to tell
    lines = text.split("\n")
    line_repeats = 1 - len(set(lines)) / len(lines) if len(lines) >= 4 else np.nan
    off = 1 - letters / inked
    return rows[:, 0].astype(np.int64), np.array([repeats, caps, shouts, tails, lone, sameness, off, line_repeats])


_BOUNDS = np.array(list(LABELLERS.values()))


def votes(measures: np.ndarray) -> np.ndarray:
    """Each labeller's vote: 1 good, 2 bad, 0 none."""
    with np.errstate(invalid="ignore"):
        return np.where(measures <= _BOUNDS[:, 0], 1, np.where(measures >= _BOUNDS[:, 1], 2, 0))


def pattern(measures: np.ndarray) -> int:
    """The votes as one number in base 3."""
    return int((votes(measures) * 3 ** np.arange(len(LABELLERS))).sum())


def fit_votes(patterns: np.ndarray, counts: np.ndarray, rounds: int = 200) -> tuple[np.ndarray, np.ndarray, float]:
    """(posterior of bad for each pattern, vote probabilities [class, labeller, vote], prior of bad).

    Expectation-maximisation of a model whose labellers vote independently given the class. It
    starts from the documents that any labeller calls bad; each count is smoothed by a half.
    """
    v = patterns[:, None] // 3 ** np.arange(len(LABELLERS)) % 3
    bad = (v == 2).any(1).astype(float)
    prob = prior = None
    for _ in range(rounds):
        prior = (counts @ bad + 0.5) / (counts.sum() + 1)
        prob = np.zeros((2, v.shape[1], 3))
        for k, share in enumerate((1 - bad, bad)):
            for x in range(3):
                prob[k, :, x] = (counts * share) @ (v == x) + 0.5
        prob /= prob.sum(2, keepdims=True)
        log = np.log([1 - prior, prior])[:, None] + np.take_along_axis(np.log(prob)[:, None, :, :].repeat(len(v), 1), v[None, :, :, None].repeat(2, 0), 3)[..., 0].sum(2)
        new = 1 / (1 + np.exp(np.clip(log[0] - log[1], -50, 50)))
        if np.abs(new - bad).max() < 1e-9:
            bad = new
            break
        bad = new
    return bad, prob, float(prior)


def features(shapes: np.ndarray, measures: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(places, values) of a document's hashed features: shape frequencies, and measures in eight steps."""
    some = np.flatnonzero(~np.isnan(measures))
    steps = DIMS - 64 + 8 * some[: len(some)] % 64 + np.minimum(7, (measures[some] * 8).astype(np.int64))
    if not len(shapes):
        return steps, np.ones(len(steps))
    count = np.bincount(shapes)
    at = np.flatnonzero(count)
    return np.concatenate([at, steps]), np.concatenate([count[at] / len(shapes), np.ones(len(steps))])


def fit_scorer(rows: list[tuple[np.ndarray, np.ndarray]], good: np.ndarray, rounds: int = 300, rate: float = 0.1, shrink: float = 1e-5) -> np.ndarray:
    """Weights (the last is the bias) of a logistic scorer for soft labels, by full-batch Adam."""
    w = np.zeros(DIMS + 1)
    if not rows:
        return w
    doc = np.repeat(np.arange(len(rows)), [len(a) for a, _ in rows])
    at, x = np.concatenate([a for a, _ in rows]), np.concatenate([v for _, v in rows])
    m, s = np.zeros_like(w), np.zeros_like(w)
    weight = np.where(good > 0.5, 0.5 / max(1e-9, good.mean()), 0.5 / max(1e-9, 1 - good.mean()))
    weight = np.minimum(weight, 20) / len(rows)
    for t in range(1, rounds + 1):
        p = 1 / (1 + np.exp(-np.clip(np.bincount(doc, w[at] * x, len(rows)) + w[-1], -40, 40)))
        e = (p - good) * weight
        g = np.append(np.bincount(at, e[doc] * x, DIMS), e.sum()) + shrink * w
        m, s = 0.9 * m + 0.1 * g, 0.99 * s + 0.01 * g * g
        w -= rate * m / (1 - 0.9**t) / (np.sqrt(s / (1 - 0.99**t)) + 1e-9)
    return w


def _logistic(z: float) -> float:
    return float(1 / (1 + np.exp(-np.clip(z, -40, 40))))


def score(text: str | None, w: np.ndarray) -> float:
    at, x = features(*_read(text or ""))
    return _logistic(w[at] @ x.astype(np.float32).astype(np.float64) + w[-1])


def read_features(docs: DataFrame) -> DataFrame:
    """(doc_id, p, at, x): each text's vote pattern and hashed features, written once: about a tenth of the text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for k in range(0, whole.num_rows, 500):
                b, ps, ats, xs = whole.slice(k, 500), [], [], []
                for t in b.column(1):
                    shapes, measures = _read(t.as_py() or "")
                    at, x = features(shapes, measures)
                    ps.append(pattern(measures))
                    ats.append(at.astype(np.int32))
                    xs.append(x.astype(np.float32))
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(ps, pa.int32()), pa.array(ats, pa.list_(pa.int32())), pa.array(xs, pa.list_(pa.float32()))], names=["doc_id", "p", "at", "x"])

    texts = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text")
    return saved(texts.mapInArrow(run, "doc_id long, p int, at array<int>, x array<float>"), "quality-features")


def fit(read: DataFrame, most: int = SAMPLE) -> np.ndarray:
    """The scorer's weights from read_features: votes of all documents count, the scorer learns from a bounded sample."""
    seen = read.groupBy("p").agg(F.count("*").alias("n")).collect()  # 3^8 patterns at most
    if not seen:
        return np.zeros(DIMS + 1)
    patterns, counts = np.array([r["p"] for r in seen]), np.array([float(r["n"]) for r in seen])
    bad = dict(zip(patterns.tolist(), fit_votes(patterns, counts)[0].tolist(), strict=True))
    chosen = read.join(F.broadcast(sampled(read.select("doc_id"), most)), "doc_id", "left_semi")
    one = chosen.groupBy("doc_id").agg(F.min(F.struct("p", "at", "x")).alias("f"))
    rows = one.orderBy("doc_id").select("f.*").collect()  # `most` at most
    return fit_scorer([(np.array(r["at"], np.int64), np.array(r["x"])) for r in rows], np.array([1 - bad[r["p"]] for r in rows]))


def classify(docs: DataFrame, keep: float = KEEP, most: int = SAMPLE) -> DataFrame:
    """docs plus _score (0 to 1, higher is better) and _keep; a column of docs that has such a name is replaced.

    No label is used. A null or empty text has no votes and is scored by the bias alone, which
    keeps it where most documents are good; null ids are scored but not learned from; repeated rows
    count as often as they come and are scored alike; an empty table gives no rows.
    """
    rated = _rated(docs, most)
    return rated.select(*own(docs, ("_score", "_keep")), F.col("_s").alias("_score"), (F.col("_s") >= keep).alias("_keep"))


def good(docs: DataFrame, keep: float = KEEP, most: int = SAMPLE) -> DataFrame:
    """The rows of docs that classify would keep, with their columns, whatever these are called."""
    return _rated(docs, most).where(F.col("_s") >= keep).select(*own(docs))


def _rated(docs: DataFrame, most: int) -> DataFrame:
    """(_d, _s): docs as one column, and scores."""
    w = fit(read_features(docs.select("doc_id", "text")), most)

    @F.pandas_udf("double")
    def rate(text: pd.Series) -> pd.Series:
        return pd.Series([score(t, w) for t in text], dtype="float64")

    return packed(docs).withColumn("_s", rate("_d.text"))


def query(spark, sf_dir: str) -> DataFrame:
    """Scores from the written features: each text is read once."""
    read = read_features(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
    w = fit(read)

    @F.pandas_udf("double")
    def rate(at: pd.Series, x: pd.Series) -> pd.Series:
        return pd.Series([_logistic(w[a] @ np.asarray(v, np.float64) + w[-1]) for a, v in zip(at, x, strict=True)], dtype="float64")

    return read.select("doc_id", rate("at", "x").alias("score")).withColumn("keep", F.col("score") >= KEEP)
