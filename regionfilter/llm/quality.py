"""Quality classifier: Bradley-Terry pairwise ranking.

Every document gets some shape counts of its whole text and hashed shares of its byte trigrams and of its words (what
it says beside how it looks; they enter with a twentieth of the counts' scale, so that the counts decide where they can). A
preference pair is a labelled document of quality 1 and
one of quality 0; the probability that the first is preferred is the logistic function of the difference of
their scores, and scores are linear in the features, so learning is logistic regression on feature differences
without an intercept. The cut between good and bad is the quantile of the training scores at the share of
quality 0 among them, moved to the middle of the gap that it falls in; the published score is the logistic
function of (score - cut), so 0.5 is the cut.

Labelled training rows are a bounded sample (``max_labelled``, those with the smallest hashes of doc_id), pairs
are all of good and bad ones, or ``pairs`` draws among them where there are more, documented parameters; every document is scored from its whole text.

Defined results: null text is the empty text and has a score; repeated labels of a document count as often as
they come, a labelled doc_id of several texts trains with the least of them; null labels are left out; without both labels in the training rows every score is 0.5; an empty table
gives no rows; other columns (lang, source, labels) never enter a score.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import table, whole_text

FEATURES = ["log_words", "mean_word", "letters", "upper", "digits", "marks", "odd_marks", "pipes", "bangs", "distinct", "repeats", "top_word", "line_repeats", "long_words", "ends", "marked_words"]
#: buckets of byte trigrams and of words, and their scale beside the counts
GRAMS, WORDS, SOFT = 64, 64, 0.05
WIDTH = len(FEATURES) + GRAMS + WORDS
SENTENCE = re.compile(r"[.?!]")
ODD = re.compile(r"[^\w\s.,;:'\"()?!-]")
DIGIT = re.compile(r"\d")
UPPER = re.compile(r"[A-ZÀ-ÖØ-Þ]")
MARKED = re.compile(r"[^\w\s.,;:'\"()-]{2,}(?:\s|$)")


def _shares(counts: np.ndarray) -> np.ndarray:
    """Square roots of shares: rare buckets count, and long texts as much as short ones."""
    return np.sqrt(counts / max(1, counts.sum()))


def features(text: str) -> np.ndarray:
    """FEATURES, trigram shares and word shares of a whole text; shares lie in [0, 1]."""
    words = text.split()
    n, chars = len(words), max(1, len(text))
    if not n:
        return np.zeros(WIDTH)
    lengths = list(map(len, words))
    counts: dict[str, int] = {}
    for w in words:
        counts[w] = counts.get(w, 0) + 1
    lines = [x for x in text.split("\n") if x.strip()]
    letters = chars - len(ODD.findall(text)) - len(DIGIT.findall(text))
    odd = len(ODD.findall(text))
    raw = np.frombuffer(text.encode("utf-8", "surrogatepass"), dtype=np.uint8).astype(np.uint32)
    mixed = (raw[:-2] * np.uint32(0x9E3779B1) + raw[1:-1] * np.uint32(0x85EBCA6B) + raw[2:] * np.uint32(0xC2B2AE35)) >> np.uint32(26) if len(raw) > 2 else raw[:0]
    grams = np.bincount(mixed, minlength=GRAMS)
    said = np.bincount([crc32(w.encode("utf-8", "surrogatepass")) % WORDS for w in counts], weights=list(counts.values()), minlength=WORDS)
    shape = [
        np.log1p(n),
        min(1.0, sum(lengths) / n / 12),
        letters / chars,
        len(UPPER.findall(text)) / chars,
        len(DIGIT.findall(text)) / chars,
        min(1.0, len(SENTENCE.findall(text)) / n),
        min(1.0, 4 * odd / chars),
        min(1.0, text.count("|") / n),
        min(1.0, text.count("!!") / n),
        len(counts) / n,
        sum(a == b for a, b in zip(words, words[1:])) / n,
        max(counts.values()) / n,
        1 - len(set(lines)) / max(1, len(lines)),
        sum(x > 20 for x in lengths) / n,
        sum(w[-1] in ".!?" for w in words) / n,
        min(1.0, len(MARKED.findall(text)) / n),
    ]
    return np.concatenate([shape, _shares(grams), _shares(said)])


def _slices(batches: Iterator[pa.RecordBatch], rows: int = 500) -> Iterator[pa.RecordBatch]:
    """Some rows at a time, so that few whole texts are held as strings."""
    for b in batches:
        for at in range(0, b.num_rows, rows):
            yield b.slice(at, rows)


def feature_rows(docs: DataFrame) -> DataFrame:
    """(doc_id, x array<double>) of every document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in _slices(batches):
            x = [features(t).tolist() for t in b.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(x, pa.list_(pa.float64()))], ["doc_id", "x"])

    return docs.select("doc_id", whole_text().alias("text")).mapInArrow(run, "doc_id long, x array<double>")


def held_out() -> F.Column:
    return F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(3)) == 1


class Ranker:
    """weights . x - cut, on features scaled by the training rows."""

    def __init__(self, mean: np.ndarray, scale: np.ndarray, weights: np.ndarray, cut: float, slope: float = 1.0):
        self.mean, self.scale, self.weights, self.cut, self.slope = mean, scale, weights, cut, slope

    def raw(self, x: np.ndarray) -> np.ndarray:
        return np.clip((x - self.mean) / self.scale, -8, 8) @ self.weights

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.slope * (self.raw(x) - self.cut), -30, 30)))


def fit(x: np.ndarray, y: np.ndarray, pairs: int = 20_000, steps: int = 40, penalty: float = 1e-3, seed: int = 7) -> Ranker:
    """Bradley-Terry weights from pairs of a good and a bad row, and the cut at the quantile of the bad share."""
    width = x.shape[1] if x.ndim == 2 else WIDTH
    good, bad = np.flatnonzero(y == 1), np.flatnonzero(y == 0)
    if not len(good) or not len(bad):
        return Ranker(np.zeros(width), np.ones(width), np.zeros(width), 0.0)
    # both classes weigh alike in the scaling, or a rare bad kind would have no spread
    mean = (x[good].mean(axis=0) + x[bad].mean(axis=0)) / 2
    scale = np.sqrt((x[good].var(axis=0) + x[bad].var(axis=0)) / 2 + (x[good].mean(axis=0) - x[bad].mean(axis=0)) ** 2 / 4) + 1e-9
    scale[len(FEATURES) :] /= SOFT
    model = Ranker(mean, scale, np.zeros(width), 0.0)
    z = np.clip((x - mean) / scale, -8, 8)
    draw = np.random.default_rng(seed)
    if len(good) * len(bad) <= pairs:  # all pairs, where they are few
        first, second = np.repeat(good, len(bad)), np.tile(bad, len(good))
    else:
        first, second = draw.choice(good, pairs), draw.choice(bad, pairs)
    d = z[first] - z[second]
    pairs = len(d)
    w, loss = np.zeros(width), lambda w: np.logaddexp(0.0, -(d @ w)).mean() + penalty * (w @ w) / 2
    for _ in range(steps):  # Newton steps, halved where they would not help
        miss = 1 / (1 + np.exp(np.clip(d @ w, -30, 30)))
        g = d.T @ miss / pairs - penalty * w
        if np.abs(g).max() < 1e-6:
            break
        step = np.linalg.solve((d * (miss * (1 - miss))[:, None]).T @ d / pairs + penalty * np.eye(width), g)
        size, now = 1.0, loss(w)
        while size > 1e-3 and loss(w + size * step) > now:
            size /= 2
        w = w + size * step
    model.weights = w
    raw = np.sort(model.raw(x))
    at = int(np.clip(len(bad), 1, len(raw) - 1))
    model.cut = float((raw[at - 1] + raw[at]) / 2)
    return model


def training_labels(labels: DataFrame, max_labelled: int) -> DataFrame:
    """(doc_id, y) of the labelled rows that are not held out; those with the smallest hashes, max_labelled at most."""
    known = labels.where("quality in (0, 1) and doc_id is not null").where(~held_out())
    return known.select("doc_id", F.col("quality").cast("int").alias("y")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_labelled)


def trained(docs: DataFrame, labels: DataFrame, max_labelled: int = 20_000) -> Ranker:
    """The model of the training rows; at most max_labelled labels reach the driver or are broadcast."""
    known = training_labels(labels, max_labelled)
    some = docs.select("doc_id", whole_text().alias("text")).join(F.broadcast(known.select("doc_id").distinct()), "doc_id", "left_semi")
    some = some.groupBy("doc_id").agg(F.min("text").alias("text"))  # a doc_id that repeats trains with its least text, once
    got = feature_rows(some).join(F.broadcast(known), "doc_id").select("doc_id", "x", "y").toPandas().sort_values(["doc_id", "y"])
    x = np.array(got["x"].tolist(), dtype=float).reshape(len(got), WIDTH)
    return fit(x, got["y"].to_numpy())


def scored(docs: DataFrame, labels: DataFrame, max_labelled: int = 20_000) -> DataFrame:
    """(doc_id, held_out, score, predicted) for every row of docs."""
    model = trained(docs, labels, max_labelled)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in _slices(batches):
            x = np.array([features(t) for t in b.column("text").to_pylist()], dtype=float).reshape(-1, WIDTH)
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(model.score(x), pa.float64())], ["doc_id", "score"])

    out = docs.select(F.col("doc_id").cast("long"), whole_text().alias("text")).mapInArrow(run, "doc_id long, score double")
    return out.select("doc_id", F.coalesce(held_out(), F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def keep_good(docs: DataFrame, labels: DataFrame, max_labelled: int = 20_000) -> DataFrame:
    """The rows of docs that the classifier does not reject, with their columns as they are; no row is moved."""
    model = trained(docs, labels, max_labelled)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in _slices(batches):
            x = np.array([features(t or "") for t in b.column("text").to_pylist()], dtype=float).reshape(-1, WIDTH)
            yield b.filter(pa.array(model.score(x) >= 0.5, pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def op9_quality(spark, sf_dir: str) -> DataFrame:
    return scored(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
