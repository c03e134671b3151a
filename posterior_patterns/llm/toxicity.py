"""Toxicity: a linear classifier over byte n-grams scaled by naive Bayes log-count ratios.

Features are the distinct lower-cased n-grams (4, 5 and 6 UTF-8 bytes, a space before and after the text) of a
whole text.  For each, r = log of the smoothed share of toxic over clean training texts that hold it.  All
n-grams whose shares differ by the likelihood-ratio test at TEST are features, however many they are.  Logistic
regression runs on presence times r, and the product of its weights with r scores every text.

The fit uses a bounded sample of labelled ids: up to SAMPLE toxic and 2 x SAMPLE clean ones, taken in the order
of a hash of the id, with their whole texts.  Tasks count n-grams; the driver gets the features that pass, and for
each text of the sample the places of those it holds.  Scoring reads all rows whole.

Defined cases: null texts count as empty; an empty text scores what the intercept gives; labels that
repeat count once, a toxic one winning; of rows that share an id the least text is learned from; rows with a null
id are scored and never learned from, their held_out is null; without labels of both kinds every score is the
share of toxic ones (0 without any); repeated rows are scored alike; long texts are cut into pieces whose n-grams
overlap, so none is lost; an empty table gives an empty result; further columns are ignored, or kept by keep_clean.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.durable import Durable
from .text import arrow_map, blob, bound_batches

SAMPLE = 1000
LENGTHS = (4, 5, 6)
#: Upper point of chi-square with one degree of freedom at 0.0001.
TEST = 15.1367
REJECT = 0.7
#: Bytes of a text whose n-grams are made at once.
PIECE = 1 << 18
_BUCKET_BITS, _STEP = 22, np.uint64(0x9E3779B97F4A7C15)


def _pieces(data: bytes) -> Iterator[np.ndarray]:
    """Codes of all n-grams, piece by piece: the length, then the bytes."""
    whole = np.frombuffer((b" " + data + b" ").lower(), dtype=np.uint8)
    for start in range(0, len(whole), PIECE):
        b = whole[start : start + PIECE + max(LENGTHS) - 1].astype(np.uint64)
        made = []
        for n in LENGTHS:
            places = min(PIECE, len(b) - n + 1)
            if places > 0:
                code = np.full(places, np.uint64(n) << np.uint64(56), dtype=np.uint64)
                for k in range(n):
                    code |= b[k : k + places] << np.uint64(8 * k)
                made.append(code)
        if made:
            yield np.concatenate(made)


def ngrams(data: bytes) -> np.ndarray:
    """Sorted codes of the distinct n-grams of a text."""
    found = np.zeros(0, dtype=np.uint64)
    for codes in _pieces(data):
        found = np.union1d(found, codes)
    return found


def _bucket(codes: np.ndarray) -> np.ndarray:
    return ((codes * _STEP) >> np.uint64(64 - _BUCKET_BITS)).astype(np.int64)


def log_ratio(pos: np.ndarray, neg: np.ndarray, n_pos: int, n_neg: int) -> np.ndarray:
    return np.log((pos + 1.0) / (n_pos + 2.0)) - np.log((neg + 1.0) / (n_neg + 2.0))


def test_column(pos: Column, neg: Column, n_pos: int, n_neg: int) -> Column:
    """Likelihood-ratio statistic of presence against label."""
    n, held = n_pos + n_neg, pos + neg
    cells = ((pos, held * (n_pos / n)), (neg, held * (n_neg / n)), (F.lit(n_pos) - pos, (F.lit(n) - held) * (n_pos / n)), (F.lit(n_neg) - neg, (F.lit(n) - held) * (n_neg / n)))
    return sum((F.when(o > 0, 2 * o * F.log(o / e)).otherwise(0.0) for o, e in cells), F.lit(0.0))


@dataclass
class Model:
    codes: np.ndarray  # sorted
    weights: np.ndarray
    intercept: float
    seen: np.ndarray | None = field(default=None, repr=False)

    def __getstate__(self):
        return {"codes": self.codes, "weights": self.weights, "intercept": self.intercept, "seen": None}

    def held(self, data: bytes) -> np.ndarray:
        """Places of the features that a text holds."""
        if not len(self.codes):
            return np.zeros(0, dtype=np.int64)
        if self.seen is None:  # n-grams in an empty bucket need not be searched for
            self.seen = np.zeros(1 << _BUCKET_BITS, dtype=bool)
            self.seen[_bucket(self.codes)] = True
        made = []
        for codes in _pieces(data):
            near = np.unique(codes[self.seen[_bucket(codes)]])
            at = np.minimum(np.searchsorted(self.codes, near), len(self.codes) - 1)
            made.append(at[self.codes[at] == near])
        return np.unique(np.concatenate(made)) if len(made) > 1 else made[0] if made else np.zeros(0, dtype=np.int64)

    def score(self, data: bytes) -> float:
        total = self.intercept + float(self.weights[self.held(data)].sum())
        return float(1 / (1 + np.exp(-np.clip(total, -30, 30))))


def constant(n_pos: int, n_neg: int) -> Model:
    """Without texts of both kinds: the share of toxic ones."""
    share = min(max(n_pos / max(1, n_pos + n_neg), 1e-9), 1 - 1e-9)
    return Model(np.zeros(0, dtype=np.uint64), np.zeros(0), float(np.log(share / (1 - share))))


def logistic(rows: np.ndarray, cols: np.ndarray, scale: np.ndarray, label: np.ndarray, rounds: int = 300, l2: float = 1e-3) -> tuple[np.ndarray, float]:
    """Weights and intercept of a regularised logistic regression on a sparse matrix whose entry (row, col) is scale[col]."""
    n, value = len(label), scale[cols]
    times = lambda w: np.bincount(rows, value * w[cols], n)
    back = lambda g: np.bincount(cols, value * g[rows], len(scale))
    w, b = np.zeros(len(scale)), float(np.log(label.sum() / (n - label.sum())))
    probe, top = np.ones(len(scale)), 1.0
    for _ in range(12):  # largest curvature
        probe = back(times(probe)) / n
        top = float(np.linalg.norm(probe)) or 1.0
        probe /= top
    rate = 1 / (0.25 * (top + 1) + l2)
    v, vb, t = w.copy(), b, 1.0
    for _ in range(rounds):  # accelerated gradient
        g = 1 / (1 + np.exp(-np.clip(times(v) + vb, -30, 30))) - label
        nw, nb = v - rate * (back(g) / n + l2 * v), vb - rate * float(g.mean())
        nt = (1 + np.sqrt(1 + 4 * t * t)) / 2
        v, vb = nw + (t - 1) / nt * (nw - w), nb + (t - 1) / nt * (nb - b)
        w, b, t = nw, nb, nt
    return w, b


def train(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> Model:
    """Fit on labelled rows of docs; labels(doc_id, toxic) are the rows one may learn from."""
    spark, store = docs.sparkSession, Durable(docs.sparkSession, "toxicity")
    truth = labels.filter("doc_id is not null and toxic is not null").groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    order = F.xxhash64(F.lit(9), "doc_id")
    side = lambda y, n: truth.filter(F.col("toxic") == y).orderBy(order, "doc_id").limit(n)
    chosen = side(1, sample).unionByName(side(0, 2 * sample))
    texts = docs.select("doc_id", blob(F.col("text")).alias("data")).join(F.broadcast(chosen), "doc_id")  # bounded by the sample
    texts = store.save(texts.groupBy("doc_id", "toxic").agg(F.min("data").alias("data")), "sample")
    kinds = {r.toxic: r["count"] for r in texts.groupBy("toxic").count().collect()}  # two rows
    n_pos, n_neg = kinds.get(1, 0), kinds.get(0, 0)
    if not n_pos or not n_neg:
        return constant(n_pos, n_neg)
    spread = texts.repartition(spark.sparkContext.defaultParallelism * 2, "doc_id")
    held = arrow_map(spread.select("toxic", "data"), lambda toxic, data: (toxic, [ngrams(d).view(np.int64) for d in data]), "toxic int, codes array<long>")
    counted = held.select("toxic", F.explode("codes").alias("code")).groupBy("code").agg(F.sum("toxic").alias("pos"), F.count("*").alias("n"))
    pos, neg = F.col("pos").cast("double"), (F.col("n") - F.col("pos")).cast("double")
    passed = counted.filter(test_column(pos, neg, n_pos, n_neg) >= TEST).select("code", pos.alias("pos"), neg.alias("neg")).toArrow()
    codes = passed.column("code").to_numpy().view(np.uint64)
    place = np.argsort(codes)
    codes = codes[place]
    r = log_ratio(passed.column("pos").to_numpy()[place], passed.column("neg").to_numpy()[place], n_pos, n_neg)
    shared = spark.sparkContext.broadcast(Model(codes, r, 0.0))  # n-grams of the sample that pass the test
    got = arrow_map(spread, lambda ids, toxic, data: (toxic, [shared.value.held(d) for d in data]), "toxic int, places array<long>").toArrow()
    label = got.column("toxic").to_numpy().astype(float)
    places = [np.asarray(x, dtype=np.int64) for x in got.column("places").to_numpy()]
    rows, cols = np.repeat(np.arange(len(label)), list(map(len, places))), np.concatenate(places)
    w, b = logistic(rows, cols, r, label)
    return Model(codes, w * r, b)


def scorer(docs: DataFrame, model: Model, text: Column) -> Column:
    """The score of a text column."""
    bound_batches(docs)
    shared = docs.sparkSession.sparkContext.broadcast(model)  # n-grams of a bounded sample

    @F.pandas_udf("double")
    def score(data: pd.Series) -> pd.Series:
        return pd.Series([shared.value.score(bytes(d)) for d in data], dtype=float)

    return score(blob(text))


def learnable(labels: DataFrame) -> DataFrame:
    return labels.filter(F.crc32(F.col("doc_id").cast("string")) % 3 != 1)


def toxicity(docs: DataFrame, labels: DataFrame, threshold: float = REJECT) -> DataFrame:
    """(doc_id, held_out, score, predicted) for every row of docs."""
    model = train(docs, learnable(labels))
    scored = docs.select("doc_id", (F.crc32(F.col("doc_id").cast("string")) % 3 == 1).alias("held_out"), scorer(docs, model, F.col("text")).alias("score"))
    return scored.select("doc_id", "held_out", "score", F.when(F.col("score") >= threshold, 1).otherwise(0).alias("predicted"))


def keep_clean(docs: DataFrame, labels: DataFrame, threshold: float = REJECT) -> DataFrame:
    """docs without those that the classifier rejects; all columns stay."""
    model = train(docs, learnable(labels))
    return docs.filter(scorer(docs, model, F.col("text")) < threshold)
