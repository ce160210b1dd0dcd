"""Toxicity by non-negative positive-unlabelled learning.

Confirmed toxic documents are positives; every other document, labelled or not, is unlabelled. A linear classifier over
word and word-beginning features is trained in numpy on the class-prior-corrected risk pi*R(p,+) + max(0, R(u,-) - pi*R(p,-)):
where the corrected negative part of a mini-batch falls below zero, the step goes against it, so the model can't drive it
down by fitting the positives hidden among the unlabelled. The prior is the share of toxic labels outside the held-out fold.

Texts are scored whole. Words are runs of letters and digits, lower-cased; a beginning is a word's first four to six characters.

Nulls: a null text is scored as an empty one, which has no feature; a null doc_id is never held out. Labels that are null
or belong to no document are ignored; of repeated labels of one document the highest counts. Repeated rows stay; extra
columns are ignored; without any confirmed toxic document, or any feature that tells these apart, every score is next to 0.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import materialise

WORD = re.compile(r"[^\W_]+")
POSITIVES, UNLABELLED = 3000, 6000  # documents that the classifier is fitted on, in expectation at most
FEATURES = 1000
BEGINNINGS = (4, 5, 6)
CACHE_WORDS = 400_000
SCHEMA = "doc_id long, held_out boolean, score double, predicted int"


def held_out(col: str = "doc_id", mod: int = 5, fold: int = 0):
    return F.coalesce(F.crc32(F.col(col).cast("string").cast("binary")) % mod == fold, F.lit(False))


def word_features(word: str) -> list[str]:
    return [word] + [word[:n] + "*" for n in BEGINNINGS if len(word) > n]


def doc_features(text: str) -> set[str]:
    return {f for w in set(WORD.findall(text.lower())) for f in word_features(w)}


class Model:
    def __init__(self, names: list[str], weights: np.ndarray, bias: float, prior: float):
        self.weights, self.bias, self.prior = weights, bias, prior
        self.names = names

    def scores(self, batches_of_texts: Iterator[list[str]]) -> Iterator[np.ndarray]:
        """Scores of each list of texts. What a word contributes is kept between texts, for a bounded number of words."""
        index = {n: i for i, n in enumerate(self.names)}
        cache: dict[str, tuple[int, ...]] = {}
        for texts in batches_of_texts:
            out = np.empty(len(texts))
            for k, text in enumerate(texts):
                words = set(WORD.findall(text.lower()))
                hits: set[int] = set()
                for w in words:
                    got = cache.get(w)
                    if got is None:
                        got = cache[w] = tuple(index[f] for f in word_features(w) if f in index)
                    if got:
                        hits.update(got)
                out[k] = self.bias + (self.weights[np.fromiter(hits, np.int64, len(hits))].sum() if hits else 0.0)
            if len(cache) > CACHE_WORDS:
                cache.clear()
            yield 1 / (1 + np.exp(-np.clip(out, -60, 60)))


def choose_features(sample: DataFrame, n_pos: int, n_unl: int, most: int = FEATURES) -> list[str]:
    """Features of at least three positives and a fiftieth of them, ranked by the significance of their excess over the unlabelled; counted on the executors."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = (Counter(), Counter())
            for text, toxic in zip(b.column("text").to_pylist(), b.column("toxic").to_pylist(), strict=True):
                found[toxic].update(doc_features(text))
            for toxic, c in enumerate(found):
                yield pa.RecordBatch.from_arrays([pa.array(list(c), pa.string()), pa.array([n * toxic for n in c.values()], pa.int64()), pa.array([n * (1 - toxic) for n in c.values()], pa.int64())], names=["feature", "p", "u"])

    counts = sample.select("text", "toxic").mapInArrow(count, "feature string, p long, u long").groupBy("feature").agg(F.sum("p").alias("p"), F.sum("u").alias("u")).where(F.col("p") >= max(3, n_pos // 50))
    both = (F.col("p") + F.col("u")) / float(n_pos + n_unl)
    z = F.abs(F.col("p") / float(n_pos) - F.col("u") / float(n_unl)) / F.sqrt(both * (1 - both) * (1 / n_pos + 1 / n_unl) + 1e-9)
    return [r["feature"] for r in counts.withColumn("z", z).where("z > 6").orderBy(F.desc("z"), "feature").limit(most).collect()]


def risk_step(xp: np.ndarray, xu: np.ndarray, w: np.ndarray, prior: float, beta: float = 0.0, gamma: float = 1.0) -> tuple[float, float, np.ndarray]:
    """Positive part and corrected negative part of the risk with the logistic loss, and the step's gradient: of their sum, or,
    where the negative part is below -beta, of gamma times its opposite."""
    sig = lambda z: 1 / (1 + np.exp(-np.clip(z, -60, 60)))
    soft = lambda z: np.logaddexp(0, z)
    w32 = w[:-1].astype(np.float32)
    zp, zu = xp @ w32 + w[-1], xu @ w32 + w[-1]
    positive, negative = prior * soft(-zp).mean(), soft(zu).mean() - prior * soft(zp).mean()
    gu, gp = (sig(zu) / len(xu)).astype(np.float32), (prior * sig(zp) / len(xp)).astype(np.float32)
    neg_w = np.append(xu.T @ gu - xp.T @ gp, gu.sum() - gp.sum())
    if negative < -beta:
        return positive, negative, -gamma * neg_w
    gq = (prior * (sig(zp) - 1) / len(xp)).astype(np.float32)
    return positive, negative, np.append(xp.T @ gq, gq.sum()) + neg_w


def nn_pu(x_pos: np.ndarray, x_unl: np.ndarray, prior: float, epochs: int = 150, batches: int = 8, rate: float = 0.02, l2: float = 1e-5, beta: float = 0.0, gamma: float = 1.0, seed: int = 7) -> tuple[np.ndarray, float]:
    """Adam on the non-negative risk with the logistic loss. beta, gamma: tolerance and step of the correction."""
    rng = np.random.default_rng(seed)
    w = np.zeros(x_pos.shape[1] + 1)
    m, v, step = np.zeros_like(w), np.zeros_like(w), 0
    for epoch in range(epochs):
        pi, ui = np.array_split(rng.permutation(len(x_pos)), batches), np.array_split(rng.permutation(len(x_unl)), batches)
        for a, b in zip(pi, ui, strict=True):
            if not len(a) or not len(b):
                continue
            grad = risk_step(x_pos[a], x_unl[b], w, prior, beta, gamma)[2]
            grad[:-1] += l2 * w[:-1]
            step += 1
            m, v = 0.9 * m + 0.1 * grad, 0.999 * v + 0.001 * grad**2
            w -= rate * (1 - epoch / epochs) * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
    return w[:-1], float(w[-1])


def fit(sample: DataFrame, prior: float) -> Model:
    """sample: text, toxic (1: confirmed, 0: unlabelled), of bounded size. Only feature places reach the driver."""
    sizes = {r["toxic"]: r["n"] for r in sample.groupBy("toxic").agg(F.count(F.lit(1)).alias("n")).collect()}
    if not sizes.get(1) or not sizes.get(0):
        return Model([], np.zeros(0), -60.0, prior)
    names = choose_features(sample, sizes[1], sizes[0])
    if not names:
        return Model([], np.zeros(0), -60.0, prior)

    def places(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = {n: i for i, n in enumerate(names)}
        for b in batches:
            found = [sorted(index[f] for f in doc_features(t) if f in index) for t in b.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("toxic"), pa.array(found, pa.list_(pa.int32()))], names=["doc_id", "toxic", "places"])

    rows = sample.select("doc_id", "toxic", "text").mapInArrow(places, "doc_id long, toxic int, places array<int>").toPandas()
    rows = rows.iloc[sorted(range(len(rows)), key=lambda i: (rows.doc_id[i], tuple(rows.places[i])))]

    def matrix(some) -> np.ndarray:
        x = np.zeros((len(some), len(names)), np.float32)
        for r, at in enumerate(some):
            x[r, at] = 1
        return x

    w, bias = nn_pu(matrix(rows.places[rows.toxic == 1]), matrix(rows.places[rows.toxic == 0]), prior)
    return Model(names, w, bias, prior)


def train(docs: DataFrame, labels: DataFrame, positives: int = POSITIVES, unlabelled: int = UNLABELLED) -> Model:
    """Sample confirmed toxic and other documents outside the held-out fold by the hash of their ids, and fit."""
    nothing = Model([], np.zeros(0), -60.0, 0.0)
    lab = labels.where(~held_out()).groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max(F.col("toxic").cast("int")).alias("toxic")).where("doc_id IS NOT NULL AND toxic IS NOT NULL")
    n, toxic = lab.agg(F.count(F.lit(1)), F.coalesce(F.sum("toxic"), F.lit(0))).first()
    total = docs.count()
    if not toxic or not total:
        return nothing
    u = F.pmod(F.xxhash64(F.col("doc_id").cast("string")), F.lit(1 << 20)) / float(1 << 20)
    p_share, u_share = min(1.0, positives / toxic), min(1.0, unlabelled / total)
    train_docs = docs.where(~held_out() & F.col("doc_id").isNotNull() & (u < max(p_share, u_share))).select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    ids = train_docs.select("doc_id").distinct().join(lab.where("toxic = 1"), "doc_id", "left").withColumn("u", u)
    ids = ids.where((F.col("toxic").isNotNull() & (F.col("u") < p_share)) | (F.col("toxic").isNull() & (F.col("u") < u_share))).select("doc_id", F.coalesce("toxic", F.lit(0)).alias("toxic"))
    sample = materialise(train_docs.join(F.broadcast(ids), "doc_id"), "toxic-sample")  # ids: positives + unlabelled at most, in expectation
    return fit(sample, toxic / n)


def score(docs: DataFrame, model: Model) -> DataFrame:
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = []

        def texts():
            for b in batches:
                held.append(b)
                yield [x or "" for x in b.column("text").to_pylist()]

        for s in shared.value.scores(texts()):
            b = held.pop()
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("held_out"), pa.array(s), pa.array((s >= 0.5).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), held_out().alias("held_out"), F.col("text").cast("string").alias("text")).mapInArrow(run, SCHEMA)


def clean(docs: DataFrame, model: Model) -> DataFrame:
    """The documents that aren't predicted toxic, with all their columns."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = []

        def texts():
            for b in batches:
                held.append(b)
                yield [x or "" for x in b.column(at).to_pylist()]

        for s in shared.value.scores(texts()):
            yield held.pop().filter(pa.array(s < 0.5))

    return docs.mapInArrow(run, docs.schema)
