"""Language identification by segmentation-marginalised unigrams.

A fixed public vocabulary of pieces is given. Each language has a probability for every piece; a word's probability is
the sum over all ways to segment it into pieces, by a forward pass over its characters; a text's score for a language is
the sum of its words' log probabilities plus the language's log prior. Piece probabilities are fitted by expectation
maximisation with the forward-backward sums over words of a bounded sample of labelled documents.

Words are the maximal runs of letters (Unicode category L; numbers such as a superscript two aren't letters), lower-cased. The model
is fitted on all words of a sample of documents whose size is a parameter (SAMPLE_DOCS a language). A text with no letter, an empty or a null text is `und` with score 0.
Languages that are null or not in the sample are never predicted. Repeated rows stay; extra columns are ignored; with no
labelled document every prediction is `und`. Texts of any length are scored whole; work a word costs is shared through a
bounded per-task cache, since the same word always gets the same scores.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

_RUN = re.compile(r"[^\W\d_]+")  # letters, and numbers that aren't decimal digits
SAMPLE_DOCS = 300  # labelled documents a language that the model is fitted on, in expectation at most
ROUNDS = 4
CACHE_WORDS = 500_000
MAX_PIECE = 16
SCHEMA = "doc_id long, held_out boolean, lang_pred string, score double"


def words_of(text: str | None) -> list[str]:
    """The maximal runs of letters, lower-cased."""
    found = _RUN.findall((text or "").lower())
    if text and not text.isascii() and not all(map(str.isalpha, found)):
        found = [w for x in found for w in (x if x.isalpha() else "".join(c if c.isalpha() else " " for c in x)).split()]
    return found


def public_pieces(path: str) -> list[str]:
    """Lower-cased pieces of a sentencepiece vocabulary; its word-start mark is kept as a space."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    found = {model.id_to_piece(i).lower().replace("▁", " ") for i in range(model.get_piece_size()) if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i))}
    return sorted(p for p in found if p.strip() and " " not in p[1:] and p[:1] + p[1:].strip() == p and len(p) <= MAX_PIECE and p.strip().isalpha())


class Lattice:
    """The segmentation lattices of distinct words: which piece, if any, covers each range of characters.

    A word gets a leading space. A single character outside the vocabulary is covered by an unknown piece, so that every
    word has a segmentation. Words are handled together by length, as arrays.
    """

    def __init__(self, pieces: list[str]):
        self.ids = {p[:k]: -1 for p in pieces for k in range(1, len(p))} | {p: i for i, p in enumerate(pieces)}  # -1: a beginning only
        self.longest = max(map(len, pieces), default=1)
        self.unknown = len(pieces)

    def of(self, words: list[str]) -> np.ndarray:
        """words of one length n -> piece ids [word, end 1..n, length 1..L], -1 where there is none."""
        n = len(words[0]) + 1
        L = min(n, self.longest)
        out = np.full((len(words), n + 1, L + 1), -1, np.int32)
        get = self.ids.get
        for w, word in enumerate(words):
            s = " " + word
            for start in range(n):
                for end in range(start + 1, min(start + L, n) + 1):
                    i = get(s[start:end])
                    if i is None:
                        break
                    if i >= 0:
                        out[w, end, end - start] = i
        single = out[:, 1:, 1]
        single[single < 0] = self.unknown
        return out


def forward(lattice: np.ndarray, logp: np.ndarray) -> np.ndarray:
    """Log of the summed probability of all segmentations of each prefix: [word, 0..n, language]."""
    W, n1, L1 = lattice.shape
    alpha = np.full((W, n1, logp.shape[1]), -np.inf, np.float64)
    alpha[:, 0] = 0
    for end in range(1, n1):
        terms = []
        for k in range(1, min(end, L1 - 1) + 1):
            ids = lattice[:, end, k]
            terms.append(np.where(ids[:, None] >= 0, alpha[:, end - k] + logp[ids], -np.inf))
        alpha[:, end] = np.logaddexp.reduce(np.stack(terms), axis=0)
    return alpha


def word_probability(lattice: np.ndarray, logp: np.ndarray) -> np.ndarray:
    """Log of forward's last column: [word, language]. Short words need no logarithms on the way."""
    W, n1, L1 = lattice.shape
    if n1 > 30:
        return forward(lattice, logp)[:, -1]
    p = np.append(np.exp(logp), np.zeros((1, logp.shape[1])), axis=0)  # the last row is for no piece
    alpha = np.zeros((n1, W, logp.shape[1]))
    alpha[0] = 1
    for end in range(1, n1):
        for k in range(1, min(end, L1 - 1) + 1):
            ids = lattice[:, end, k]
            if (ids >= 0).any():
                alpha[end] += alpha[end - k] * p[ids]
    return np.log(alpha[-1])


def expected(lattice: np.ndarray, logp: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """Expected uses of each piece over all segmentations, weighted by word counts: [piece, language]."""
    W, n1, L1 = lattice.shape
    alpha = forward(lattice, logp)
    beta = np.full_like(alpha, -np.inf)
    beta[:, n1 - 1] = 0
    for start in range(n1 - 2, -1, -1):
        terms = []
        for k in range(1, min(n1 - 1 - start, L1 - 1) + 1):
            ids = lattice[:, start + k, k]
            terms.append(np.where(ids[:, None] >= 0, beta[:, start + k] + logp[ids], -np.inf))
        beta[:, start] = np.logaddexp.reduce(np.stack(terms), axis=0)
    out = np.zeros_like(logp)
    total = alpha[:, n1 - 1]
    for end in range(1, n1):
        for k in range(1, min(end, L1 - 1) + 1):
            ids = lattice[:, end, k]
            on = ids >= 0
            if on.any():
                p = np.exp(alpha[on, end - k] + logp[ids[on]] + beta[on, end] - total[on]) * weight[on]
                for lang in range(logp.shape[1]):
                    out[:, lang] += np.bincount(ids[on], p[:, lang], minlength=len(out))
    return out


def by_length(words: list[str], block: int = 4000) -> Iterator[list[int]]:
    """Indices of words of equal length, in blocks of bounded size."""
    order = sorted(range(len(words)), key=lambda i: len(words[i]))
    start = 0
    while start < len(order):
        n, end = len(words[order[start]]), start
        size = max(1, min(block, 200_000 // (n + 1) // 17))
        while end < len(order) and end - start < size and len(words[order[end]]) == n:
            end += 1
        yield order[start:end]
        start = end


class Model:
    def __init__(self, pieces: list[str], langs: list[str], logp: np.ndarray, prior: np.ndarray):
        self.pieces, self.langs, self.logp, self.prior = pieces, langs, logp, prior
        self._lattice: Lattice | None = None

    def __getstate__(self):
        return {**self.__dict__, "_lattice": None}

    def word_scores(self, words: list[str]) -> np.ndarray:
        """Log probability of each word under each language."""
        self._lattice = self._lattice or Lattice(self.pieces)
        out = np.zeros((len(words), len(self.langs)))
        for block in by_length(words):
            out[block] = word_probability(self._lattice.of([words[i] for i in block]), self.logp)
        return out


def fit(counts: dict[str, Counter], docs_per_lang: dict[str, int], pieces: list[str], rounds: int = ROUNDS) -> Model:
    langs = sorted(counts)
    lattice = Lattice(pieces)
    words = sorted(set().union(*counts.values())) if counts else []
    weight = np.array([[counts[lang][w] for lang in langs] for w in words], np.float64).reshape(len(words), len(langs))
    start = np.array([1.0 + len(p) for p in pieces] + [1e-3])  # longer pieces are likelier at first, as in a code by length
    logp = np.repeat(np.log(start / start.sum())[:, None], len(langs), 1)
    for _ in range(rounds):
        uses = np.zeros_like(logp)
        for block in by_length(words):
            uses += expected(lattice.of([words[i] for i in block]), logp, weight[block])
        uses += 0.1
        uses[-1] += 0.9
        logp = np.log(uses / uses.sum(0))
    prior = np.array([docs_per_lang[x] for x in langs], np.float64)
    return Model(pieces, langs, logp, np.log(prior / max(prior.sum(), 1)))


def split(held_key: str = "doc_id", mod: int = 4, fold: int = 2):
    return F.coalesce(F.crc32(F.col(held_key).cast("string").cast("binary")) % mod == fold, F.lit(False))


def train(docs: DataFrame, pieces: list[str], sample_docs: int = SAMPLE_DOCS) -> Model:
    """Fit on the documents with the smallest hashes of each language, `sample_docs` in expectation at most, outside the held-out fold."""
    labelled = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & ~split())
    totals = {r["lang"]: r["n"] for r in labelled.groupBy(F.col("lang").cast("string").alias("lang")).agg(F.count(F.lit(1)).alias("n")).collect()}  # a row for each language
    if not totals:
        return fit({}, {}, pieces)
    shares = F.create_map(*[F.lit(x) for lang, n in sorted(totals.items()) for x in (lang, min(1.0, sample_docs / n))])
    # A share of a language's hashes: the sample's size is bounded in expectation and needs no sort of the corpus.
    draw = (F.pmod(F.xxhash64(F.col("doc_id").cast("string")), F.lit(1 << 20)) / float(1 << 20)) < shares[F.col("lang").cast("string")]
    sample = labelled.where(draw)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found: dict[str, Counter] = {}
        for b in batches:
            for text, lang in zip(b.column("text").to_pylist(), b.column("lang").to_pylist(), strict=True):
                found.setdefault(lang, Counter()).update(words_of(text))
        rows = [(lang, w, n) for lang, c in found.items() for w, n in c.items()]
        cols = list(zip(*rows, strict=True)) if rows else [[]] * 3
        yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.string()), pa.array(cols[1], pa.string()), pa.array(cols[2], pa.int64())], names=["lang", "word", "n"])

    words = sample.select(F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang")).mapInArrow(count, "lang string, word string, n long")
    counts: dict[str, Counter] = {lang: Counter() for lang in sorted(totals)}
    for lang, word, n in words.groupBy("lang", "word").agg(F.sum("n").alias("n")).toPandas().itertuples(index=False):  # the sample's distinct words
        counts[lang][word] = int(n)
    counts = {k: v for k, v in counts.items() if v}
    return fit(counts, {k: totals[k] for k in counts}, pieces)


def predict(docs: DataFrame, model: Model) -> DataFrame:
    """Score every whole text. The score is the posterior of the predicted language."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model, cache = shared.value, {}
        scores = np.empty((0, len(model.langs)))
        for b in batches:
            texts = [words_of(x) for x in b.column("text").to_pylist()]
            if len(cache) > CACHE_WORDS:
                cache, scores = {}, scores[:0]
            fresh = list(dict.fromkeys(w for ws in texts for w in ws if w not in cache)) if model.langs else []
            if fresh:
                cache.update(zip(fresh, range(len(cache), len(cache) + len(fresh)), strict=True))
                scores = np.concatenate([scores, model.word_scores(fresh)])
            pred, conf = [], []
            for ws in texts:
                if not ws or not model.langs:
                    pred.append("und")
                    conf.append(0.0)
                    continue
                total = scores[np.fromiter(map(cache.__getitem__, ws), np.int64, len(ws))].sum(0) + model.prior
                best = int(total.argmax())
                pred.append(model.langs[best])
                conf.append(float(1 / np.exp(total - total[best]).sum()))
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("held_out"), pa.array(pred, pa.string()), pa.array(conf, pa.float64())], names=["doc_id", "held_out", "lang_pred", "score"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), split().alias("held_out"), F.col("text").cast("string").alias("text")).mapInArrow(run, SCHEMA)
