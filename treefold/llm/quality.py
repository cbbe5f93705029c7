"""Quality classifier: random-indexing word vectors, pooled per document, and a two-layer network.

A word's index vector is a sparse ternary one drawn from the hashes of its
character trigrams, so that unseen words have one too; its context vector is
the sum of the index vectors of its neighbours in the training sample. A
document is the mean and the spread of its words' vectors. A two-layer numpy
network turns that into a logit, and a temperature fitted on rows kept out of
training makes it a calibrated probability.
"""

from __future__ import annotations

from collections import Counter

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import crc_fold, labelled_sample
from .scoring import predicted, score_texts, sigmoid

MODULUS, REMAINDER = 3, 1
PER_CLASS = 3000
MAX_CHARS = 24_000_000
DIMENSIONS = 32
NONZERO = 4
TRIGRAM_SLOTS = 1 << 14
WINDOW = 2
LEAST_COUNT = 3
MOST_WORDS = 50_000
HIDDEN = 32
CACHE_WORDS = 50_000


def _index_table(seed: int = 5) -> np.ndarray:
    rng = np.random.default_rng(seed)
    table = np.zeros((TRIGRAM_SLOTS, DIMENSIONS), np.float32)
    where = np.argsort(rng.random((TRIGRAM_SLOTS, DIMENSIONS)), axis=1)[:, :NONZERO]
    np.put_along_axis(table, where, rng.choice(np.array([-1, 1], np.float32), (TRIGRAM_SLOTS, NONZERO)), axis=1)
    return table


def index_vectors(words: list[bytes], table: np.ndarray) -> np.ndarray:
    """Unit sums of the trigram vectors of each word, ends marked by a blank."""
    if not words:
        return np.zeros((0, DIMENSIONS), np.float32)
    raw = np.frombuffer(b" " + b"  ".join(words) + b"  ", np.uint8).astype(np.uint32)
    code = (raw[:-2] * np.uint32(0x9E3779B1) ^ raw[1:-1] * np.uint32(0x85EBCA6B) ^ raw[2:] * np.uint32(0xC2B2AE35)) >> np.uint32(7)
    sizes = np.fromiter(map(len, words), np.int64, len(words))
    starts = np.concatenate(([0], np.cumsum(sizes + 2)[:-1]))
    # a word of n bytes has the n trigrams that start at its leading blank
    owner = np.repeat(np.arange(len(words)), sizes)
    inside = np.arange(len(owner)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
    slots = (code[starts[owner] + inside] % np.uint32(TRIGRAM_SLOTS)).astype(np.int64)
    sums = np.add.reduceat(table[slots], np.cumsum(sizes) - sizes, axis=0)
    return sums / (np.linalg.norm(sums, axis=1, keepdims=True) + 1e-6)


class QualityModel:
    def __init__(self):
        self.context: dict[bytes, int] = {}
        self.vectors = np.zeros((0, DIMENSIONS), np.float32)
        self.layers: tuple | None = None
        self.temperature = 1.0
        self._clear()

    def _clear(self):
        self._known: dict[bytes, int] = {}
        self._rows: np.ndarray | None = None
        self._used = 0
        self._table: np.ndarray | None = None

    def __getstate__(self):
        return {"context": self.context, "vectors": self.vectors, "layers": self.layers, "temperature": self.temperature}

    def __setstate__(self, state):
        self.__dict__.update(state)
        self._clear()

    def _table_(self) -> np.ndarray:
        if self._table is None:
            self._table = _index_table()
        return self._table

    def _learn(self, words: list[bytes]) -> None:
        if self._rows is None or self._used + len(words) > CACHE_WORDS:
            self._known, self._used = {}, 0
            if self._rows is None or len(words) > len(self._rows):
                self._rows = np.zeros((max(CACHE_WORDS, len(words)), 2 * DIMENSIONS), np.float32)
        block = self._rows[self._used : self._used + len(words)]
        block[:, :DIMENSIONS] = index_vectors(words, self._table_())
        block[:, DIMENSIONS:] = 0
        at = [(i, self.context[w]) for i, w in enumerate(words) if w in self.context]
        if at:
            i, j = np.array(at).T
            block[i, DIMENSIONS:] = self.vectors[j]
        self._known.update(zip(words, range(self._used, self._used + len(words))))
        self._used += len(words)

    def pooled(self, texts: list[str]) -> np.ndarray:
        """Mean and spread of the word vectors, and two lengths; zeros for a text without words."""
        out = np.zeros((len(texts), 4 * DIMENSIONS + 2), np.float32)
        for begin in range(0, len(texts), 200):
            split = [t.encode("utf-8", "replace").split() for t in texts[begin : begin + 200]]
            missing = list(set().union(*split).difference(self._known)) if split else []
            if missing and self._used + len(missing) > CACHE_WORDS:
                missing = list(set().union(*split))
            if missing:
                self._learn(missing)
            get = self._known.__getitem__
            for i, words in enumerate(split, begin):
                n = len(words)
                if not n:
                    continue
                ids, counts = np.unique(np.fromiter(map(get, words), np.int64, n), return_counts=True)
                v = self._rows[ids]
                share = (counts / n).astype(np.float32)
                mean = share @ v
                out[i, : 2 * DIMENSIONS] = mean
                out[i, 2 * DIMENSIONS : -2] = np.sqrt(np.maximum(share @ (v * v) - mean * mean, 0))
                out[i, -2] = np.linalg.norm(mean)
                out[i, -1] = np.log(n)
        return out

    def _learn_contexts(self, texts: list[str]) -> None:
        counted = Counter()
        for t in texts:
            counted.update(t.encode("utf-8", "replace").split())
        kept = [w for w, c in counted.most_common(MOST_WORDS) if c >= LEAST_COUNT]
        del counted
        self.context = {w: i for i, w in enumerate(kept)}
        sums = np.zeros((len(kept) + 1, DIMENSIONS), np.float32)
        for t in texts:  # split again: all words of the sample at once would take far more memory
            words = t.encode("utf-8", "replace").split()
            if len(words) < 2:
                continue
            own = list(dict.fromkeys(words))
            place = {w: i for i, w in enumerate(own)}
            at = np.fromiter(map(place.__getitem__, words), np.int64, len(words))
            index = index_vectors(own, self._table_())[at]
            rows = np.fromiter((self.context.get(w, len(kept)) for w in words), np.int64, len(words))
            for shift in range(1, WINDOW + 1):
                if len(words) > shift:
                    np.add.at(sums, rows[shift:], index[:-shift])
                    np.add.at(sums, rows[:-shift], index[shift:])
        self.vectors = sums[:-1] / (np.linalg.norm(sums[:-1], axis=1, keepdims=True) + 1e-6)

    def fit(self, rows: list[tuple[int, str, int]], epochs: int = 60, seed: int = 3) -> QualityModel:
        """A fifth of the rows is kept from training and sets the temperature."""
        train = [r for i, r in enumerate(rows) if i % 5]
        held = [r for i, r in enumerate(rows) if i % 5 == 0]
        if len({y for *_, y in train}) < 2 or len({y for *_, y in held}) < 2:
            return self
        self._learn_contexts([t for _, t, _ in train])
        x, y = self.pooled([t for _, t, _ in train]).astype(np.float64), np.array([v for *_, v in train], float)
        mean, scale = x.mean(axis=0), x.std(axis=0) + 1e-6
        x = (x - mean) / scale
        rng = np.random.default_rng(seed)
        p = [rng.normal(0, x.shape[1] ** -0.5, (x.shape[1], HIDDEN)), np.zeros(HIDDEN), rng.normal(0, HIDDEN**-0.5, HIDDEN), np.zeros(1)]
        m, v, step = [np.zeros_like(a) for a in p], [np.zeros_like(a) for a in p], 0
        for _ in range(epochs):
            order = rng.permutation(len(x))
            for at in range(0, len(x), 128):
                b = order[at : at + 128]
                h = np.tanh(x[b] @ p[0] + p[1])
                d = (sigmoid(h @ p[2] + p[3][0]) - y[b]) / len(b)
                back = d[:, None] * p[2][None, :] * (1 - h * h)
                grads = [x[b].T @ back + 1e-3 * p[0], back.sum(axis=0), h.T @ d + 1e-3 * p[2], np.array([d.sum()])]
                step += 1
                for k, g in enumerate(grads):
                    m[k] = 0.9 * m[k] + 0.1 * g
                    v[k] = 0.999 * v[k] + 0.001 * g * g
                    p[k] = p[k] - 3e-3 * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.999**step)) + 1e-8)
        self.layers = (mean, scale, *p)
        del x
        logits, truth = self.logits([t for _, t, _ in held]), np.array([v for *_, v in held], float)
        grid = np.geomspace(0.25, 8, 60)
        losses = [np.mean(np.logaddexp(0, -np.where(truth > 0, logits, -logits) / t)) for t in grid]
        self.temperature = float(grid[int(np.argmin(losses))])
        return self

    def logits(self, texts: list[str]) -> np.ndarray:
        mean, scale, w1, b1, w2, b2 = self.layers
        return np.tanh(((self.pooled(texts) - mean) / scale) @ w1 + b1) @ w2 + b2[0]

    def release(self) -> None:
        """Frees the word cache, which a reused worker would otherwise keep."""
        self._clear()

    def score(self, texts: list[str]) -> np.ndarray:
        if self.layers is None:
            return np.full(len(texts), 0.5)
        return sigmoid(self.logits(texts) / self.temperature)


def fit_quality(docs: DataFrame, marks: DataFrame) -> QualityModel:
    """Word vectors, network and temperature from a bounded sample (PER_CLASS rows of each class, MAX_CHARS in all) outside the held-out fold."""
    return QualityModel().fit(labelled_sample(docs, marks, "quality", MODULUS, REMAINDER, PER_CLASS, MAX_CHARS))


def with_quality(docs: DataFrame, marks: DataFrame, score_col: str = "score") -> DataFrame:
    """docs with the score of each whole text added."""
    model = docs.sparkSession.sparkContext.broadcast(fit_quality(docs, marks))
    return score_texts(docs, lambda: model.value.score, score_col=score_col)


def score_quality(docs: DataFrame, marks: DataFrame) -> DataFrame:
    """One row per input row: doc_id, held_out, score, predicted.

    Whole texts are scored, from the text alone. A null text is empty: no words,
    the vector of zeros. Without labelled rows of both classes every score is 0.5.
    Repeated rows are scored alike; held_out is null for a null id. Empty tables
    give no rows.
    """
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    scored = with_quality(slim, marks)
    return scored.select("doc_id", crc_fold(F.col("doc_id"), MODULUS, REMAINDER).alias("held_out"), "score", predicted().alias("predicted"))
