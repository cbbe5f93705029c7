"""Toxicity by compression distance.

Two zstandard dictionaries are trained, one on toxic and one on ordinary text.
A toxic document is mostly ordinary prose, so dictionaries of whole documents
differ by chance alone; each class's dictionary is therefore trained on the
windows around words whose rate in its documents is surely several times their
rate in the other class's. Both start with the same ordinary text, so that
windows of neither kind compress alike. A document's windows are compressed
with both, and what the toxic dictionary saves is compared with thresholds that
are calibrated on labelled rows of their own: how many windows pass what hardly
any ordinary window passes, and by how much the best ones do, become a
probability, for classes as frequent as in the sample.
"""

from __future__ import annotations

import math
from collections import Counter

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import crc_fold, labelled_sample
from .scoring import fit_logistic, predicted, score_texts, sigmoid

MODULUS, REMAINDER = 5, 0
PER_CLASS = 4000
MAX_CHARS = 32_000_000
WINDOW = 64
BASE_BYTES = 100_000
DICTIONARY_BYTES = 2048
LEAST_DOCUMENTS = 3
LEAST_SHARE = 0.01
#: How many times more frequent a telling word is, at the lower end of its rate's confidence interval.
RATE_RATIO = 8.0
CONFIDENCE = 2.0
#: Words on each side of a telling one that its training window takes along.
CONTEXT = 1
#: Shares of ordinary windows below the calibrated thresholds.
QUIET = (0.97, 0.99, 0.997, 0.999)
STRIP = b".,!?;:\"'()"


def windows(raw: bytes, size: int = WINDOW) -> list[bytes]:
    """The whole text in windows that end at blanks where one is near."""
    out, at = [], 0
    while at + size < len(raw):
        blank = raw.find(b" ", at + size, at + size + 32)
        stop = blank if blank > 0 else at + size
        out.append(raw[at:stop])
        at = stop
    out.append(raw[at:])
    return out


def _word(raw: bytes) -> bytes:
    return raw.strip(STRIP)


def _held(docs: list[bytes]) -> Counter:
    """In how many documents each word stands; one that always has the same neighbours, as in copies, counts once for them."""
    documents, contexts = Counter(), set()
    for d in docs:
        words = [_word(x) for x in d.split()]
        documents.update(set(words))
        contexts.update(zip([b"", *words], words, [*words[1:], b""]))
    places = Counter(w for _, w, _ in contexts)
    return Counter({w: min(k, places[w]) for w, k in documents.items()})


def telling_words(mine: list[bytes], other: list[bytes]) -> set[bytes]:
    """Words that a hundredth of the class's documents hold (three at least), surely RATE_RATIO times as often as the other class's."""
    least = max(LEAST_DOCUMENTS, math.ceil(LEAST_SHARE * len(mine)))
    held, there = _held(mine), _held(other)
    n = len(mine)
    out = set()
    for w, k in held.items():
        if w and k >= least:
            rate = k / n
            surely = rate - CONFIDENCE * math.sqrt(rate * (1 - rate) / n + 1 / n**2)
            if surely > RATE_RATIO * (there[w] + 1) / (len(other) + 2):
                out.add(w)
    return out


def telling_windows(mine: list[bytes], other: list[bytes]) -> list[bytes]:
    """The class's windows around its telling words."""
    wanted = telling_words(mine, other)
    out = []
    for d in mine:
        words = d.split()
        for i, w in enumerate(words):
            if _word(w) in wanted:
                out.append(b" " + b" ".join(words[max(0, i - CONTEXT) : i + 1 + CONTEXT]) + b" ")
    return out


def _dictionary(samples: list[bytes]) -> bytes:
    import zstandard

    try:
        return zstandard.train_dictionary(DICTIONARY_BYTES, samples, k=16, d=6).as_bytes()
    except zstandard.ZstdError:  # too little text to train on
        return b"".join(samples)[:DICTIONARY_BYTES]


class CompressionClassifier:
    """fit() once on the driver; the model is two dictionaries and a few numbers."""

    def __init__(self):
        self.toxic = self.ordinary = b""
        self.thresholds: list[float] = [math.inf] * len(QUIET)
        self.calibration: tuple | None = None
        self._pair = None

    def __getstate__(self):
        return {"toxic": self.toxic, "ordinary": self.ordinary, "thresholds": self.thresholds, "calibration": self.calibration, "_pair": None}

    def _compressors(self):
        if self._pair is None:
            import zstandard

            level = zstandard.ZstdCompressionParameters.from_level(3, write_content_size=0, write_checksum=0, write_dict_id=0)
            made = []
            for raw in (self.ordinary, self.toxic):
                d = zstandard.ZstdCompressionDict(raw, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
                d.precompute_compress(compression_params=level)
                made.append(zstandard.ZstdCompressor(dict_data=d, compression_params=level).compress)
            self._pair = made
        return self._pair

    def saved(self, text: str) -> np.ndarray:
        """Bytes that the toxic dictionary saves on each window."""
        by_ordinary, by_toxic = self._compressors()
        return np.array([len(by_ordinary(w)) - len(by_toxic(w)) for w in windows(text.lower().encode("utf-8", "replace"))], np.float64)

    def features(self, text: str) -> list[float]:
        saved = self.saved(text)
        best = np.sort(saved)[::-1]
        n = len(best)
        passed = [(saved > t).sum() for t in self.thresholds]
        return [saved.mean(), best[0], best[: max(1, n // 4)].mean(), best[: max(1, n // 10)].mean(), *[np.log1p(k) for k in passed], *[k / n for k in passed], (saved < -max(2.0, self.thresholds[0])).mean()]

    def fit(self, rows: list[tuple[int, str, int]]) -> CompressionClassifier:
        """Dictionaries from three quarters of the rows, thresholds and calibration from the rest."""
        raw = [(t.lower().encode("utf-8", "replace"), y) for i, (_, t, y) in enumerate(rows) if i % 4]
        toxic, ordinary = [r for r, y in raw if y], [r for r, y in raw if not y]
        held = [r for i, r in enumerate(rows) if i % 4 == 0]
        if not toxic or not ordinary or len({y for *_, y in held}) < 2:
            return self
        every = b"".join(windows(d, 400)[0] for d in ordinary)
        base = every[:BASE_BYTES]
        self.toxic = base + _dictionary(telling_windows(toxic, ordinary))
        self.ordinary = base + _dictionary(telling_windows(ordinary, toxic))
        quiet = np.concatenate([self.saved(t) for _, t, y in held if not y])
        self.thresholds = [float(np.quantile(quiet, share)) for share in QUIET]
        self.calibration = fit_logistic(np.array([self.features(t) for _, t, _ in held]), np.array([y for *_, y in held], float))
        return self

    def score(self, texts: list[str]) -> np.ndarray:
        if self.calibration is None:
            return np.full(len(texts), 0.5)
        mean, scale, w = self.calibration
        x = (np.array([self.features(t) for t in texts]) - mean) / scale
        return sigmoid(x @ w[:-1] + w[-1])


def fit_toxicity(docs: DataFrame, marks: DataFrame) -> CompressionClassifier:
    """Learns from a bounded sample (PER_CLASS rows of each class, MAX_CHARS in all) outside the held-out fold."""
    return CompressionClassifier().fit(labelled_sample(docs, marks, "toxic", MODULUS, REMAINDER, PER_CLASS, MAX_CHARS))


def score_toxicity(docs: DataFrame, marks: DataFrame) -> DataFrame:
    """One row per input row: doc_id, held_out, score, predicted.

    Whole texts are scored, from the text alone. A null text is empty and gets the
    score of a text that no dictionary shortens. Without labelled rows of both
    classes every score is 0.5. Repeated rows are scored alike. A null id is held
    out by no fold (held_out is null there). Empty tables give no rows.
    """
    model = docs.sparkSession.sparkContext.broadcast(fit_toxicity(docs, marks))
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    scored = score_texts(slim, lambda: model.value.score)
    return scored.select("doc_id", crc_fold(F.col("doc_id"), MODULUS, REMAINDER).alias("held_out"), "score", predicted().alias("predicted"))
