"""What the two text classifiers share: numpy training helpers and the scoring pass."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import freed, prepare


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1.0 / (1.0 + np.exp(-np.clip(x, -60, 60)))


def fit_logistic(features: np.ndarray, labels: np.ndarray, ridge: float = 1e-2, steps: int = 40) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ridge logistic regression by Newton steps: (means, scales, weights with the intercept last)."""
    mean, scale = features.mean(axis=0), features.std(axis=0) + 1e-9
    x = np.hstack([(features - mean) / scale, np.ones((len(features), 1))])
    w = np.zeros(x.shape[1])
    penalty = np.full(x.shape[1], ridge * len(x))
    penalty[-1] = 1e-6
    for _ in range(steps):
        p = sigmoid(x @ w)
        gradient = x.T @ (p - labels) + penalty * w
        hessian = (x * (p * (1 - p) + 1e-9)[:, None]).T @ x + np.diag(penalty)
        move = np.linalg.solve(hessian, gradient)
        w -= move
        if np.abs(move).max() < 1e-8:
            break
    return mean, scale, w


def score_texts(docs: DataFrame, build: Callable[[], Callable[[list[str]], np.ndarray]], text_col: str = "text", score_col: str = "score") -> DataFrame:
    """docs with a score of each whole text added (a column of that name is replaced); build() makes the scorer in a worker."""
    prepare(docs.sparkSession)
    rows = docs.drop(score_col)
    names = rows.columns
    at = names.index(next(c for c in names if c.lower() == text_col.lower()))

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = build()
        for batch in batches:
            for begin in range(0, batch.num_rows, 1000):
                part = batch.slice(begin, 1000)
                scores = scorer([t or "" for t in part.column(at).to_pylist()])
                # rounded, so that a score does not depend on which rows were scored together
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(np.round(np.asarray(scores, np.float64), 9))], [*names, score_col])
        getattr(getattr(scorer, "__self__", None), "release", lambda: None)()

    from pyspark.sql.types import DoubleType, StructField, StructType

    return rows.mapInArrow(freed(run), StructType([*rows.schema.fields, StructField(score_col, DoubleType())]))


def predicted(score_col: str = "score"):
    return (F.col(score_col) >= 0.5).cast("int")
