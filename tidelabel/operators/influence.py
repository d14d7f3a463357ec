"""Influence of rows on the validation loss, and the choice of rows to clean.

With s = V x, p = softmax(W x) and a row's weak label y, cleaning the row to class c
(label to the class's one-hot, weight from gamma to 1) changes N times the validation
loss by about  y.s - s_c + (1 - gamma) (p - y).s . The smallest class score of a row is
its rank and names the suggested label. All scores are one pass without a shuffle.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Row
from pyspark.sql import functions as F

from tidelabel.operators.core import ClusterRows, LocalRows, softmax
from tidelabel.schema import SCORES


def uplift_scores(x, y, w, v, gamma: float) -> np.ndarray:
    p, s = softmax(x @ w.T), x @ v.T
    ys = (y * s).sum(axis=1, keepdims=True)
    return ys - s + (1 - gamma) * ((p * s).sum(axis=1, keepdims=True) - ys)


def reweight_scores(x, y, w, v, gamma: float) -> np.ndarray:
    p, s = softmax(x @ w.T), x @ v.T
    return (1 - gamma) * ((p - y) * s).sum(axis=1)


def deletion_scores(x, y, w, v, gamma: float = 1.0, convention: str = "printed") -> np.ndarray:
    """(p - y).s as printed, which is the effect of a larger weight; ``effect`` is that of leaving the row out."""
    p, s = softmax(x @ w.T), x @ v.T
    r = ((p - y) * s).sum(axis=1)
    return r if convention == "printed" else -gamma * r


def feature_scores(x, y, w, v) -> np.ndarray:
    """Change of the score by a nudge of the features: V'r + W'A_p s, one vector a row."""
    p, s = softmax(x @ w.T), x @ v.T
    return (p - y) @ v + (p * (s - (p * s).sum(axis=1, keepdims=True))) @ w


def label_gradient_scores(x, w, v) -> np.ndarray:
    """p.s - s_j for each class j: the earlier score that knows no label change and no weight."""
    p, s = softmax(x @ w.T), x @ v.T
    return (p * s).sum(axis=1, keepdims=True) - s


@dataclass
class LocalScores:
    """Scores of rows that the driver holds."""

    ids: np.ndarray
    scores: np.ndarray

    def top(self, b: int) -> list[Row]:
        best = self.scores.argmin(axis=1)
        score = self.scores[np.arange(len(best)), best]
        return [Row(row_id=int(self.ids[i]), best_class=int(best[i]), best_score=float(score[i])) for i in np.lexsort((self.ids, score))[:b]]


def smallest(order: np.ndarray, ids: np.ndarray, b: int) -> np.ndarray:
    """Places of the b smallest, ties by id; NaN comes last, as in Spark."""
    at = np.arange(len(order))
    if len(order) > b:
        at = np.flatnonzero(~(order > np.partition(order, b - 1)[b - 1]))
    return at[np.lexsort((ids[at], order[at]))[:b]]


def score_batch(ids: np.ndarray, s: np.ndarray, b: int | None = None) -> pa.RecordBatch:
    """SCORES from class scores [n, classes]; with ``b`` of the b best rows alone."""
    best = s.argmin(axis=1)
    score = s[np.arange(len(s)), best]
    if b is not None:
        at = smallest(score, ids, b)
        ids, s, best, score = ids[at], s[at], best[at], score[at]
    offsets = pa.array(np.arange(len(s) + 1, dtype=np.int32) * s.shape[1])
    return pa.RecordBatch.from_arrays([pa.array(ids), pa.array(best.astype(np.int32)), pa.array(score), pa.ListArray.from_arrays(offsets, pa.array(s.ravel()))], names=["row_id", "best_class", "best_score", "scores"])


def scored(rows: DataFrame | LocalRows | ClusterRows, fn: Callable[[np.ndarray, np.ndarray], np.ndarray], b: int | None = None) -> DataFrame | LocalScores:
    """SCORES of (row_id, x, weak) rows; ``fn`` gives [n, classes], or [n] for scores without a class.

    With ``b`` a batch gives only its b best, all that ``select_top`` may need of it.
    """
    if isinstance(rows, LocalRows):
        return LocalScores(rows.ids, np.asarray(fn(rows.x, rows.y)).reshape(rows.size, -1) if rows.size else np.empty((0, 1)))

    def of(ids, x, y):
        return score_batch(ids, np.asarray(fn(x, y)).reshape(len(ids), -1), b)

    if isinstance(rows, ClusterRows):
        return rows.over(lambda part: of(part.ids, part.x, part.y), SCORES)

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                yield of(batch.column(0).to_numpy(), *(batch.column(i).flatten().to_numpy().reshape(batch.num_rows, -1) for i in (1, 2)))

    return rows.select("row_id", "x", "weak").mapInArrow(run, SCORES)


def pool(train: DataFrame | LocalRows | ClusterRows) -> DataFrame | LocalRows | ClusterRows:
    """The rows that may be chosen: training rows not cleaned yet."""
    if isinstance(train, ClusterRows):
        return train.uncleaned()
    if isinstance(train, LocalRows):
        m = ~train.clean
        return LocalRows(train.ids[m], train.x[m], train.y[m], train.clean[m], train.gamma)
    return train.where("split = 'train' and not is_clean")


def uplift_influence(train: DataFrame, w: np.ndarray, v: np.ndarray, gamma: float, b: int | None = None) -> DataFrame:
    return scored(pool(train), lambda x, y: uplift_scores(x, y, w, v, gamma), b)


def deletion_influence(train: DataFrame, w, v, gamma: float = 1.0, convention: str = "printed") -> DataFrame:
    return scored(pool(train), lambda x, y: deletion_scores(x, y, w, v, gamma, convention))


def label_gradient_influence(train: DataFrame, w, v, reduce: str = "min") -> DataFrame:
    """``reduce``: rank by the smallest entry, or by the negated l2 norm or largest size."""

    def fn(x, y):
        s = label_gradient_scores(x, w, v)
        return s if reduce == "min" else -np.sqrt((s**2).sum(axis=1)) if reduce == "l2" else -np.abs(s).max(axis=1)

    return scored(pool(train), fn)


def select_top(scores: DataFrame, b: int) -> DataFrame:
    """The b rows of smallest score, ties by row_id; one heap a task, then one merge."""
    return scores.orderBy("best_score", "row_id").limit(b)


def scores_long(scores: DataFrame) -> DataFrame:
    return scores.select("row_id", F.posexplode("scores").alias("class", "score"))


def sign_report(scores: DataFrame) -> DataFrame:
    """Rows whose cleaning is estimated to lower the validation loss, and the others."""
    return scores.groupBy((F.col("best_score") < 0).alias("is_harmful")).agg(F.count("*").alias("n"))


def exact_influence(rows, val_loss: Callable[[np.ndarray], float], fit: Callable, ids: list[int], classes: list[int]) -> np.ndarray:
    """N times the change of the validation loss when one row is cleaned and the model refitted; small data."""
    base = val_loss(fit(rows))
    out = []
    for i, c in zip(ids, classes):
        at = int(np.flatnonzero(rows.ids == i)[0])
        y, clean = rows.y.copy(), rows.clean.copy()
        y[at], clean[at] = np.eye(y.shape[1])[c], True
        edited = type(rows)(rows.ids, rows.x, y, clean, rows.gamma)
        out.append(rows.size * (val_loss(fit(edited)) - base))
    return np.array(out)
