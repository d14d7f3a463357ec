"""Other rankers. Each gives SCORES rows, so that ``select_top`` picks from any of them.

The two noise detectors and the bi-level method are reconstructions: only their roles
are given, not their formulas.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tidelabel.config import CleanConfig
from tidelabel.functions.rand import uniform, uniform_of
from tidelabel.operators.core import LocalRows, influence_vector, loss_of, softmax, train_newton, validation_gradient
from tidelabel.operators.influence import LocalScores, pool, scored, uplift_scores
from tidelabel.operators.measures import confusions


def _by_probability(fn):
    def ranked(train: DataFrame, w: np.ndarray) -> DataFrame:
        return scored(pool(train), lambda x, y: fn(softmax(x @ w.T)))

    return ranked


least_confidence = _by_probability(lambda p: -(1 - p.max(axis=1)))
entropy = _by_probability(lambda p: (p * np.log(np.maximum(p, 1e-300))).sum(axis=1))
margin = _by_probability(lambda p: (s := np.sort(p, axis=1))[:, -1] - s[:, -2])


def random_order(train: DataFrame | LocalRows, seed: str = "random") -> DataFrame | LocalScores:
    if isinstance(train, LocalRows):
        ids = train.ids[~train.clean]
        return LocalScores(ids, np.array([uniform_of(seed, i) for i in ids.tolist()]).reshape(-1, 1))
    return pool(train).select("row_id", F.lit(0).alias("best_class"), uniform(seed, "row_id").alias("best_score"), F.array(uniform(seed, "row_id")).alias("scores"))


def harden(weak):
    """Nearest hard label of probability vectors (ties: the lowest class)."""
    return np.eye(weak.shape[1])[weak.argmax(axis=1)]


def detector_a(train: DataFrame, rows: LocalRows, w: np.ndarray, cfg: CleanConfig, epochs: int = 6) -> DataFrame:
    """Rows whose loss stays above the epoch's mean while the learning rate goes up and down, largest first."""
    models, now = [], w.copy()
    for e in range(epochs):
        rate = cfg.rate * (1 - (e % 3) / 3)
        s, n = rows.total(lambda x, y, g: ((softmax(x @ now.T) - y) * g[:, None]).T @ x)
        now = now - rate * (np.reshape(s, now.shape) / max(n, 1) + cfg.lam * now)
        mean, _ = rows.total(lambda x, y, g: np.array([loss_of(x, y, np.ones(len(x)), now).sum()]))
        models.append((now, float(np.ravel(mean)[0]) / max(rows.size, 1)))
    return scored(pool(train), lambda x, y: -np.mean([loss_of(x, y, np.ones(len(x)), m) - mean for m, mean in models], axis=0))


def detector_b(train: DataFrame, val, w: np.ndarray, v: np.ndarray) -> DataFrame:
    """Hard labels: chance that the label is wrong, from confusions on trusted rows, times the gain of the best other class."""
    table = 1 + confusions(val, w)[1].T
    given = table / table.sum(axis=1, keepdims=True)  # P(truth | predicted)

    def fn(x, y):
        hard = harden(y)
        wrong = 1 - (given[(x @ w.T).argmax(axis=1)] * hard).sum(axis=1)
        gain = uplift_scores(x, hard, w, v, 1.0)
        return wrong[:, None] * np.minimum(gain, 0.0)

    return scored(pool(train), fn)


def to_simplex(y: np.ndarray) -> np.ndarray:
    """Nearest probability vectors."""
    u = -np.sort(-y, axis=1)
    c = np.cumsum(u, axis=1) - 1
    k = np.arange(1, y.shape[1] + 1)
    last = (u - c / k > 0).sum(axis=1)
    shift = c[np.arange(len(y)), last - 1] / last
    return np.maximum(y - shift[:, None], 0)


def bilevel(rows: LocalRows, val, cfg: CleanConfig, outer: int = 5, rate: float = 50.0, pull: float = 0.1) -> tuple[np.ndarray, np.ndarray]:
    """(L1 distance moved, suggested class) of each row: soft labels are moved to lower the validation loss of the refit.

    gamma is 1; the soft labels are on the driver, so the training rows must be too. Each outer step refits, solves for v and moves the labels against the
    implicit gradient, with a pull towards the given labels, back onto the simplex.
    """
    y = rows.y.copy()
    cfg = cfg.but(gamma=1.0)
    w = None
    for _ in range(outer):
        now = LocalRows(rows.ids, rows.x, y, np.ones(rows.size, bool), 1.0)
        w = train_newton(now, cfg, w)
        v = influence_vector(now, validation_gradient(val, w), w, cfg)
        s = rows.x @ v.T
        y = to_simplex(y - rate * (-s) / rows.size * 1.0 - pull * (y - rows.y))
    return np.abs(y - rows.y).sum(axis=1), y.argmax(axis=1)
